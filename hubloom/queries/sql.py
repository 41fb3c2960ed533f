"""The same graphs, searches and aggregates as DuckDB SQL: common table expressions that queries' oracles are put together from."""

from __future__ import annotations


def part_flow(m: int = 1, v_card: int = 10, e_card: int = 10) -> str:
    return f"""
    lines AS (SELECT l_orderkey AS o, l_partkey AS p, CAST(SUM(l_quantity) AS BIGINT) AS q FROM lineitem WHERE l_orderkey % {m} = 0 GROUP BY 1, 2),
    steps AS (SELECT o, p AS src, LEAD(p) OVER (PARTITION BY o ORDER BY p) AS tgt, LEAD(q) OVER (PARTITION BY o ORDER BY p) AS q FROM lines),
    e AS (SELECT src, tgt, MIN(o) % {e_card} AS e_grp, CAST(SUM(q) AS BIGINT) AS e_mr, COUNT(*) AS n_steps FROM steps WHERE tgt IS NOT NULL GROUP BY 1, 2),
    v AS (SELECT p_partkey AS vid, p_partkey % {v_card} AS v_grp, CAST(p_size AS BIGINT) AS v_mr, p_brand FROM part)"""


def part_flow_dense(v_card: int = 10, e_card: int = 10) -> str:
    return f"""
    lines AS (SELECT l_orderkey AS o, l_partkey AS p, CAST(SUM(l_quantity) AS BIGINT) AS q FROM lineitem GROUP BY 1, 2),
    e AS (SELECT a.p AS src, b.p AS tgt, MIN(a.o) % {e_card} AS e_grp, CAST(SUM(b.q) AS BIGINT) AS e_mr, COUNT(*) AS n_steps FROM lines a JOIN lines b ON a.o = b.o AND a.p < b.p GROUP BY 1, 2),
    v AS (SELECT p_partkey AS vid, p_partkey % {v_card} AS v_grp, CAST(p_size AS BIGINT) AS v_mr, p_brand FROM part)"""


def order_chain(v_card: int = 10) -> str:
    return f"""
    lines AS (SELECT l_orderkey AS o, l_partkey AS p, CAST(SUM(l_quantity) AS BIGINT) AS q, MIN(l_returnflag || l_linestatus) AS f FROM lineitem GROUP BY 1, 2),
    steps AS (SELECT o AS src, LEAD(o) OVER (PARTITION BY p ORDER BY o) AS tgt, LEAD(q) OVER (PARTITION BY p ORDER BY o) AS q, LEAD(f) OVER (PARTITION BY p ORDER BY o) AS f FROM lines),
    e AS (SELECT src, tgt, CAST((instr('ANR', MIN(f)[1]) - 1) * 2 + instr('FO', MIN(f)[2]) - 1 AS BIGINT) AS e_grp, CAST(SUM(q) AS BIGINT) AS e_mr FROM steps WHERE tgt IS NOT NULL GROUP BY 1, 2),
    v AS (SELECT o_orderkey AS vid, o_orderkey % {v_card} AS v_grp, CAST(FLOOR(o_totalprice) AS BIGINT) AS v_mr, o_orderpriority FROM orders)"""


def contact(max_gap_s: int | None = None, freq_scope: str = "kept") -> str:
    near = "TRUE" if max_gap_s is None else f"gap_us <= {max_gap_s * 1_000_000}"
    counted = "all_steps" if freq_scope == "all" else "near_steps"
    keep = "WHERE (src, tgt) IN (SELECT (src, tgt) FROM near_steps)" if freq_scope == "all" and max_gap_s is not None else ""
    return f"""
    seq AS (SELECT user_id AS src, LEAD(user_id) OVER w AS tgt, LEAD(event_type) OVER w AS event_type, epoch_us(LEAD(ts) OVER w) - epoch_us(ts) AS gap_us FROM events WINDOW w AS (ORDER BY ts, event_id)),
    all_steps AS (SELECT * FROM seq WHERE tgt IS NOT NULL AND src <> tgt),
    near_steps AS (SELECT * FROM all_steps WHERE {near}),
    kinds AS (SELECT src, tgt, event_type, COUNT(*) AS n FROM {counted} GROUP BY 1, 2, 3),
    ranked AS (SELECT *, ROW_NUMBER() OVER (PARTITION BY src, tgt ORDER BY n DESC, event_type) AS rn, CAST(SUM(n) OVER (PARTITION BY src, tgt) AS BIGINT) AS freq FROM kinds),
    e AS (SELECT src, tgt, freq, event_type AS rel, CASE WHEN freq >= 3 THEN 'HIGH' WHEN freq = 2 THEN 'MIDDLE' ELSE 'LOW' END AS closeness, freq AS e_mr, freq % 3 AS e_grp
          FROM (SELECT * FROM ranked WHERE rn = 1) {keep}),
    v AS (SELECT user_id AS vid, COUNT(*) AS n_events, CAST(SUM(FLOOR(value)) AS BIGINT) AS total_value, user_id % 10 AS v_grp, COUNT(*) AS v_mr FROM events GROUP BY user_id)"""


def mutual(max_gap_s: int | None = None) -> str:
    return contact(max_gap_s).replace("    e AS (", "    e0 AS (") + """,
    e AS (SELECT a.* FROM e0 a WHERE EXISTS (SELECT 1 FROM e0 b WHERE b.src = a.tgt AND b.tgt = a.src))"""


LAYER = 1_000_000_000_000

SUPPLY = f"""
    arcs AS (
      SELECT o_custkey + {LAYER} AS src, o_orderkey + 2 * {LAYER} AS tgt FROM orders
      UNION ALL SELECT l_orderkey + 2 * {LAYER}, l_partkey + 3 * {LAYER} FROM lineitem
      UNION ALL SELECT l_partkey + 3 * {LAYER}, l_suppkey + 4 * {LAYER} FROM lineitem
      UNION ALL SELECT s_suppkey + 4 * {LAYER}, s_nationkey + 5 * {LAYER} FROM supplier
      UNION ALL SELECT n_nationkey + 5 * {LAYER}, n_regionkey + 6 * {LAYER} FROM nation),
    e AS (SELECT src, tgt, COUNT(*) AS e_mr, tgt // {LAYER} AS e_grp FROM arcs GROUP BY 1, 2)"""

DIALOGUE = """
    turns AS (SELECT conv_id, turn, LEAD(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations),
    e AS (SELECT conv_id * 1000 + turn AS src, conv_id * 1000 + nxt AS tgt, CAST(0 AS BIGINT) AS e_grp, CAST(1 AS BIGINT) AS e_mr FROM turns WHERE nxt IS NOT NULL),
    v AS (SELECT conv_id * 1000 + turn AS vid FROM conversations)"""


def synthetic(n: int, degree: int, v_card: int = 10, e_card: int = 10, seed: int = 1, numbers: str | None = None) -> str:
    draw = lambda tag: f"CAST(('0x' || substr(md5('{seed}{tag}' || id::VARCHAR), 1, 8)) AS BIGINT)"
    return f"""
    drawn AS (SELECT id, {draw("a")} % {n} AS a, {draw("b")} % {n} AS b FROM {numbers or f"range({n * degree}) t(id)"}),
    e AS (SELECT LEAST(a, b) AS src, GREATEST(a, b) AS tgt, MIN(id) % {e_card} AS e_grp, CAST(SUM(id % 100) AS BIGINT) AS e_mr FROM drawn WHERE a <> b GROUP BY 1, 2),
    v AS (SELECT id AS vid, id % {v_card} AS v_grp, id % 97 AS v_mr FROM range({n}) t(id))"""


DEGREES = """
    deg AS (SELECT vid, COUNT(*) AS degree, CAST(SUM(o) AS BIGINT) AS out_degree, CAST(SUM(1 - o) AS BIGINT) AS in_degree
            FROM (SELECT src AS vid, 1 AS o FROM e UNION ALL SELECT tgt, 0 FROM e) GROUP BY vid)"""


def top_hubs(k: int, column: str = "degree") -> str:
    return f"""{DEGREES},
    h AS (SELECT CAST(ROW_NUMBER() OVER (ORDER BY {column} DESC, vid) - 1 AS INTEGER) AS i, vid FROM deg ORDER BY {column} DESC, vid LIMIT {k})"""


REACH = """
    fwd(i, vid) AS (SELECT i, vid FROM h UNION SELECT f.i, e.tgt FROM fwd f JOIN e ON e.src = f.vid),
    bwd(i, vid) AS (SELECT i, vid FROM h UNION SELECT b.i, e.src FROM bwd b JOIN e ON e.tgt = b.vid)"""


def reach_hops(h: int) -> str:
    return f"""
    fwd_d(i, vid, d) AS (SELECT i, vid, 0 FROM h UNION SELECT f.i, e.tgt, f.d + 1 FROM fwd_d f JOIN e ON e.src = f.vid WHERE f.d < {h}),
    bwd_d(i, vid, d) AS (SELECT i, vid, 0 FROM h UNION SELECT b.i, e.src, b.d + 1 FROM bwd_d b JOIN e ON e.tgt = b.vid WHERE b.d < {h}),
    fwd AS (SELECT i, vid, MIN(d) AS d FROM fwd_d GROUP BY 1, 2),
    bwd AS (SELECT i, vid, MIN(d) AS d FROM bwd_d GROUP BY 1, 2)"""


MEMBERS = """
    mem AS (SELECT hx.vid AS x, hy.vid AS y, f.vid FROM fwd f JOIN bwd b ON f.vid = b.vid AND f.i <> b.i JOIN h hx ON hx.i = f.i JOIN h hy ON hy.i = b.i)"""

EDGE_MEMBERS = """
    emem AS (SELECT hx.vid AS x, hy.vid AS y, e.* FROM e JOIN fwd f ON f.vid = e.src JOIN bwd b ON b.vid = e.tgt AND f.i <> b.i JOIN h hx ON hx.i = f.i JOIN h hy ON hy.i = b.i)"""

EDGE_MEMBERS_ENDS = """
    emem AS (SELECT a.x, a.y, e.* FROM e JOIN mem a ON a.vid = e.src JOIN mem b ON b.vid = e.tgt AND a.x = b.x AND a.y = b.y)"""

TAGS = """
    tags AS (SELECT COALESCE(f.vid, b.vid) AS vid, COALESCE(f.s, 0) AS s0, COALESCE(b.r, 0) AS r0
             FROM (SELECT vid, CAST(SUM(1::BIGINT << i) AS BIGINT) AS s FROM fwd GROUP BY vid) f
             FULL JOIN (SELECT vid, CAST(SUM(1::BIGINT << i) AS BIGINT) AS r FROM bwd GROUP BY vid) b ON f.vid = b.vid)"""


def distances(cap: int) -> str:
    """Hop distances from hubs; ``cap`` ends the search (a bound above any distance changes nothing)."""
    return f"""
    walk(i, vid, d) AS (SELECT i, vid, 0 FROM h UNION SELECT w.i, e.tgt, w.d + 1 FROM walk w JOIN e ON e.src = w.vid WHERE w.d < {cap}),
    dist AS (SELECT h.vid AS x, w.vid, MIN(w.d) AS d FROM walk w JOIN h ON h.i = w.i GROUP BY 1, 2)"""


PATHS = """
    back(x, y, node, d, path) AS (
      SELECT dist.x, dist.vid, dist.vid, dist.d, CAST(dist.vid AS VARCHAR) FROM dist JOIN h ON h.vid = dist.vid WHERE dist.x <> dist.vid
      UNION ALL
      SELECT b.x, b.y, n.src, b.d - 1, CAST(n.src AS VARCHAR) || '>' || b.path
      FROM back b JOIN (SELECT q.x, e.tgt, MIN(e.src) AS src, q.d + 1 AS d FROM e JOIN dist q ON q.vid = e.src GROUP BY q.x, e.tgt, q.d) n
        ON n.x = b.x AND n.tgt = b.node AND n.d = b.d WHERE b.d > 0)"""


def closeness_all(cap: int) -> str:
    return f"""
    aw(src, vid, d) AS (SELECT vid, vid, 0 FROM v UNION SELECT w.src, e.tgt, w.d + 1 FROM aw w JOIN e ON e.src = w.vid WHERE w.d < {cap}),
    apsp AS (SELECT src, vid AS tgt, MIN(d) AS d FROM aw GROUP BY 1, 2),
    close AS (SELECT src AS vid, CASE WHEN SUM(d) > 0 THEN ROUND((COUNT(*) - 1) / SUM(d), 9) ELSE 0.0 END AS closeness FROM apsp GROUP BY src)"""


def sql(*parts: str, final: str) -> str:
    return "WITH RECURSIVE " + ",".join(parts) + "\n" + final
