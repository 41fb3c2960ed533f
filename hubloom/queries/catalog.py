"""Every method, variant, baseline, measure and workload as a query on the given tables, with its SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg
from hubloom.functions.bits import cardinality
from hubloom.operators import cycles, measures, reach_index, structure
from hubloom.operators import hubs as hub_ops
from hubloom.operators import scope as scope_ops
from hubloom.operators.graph import PropertyGraph, group_cardinality
from hubloom.operators.pair_aggregate import aggregate_pairs, combine_equal_tags, lift_edges, tag_groups
from hubloom.operators.runtime import saved
from hubloom.operators.tags import TagCache, between_hops_total, hub_pairs, live, membership, tag_edges, tag_vertices
from hubloom.plans import query as q
from hubloom.plans.sharing import add_operations, plan_sharing
from hubloom.plans.text import parse_query
from hubloom.queries import sql as S
from hubloom.sources import graphs
from hubloom.sources.generator import drawn_from
from hubloom.sources.tables import read_table
from hubloom.streaming.contacts import as_of, contact_windows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

_graphs: dict[tuple, PropertyGraph] = {}
_tags = TagCache()
_hubs: dict[tuple, list[int]] = {}


def query(name: str, oracle: str | None = None):  # noqa: ANN201
    def add(fn: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[name] = fn
        if oracle is not None:
            SQL[name] = oracle
        return fn

    return add


def graph(spark: SparkSession, sf_dir: str, kind: str, **options: object) -> PropertyGraph:
    """A derived graph, written once a session: several queries explore the same one."""
    key = (spark.sparkContext.applicationId, sf_dir, kind, *sorted(options.items(), key=str))
    if key not in _graphs:
        make = getattr(graphs, kind)
        _graphs[key] = (make(spark, **options) if kind == "synthetic_dag" else make(spark, sf_dir, **options)).saved()
    return _graphs[key]


def hubs_of(g: PropertyGraph, k: int) -> list[int]:
    key = (id(g), k)
    if key not in _hubs:
        _hubs[key] = hub_ops.top_degree(g, k)
    return _hubs[key]


def flow(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return graph(spark, sf_dir, "part_flow", m=1)


def near(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """The contacts within ten seconds, counted over all hand-offs; cyclic."""
    return graph(spark, sf_dir, "contact_graph", max_gap_s=10, freq_scope="all")


def ids(spark: SparkSession, vids: list[int]) -> DataFrame:
    return spark.createDataFrame(list(enumerate(map(int, vids))), "rank int, vid long")


FLOW, NEAR = S.part_flow(), S.contact(10, "all")
K = 5
FLOW_REACH = [FLOW, S.top_hubs(K), S.REACH]
NEAR_REACH = [NEAR, S.top_hubs(3), S.REACH]

# -- derived graphs ---------------------------------------------------------------
query("graph_part_flow_vertices", S.sql(FLOW, final="SELECT * FROM v"))(lambda s, d: flow(s, d).vertices)
query("graph_part_flow_edges", S.sql(FLOW, final="SELECT * FROM e"))(lambda s, d: flow(s, d).edges)
query("graph_part_flow_dense_edges", S.sql(S.part_flow_dense(), final="SELECT * FROM e"))(lambda s, d: graphs.part_flow_dense(s, d).edges)
query("graph_order_chain_edges", S.sql(S.order_chain(), final="SELECT * FROM e"))(lambda s, d: graphs.order_chain(s, d).edges)
query("graph_contact_edges", S.sql(S.contact(), final="SELECT * FROM e"))(lambda s, d: graphs.contact_graph(s, d).edges)
query("graph_contact_near_edges", S.sql(NEAR, final="SELECT * FROM e"))(lambda s, d: near(s, d).edges)
query("graph_contact_vertices", S.sql(S.contact(), final="SELECT * FROM v"))(lambda s, d: graphs.contact_graph(s, d).vertices.drop("first_ts"))
query("graph_mutual_edges", S.sql(S.mutual(180), final="SELECT * FROM e"))(lambda s, d: graphs.mutual_contact(s, d, 180).edges)
query("graph_supply_layers_edges", S.sql(S.SUPPLY, final="SELECT * FROM e"))(lambda s, d: graphs.supply_layers(s, d).edges)
query("graph_dialogue_edges", S.sql(S.DIALOGUE, final="SELECT * FROM e"))(lambda s, d: graphs.dialogue_flow(s, d).edges)
query(
    "graph_page_links",
    "SELECT page_id, href, COUNT(*) AS n FROM (SELECT page_id, UNNEST(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) GROUP BY 1, 2",
)(graphs.page_links)
query("graph_synthetic_edges", S.sql(S.synthetic(2000, 8, numbers="(SELECT o_orderkey AS id FROM orders)"), final="SELECT * FROM e"))(  # an edge drawn for each order
    lambda s, d: graphs.synthetic_dag(s, 2000, 8, numbers=read_table(s, d, "orders").select(F.col("o_orderkey").alias("id"))).edges
)
query(
    "graph_word_succession",
    """WITH w AS (SELECT lang, list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') AS w FROM documents),
       p AS (SELECT lang, w[i] AS a, w[i + 1] AS b FROM w, UNNEST(range(1, len(w))) t(i)) SELECT lang, a, b, COUNT(*) AS n FROM p GROUP BY 1, 2, 3""",
)(graphs.word_succession)

# -- measures ------------------------------------------------------------------------
query(
    "graph_stats",
    S.sql(FLOW, final="SELECT (SELECT COUNT(*) FROM v) AS n_vertices, (SELECT COUNT(*) FROM e) AS n_edges, ROUND((SELECT COUNT(*) FROM e) / (SELECT COUNT(*) FROM v), 6) AS mean_degree"),
)(lambda s, d: flow(s, d).stats())
query(
    "group_cardinality",
    S.sql(FLOW, final="SELECT v_groups, e_groups, v_groups + e_groups AS groups FROM (SELECT (SELECT COUNT(DISTINCT v_grp) FROM v) AS v_groups, (SELECT COUNT(DISTINCT e_grp) FROM e) AS e_groups)"),
)(lambda s, d: group_cardinality(flow(s, d)))

# -- hubs ------------------------------------------------------------------------------
for _column, _direction in (("degree", "total"), ("in_degree", "in"), ("out_degree", "out")):
    query(f"hubs_top_{_column}", S.sql(FLOW, S.top_hubs(K, _column), final="SELECT i AS rank, vid FROM h"))(
        lambda s, d, way=_direction: ids(s, hub_ops.top_degree(flow(s, d), K, way))
    )
query(
    "hubs_by_attribute", S.sql(FLOW, final="SELECT CAST(ROW_NUMBER() OVER (ORDER BY vid) - 1 AS INTEGER) AS rank, vid FROM v WHERE v_mr >= 50 ORDER BY vid LIMIT 20")
)(lambda s, d: ids(s, hub_ops.by_attribute(flow(s, d), "v_mr >= 50", 20)))
query(
    "hubs_predicate_topk",
    S.sql(FLOW, S.DEGREES, final="SELECT CAST(ROW_NUMBER() OVER (ORDER BY degree DESC, vid) - 1 AS INTEGER) AS rank, vid FROM (SELECT deg.* FROM deg JOIN v USING (vid) WHERE v_grp = 7) ORDER BY degree DESC, vid LIMIT 10"),
)(lambda s, d: ids(s, hub_ops.top_degree(flow(s, d), 10, where="v_grp = 7")))
CLOSE = [NEAR, S.closeness_all(40)]
query("closeness_exact", S.sql(*CLOSE, final="SELECT vid, closeness FROM close"))(lambda s, d: hub_ops.closeness(near(s, d)))
_top = "SELECT CAST(ROW_NUMBER() OVER (ORDER BY closeness {0}, vid) - 1 AS INTEGER) AS rank, vid FROM {1} ORDER BY closeness {0}, vid LIMIT 10"
query("hubs_top_closeness_dynamic", S.sql(*CLOSE, final=_top.format("DESC", "close")))(lambda s, d: ids(s, hub_ops.top_by(hub_ops.closeness(near(s, d)), "closeness", 10)))
query("hubs_lowest_closeness", S.sql(*CLOSE, final=_top.format("ASC", "close")))(lambda s, d: ids(s, hub_ops.top_by(hub_ops.closeness(near(s, d)), "closeness", 10, ascending=True)))


@query("hubs_top_closeness_static", S.sql(*CLOSE, final=_top.format("DESC", "(SELECT * FROM close JOIN v USING (vid) WHERE v_grp = 3)")))
def _static(spark: SparkSession, sf_dir: str) -> DataFrame:
    from hubloom.operators.runtime import shared_root

    g = near(spark, sf_dir)
    path = f"{shared_root(spark)}/hubloom-measure-{abs(hash((spark.sparkContext.applicationId, sf_dir)))}"
    hub_ops.build_measure_index(hub_ops.closeness(g).join(g.vertices.select("vid", "v_grp"), "vid"), "closeness", path)
    return ids(spark, hub_ops.lookup_measure(spark, path, "closeness", 10, where="v_grp = 3"))


query(
    "hubs_closeness_apsp",
    S.sql(
        NEAR, S.closeness_all(40),
        """ part AS (SELECT vid FROM v WHERE v_grp IN (1, 2, 3)),
        inner_close AS (SELECT src AS vid, CASE WHEN SUM(d) > 0 THEN ROUND((COUNT(*) - 1) / SUM(d), 9) ELSE 0.0 END AS closeness
                        FROM apsp WHERE src IN (SELECT vid FROM part) AND tgt IN (SELECT vid FROM part) GROUP BY src)""",
        final="SELECT vid, closeness FROM inner_close",
    ),
)(lambda s, d: hub_ops.closeness_from_distances(hub_ops.all_distances(near(s, d)), near(s, d).vertices.where("v_grp in (1, 2, 3)")))
query(
    "hubs_closeness_pivots",
    S.sql(
        NEAR,
        " h AS (SELECT CAST(ROW_NUMBER() OVER (ORDER BY md5(vid::VARCHAR), vid) - 1 AS INTEGER) AS i, vid FROM v ORDER BY md5(vid::VARCHAR), vid LIMIT 16)",
        S.reach_hops(40),
        final="SELECT vid, ROUND(COUNT(*) / SUM(d), 9) AS closeness FROM bwd WHERE d > 0 GROUP BY vid",
    ),
)(lambda s, d: hub_ops.pivot_closeness(near(s, d), 16))
query(
    "measure_pagerank",
    S.sql(
        NEAR,
        """ outs AS (SELECT src, COUNT(*) AS deg FROM e GROUP BY src)""",
        *[
            f" p{i} AS (SELECT v.vid, 0.15 + 0.85 * COALESCE(g.got, 0.0) AS rank FROM v LEFT JOIN (SELECT e.tgt, SUM(p.rank / outs.deg) AS got FROM e JOIN outs USING (src) JOIN {'(SELECT vid, 1.0::DOUBLE AS rank FROM v)' if i == 1 else f'p{i - 1}'} p ON p.vid = e.src GROUP BY e.tgt) g ON g.tgt = v.vid)"
            for i in range(1, 6)
        ],
        final="SELECT vid, ROUND(rank, 6) AS rank FROM p5",
    ),
)(lambda s, d: hub_ops.pagerank(near(s, d), 5).select("vid", F.round("rank", 6).alias("rank")))

# -- scopes --------------------------------------------------------------------------------
for _name, _gap in (("scope_paths_between", 180), ("scope_paths_far", 90)):
    query(
        _name,
        S.sql(
            S.mutual(_gap),
            " h AS (SELECT 0 AS i, 0::BIGINT AS vid)", S.distances(30).replace("walk", "wx").replace("dist AS", "dx AS"),
            """ wy(vid, d) AS (SELECT 149::BIGINT, 0 UNION SELECT e.src, w.d + 1 FROM wy w JOIN e ON e.tgt = w.vid WHERE w.d < 30),
            dy AS (SELECT vid, MIN(d) AS d FROM wy GROUP BY vid),
            bound AS (SELECT GREATEST(4, (SELECT MIN(d) FROM dy WHERE vid = 0)) AS b)""",
            final="SELECT e.src, e.tgt FROM e JOIN dx ON dx.vid = e.src JOIN dy ON dy.vid = e.tgt, bound WHERE dx.d + 1 + dy.d <= bound.b",
        ),
    )(lambda s, d, gap=_gap: scope_ops.paths_between(graph(s, d, "mutual_contact", max_gap_s=gap), 0, 149, 4).edges.select("src", "tgt"))
query("scope_attribute", S.sql(FLOW, final="SELECT e.src, e.tgt FROM e JOIN v a ON a.vid = e.src JOIN v b ON b.vid = e.tgt WHERE a.v_grp < 4 AND b.v_grp < 4"))(
    lambda s, d: scope_ops.attribute_subgraph(flow(s, d), "v_grp < 4").edges.select("src", "tgt")
)

# -- reachability and tags -------------------------------------------------------------------
TAG_SQL = S.sql(*FLOW_REACH, S.TAGS, final="SELECT vid, s0, r0 FROM tags")
NEAR_TAG_SQL = S.sql(*NEAR_REACH, S.TAGS, final="SELECT vid, s0, r0 FROM tags")
query("reach_tags_vertices", TAG_SQL)(lambda s, d: tag_vertices(flow(s, d), hubs_of(flow(s, d), K)))
query("reach_tags_joins", TAG_SQL)(lambda s, d: tag_vertices(flow(s, d), hubs_of(flow(s, d), K), local_edges=0))
query("reach_tags_contact", NEAR_TAG_SQL)(lambda s, d: tag_vertices(near(s, d), hubs_of(near(s, d), 3)))
query("reach_hops_tags", S.sql(NEAR, S.top_hubs(3), S.reach_hops(3), S.TAGS, final="SELECT vid, s0, r0 FROM tags"))(lambda s, d: tag_vertices(near(s, d), hubs_of(near(s, d), 3), 3))
query(
    "reach_hops_total",
    S.sql(NEAR, S.top_hubs(3), S.reach_hops(4), final="SELECT CAST(f.i AS INTEGER) AS x, CAST(b.i AS INTEGER) AS y, f.vid FROM fwd f JOIN bwd b ON f.vid = b.vid WHERE f.i <> b.i AND f.d + b.d <= 4"),
)(lambda s, d: between_hops_total(near(s, d), hubs_of(near(s, d), 3), 4))


def _flow_tags(s: SparkSession, d: str, k: int = K) -> tuple[PropertyGraph, list[int], DataFrame]:
    g = flow(s, d)
    return g, hubs_of(g, k), _tags.vertices(g, hubs_of(g, k))


@query("reach_tags_edges", S.sql(*FLOW_REACH, S.TAGS, final="SELECT e.src, e.tgt, a.s0, b.r0 FROM e JOIN tags a ON a.vid = e.src JOIN tags b ON b.vid = e.tgt"))
def _edge_tags(s: SparkSession, d: str) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d)
    return tag_edges(g, tags, len(hubs)).select("src", "tgt", "s0", "r0")


@query("reach_tag_cardinality", S.sql(*FLOW_REACH, S.TAGS, final="SELECT vid, CAST(bit_count(s0) AS BIGINT) * CAST(bit_count(r0) AS BIGINT) AS cardinality FROM tags"))
def _card(s: SparkSession, d: str) -> DataFrame:
    return _flow_tags(s, d)[2].select("vid", cardinality(1).alias("cardinality"))


@query("reach_hub_pairs", S.sql(*FLOW_REACH, final="SELECT f.i AS x, h.i AS y FROM fwd f JOIN h ON h.vid = f.vid WHERE f.i <> h.i"))
def _pairs(s: SparkSession, d: str) -> DataFrame:
    _, hubs, tags = _flow_tags(s, d)
    return hub_pairs(tags, hubs)


@query("reach_membership", S.sql(*FLOW_REACH, final="SELECT f.vid, f.i AS x, b.i AS y FROM fwd f JOIN bwd b ON f.vid = b.vid WHERE f.i <> b.i"))
def _membership(s: SparkSession, d: str) -> DataFrame:
    _, hubs, tags = _flow_tags(s, d)
    return membership(tags, len(hubs), "vid")


query("reach_index_tc", S.sql(NEAR, " tc(src, tgt) AS (SELECT vid, vid FROM v UNION SELECT t.src, e.tgt FROM tc t JOIN e ON e.src = t.tgt)", final="SELECT src, tgt FROM tc"))(
    lambda s, d: reach_index.transitive_closure(near(s, d))
)
query("reach_recursive_hops", S.sql(NEAR, S.top_hubs(3), S.reach_hops(3), final="SELECT h.vid AS hub, f.vid FROM fwd f JOIN h ON h.i = f.i"))(
    lambda s, d: reach_index.closure_by_recursion(near(s, d), hubs_of(near(s, d), 3), 3)
)
query("extract_index_tc", NEAR_TAG_SQL)(lambda s, d: reach_index.tags_from_closure(reach_index.condensed_closure(near(s, d)), hubs_of(near(s, d), 3)))
CONTACT_TAG_SQL = S.sql(S.contact(), S.top_hubs(3), S.REACH, S.TAGS, final="SELECT vid, s0, r0 FROM tags")
contacts = lambda s, d: graph(s, d, "contact_graph")
for _m in reach_index.METHODS:
    query(f"extract_{_m}", TAG_SQL if _m != "tree_interval" else CONTACT_TAG_SQL)(
        lambda s, d, m=_m: reach_index.extract(*((flow(s, d), hubs_of(flow(s, d), K)) if m != "tree_interval" else (contacts(s, d), hubs_of(contacts(s, d), 3))), m)
    )

# -- cycles --------------------------------------------------------------------------------------
SCC = [
    NEAR,
    " tc(src, tgt) AS (SELECT vid, vid FROM v UNION SELECT t.src, e.tgt FROM tc t JOIN e ON e.src = t.tgt)",
    " comp AS (SELECT a.src AS vid, MIN(a.tgt) AS comp FROM tc a JOIN tc b ON a.src = b.tgt AND a.tgt = b.src GROUP BY a.src)",
]
query("scc_components", S.sql(*SCC, final="SELECT vid, comp FROM comp"))(lambda s, d: cycles.scc(near(s, d)))
query("scc_components_joins", S.sql(*SCC, final="SELECT vid, comp FROM comp"))(lambda s, d: cycles.scc(near(s, d), local_edges=0))
query("scc_condensed_edges", S.sql(*SCC, final="SELECT a.comp AS src, b.comp AS tgt, COUNT(*) AS e_mr FROM e JOIN comp a ON a.vid = e.src JOIN comp b ON b.vid = e.tgt WHERE a.comp <> b.comp GROUP BY 1, 2"))(
    lambda s, d: cycles.condense(near(s, d), saved(cycles.scc(near(s, d)), "comp"), ["v_grp"], [Agg("sum", "v_mr")])[0].edges
)
query("scc_preaggregate", S.sql(*SCC, final="SELECT comp, v_grp, COUNT(*) AS elements, CAST(SUM(v_mr) AS BIGINT) AS sum_v_mr FROM comp JOIN v USING (vid) GROUP BY 1, 2"))(
    lambda s, d: cycles.condense(near(s, d), saved(cycles.scc(near(s, d)), "comp"), ["v_grp"], [Agg("sum", "v_mr")])[1]
)


@query("topo_levels", S.sql(FLOW, " lv(vid, d) AS (SELECT vid, 0 FROM v UNION SELECT e.tgt, l.d + 1 FROM lv l JOIN e ON e.src = l.vid)", final="SELECT vid, CAST(MAX(d) AS BIGINT) AS level FROM lv GROUP BY vid"))
def _levels(s: SparkSession, d: str) -> DataFrame:
    return cycles.topo_levels(flow(s, d))


# -- summaries -----------------------------------------------------------------------------------------
V_MEM, E_MEM = [*FLOW_REACH, S.MEMBERS], [*FLOW_REACH, S.EDGE_MEMBERS]


def _v_agg(s: SparkSession, d: str, aggs: list[Agg], dims: list[str], method: str = "sharing", k: int = K, **options: object) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d, k)
    return aggregate_pairs(g.vertices.join(tags, "vid"), hubs, dims, aggs, method, **options)


def _e_agg(s: SparkSession, d: str, aggs: list[Agg], method: str = "sharing", k: int = K, **options: object) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d, k)
    lifted = PropertyGraph(g.vertices, lift_edges(g.edges, g.vertices, ["v_grp"]))
    return aggregate_pairs(tag_edges(lifted, tags, len(hubs)), hubs, ["src_v_grp", "e_grp", "tgt_v_grp"], aggs, method, **options)


query("tau_vertex_count", S.sql(*V_MEM, final="SELECT x, y, COUNT(*) AS vertices FROM mem GROUP BY 1, 2"))(lambda s, d: _v_agg(s, d, [Agg("count", None, "vertices")], []))
for _kind, _expr in {
    "sum": "CAST(SUM(v_mr) AS BIGINT)", "min": "MIN(v_mr)", "max": "MAX(v_mr)", "avg": "ROUND(AVG(v_mr), 6)", "var": "ROUND(VAR_POP(v_mr), 6)", "stddev": "ROUND(STDDEV_POP(v_mr), 6)"
}.items():
    query(f"tau_vertex_{_kind}", S.sql(*V_MEM, final=f"SELECT x, y, {_expr} AS value FROM mem JOIN v USING (vid) GROUP BY 1, 2"))(
        lambda s, d, kind=_kind: _v_agg(s, d, [Agg(kind, "v_mr", "value")], []).select("x", "y", F.round("value", 6).alias("value") if kind in ("avg", "var", "stddev") else "value")
    )
query("tau_vertex_median_sn", S.sql(*V_MEM, final="SELECT x, y, MEDIAN(v_mr) AS value FROM mem JOIN v USING (vid) GROUP BY 1, 2"))(
    lambda s, d: _v_agg(s, d, [Agg("median", "v_mr", "value")], [], "share_nothing")
)
query("tau_vertex_distinct_sn", S.sql(*V_MEM, final="SELECT x, y, COUNT(DISTINCT v_mr) AS value FROM mem JOIN v USING (vid) GROUP BY 1, 2"))(
    lambda s, d: _v_agg(s, d, [Agg("count_distinct", "v_mr", "value")], [], "share_nothing")
)
query("tau_vertex_approx_distinct")(lambda s, d: _v_agg(s, d, [Agg("approx_distinct", "v_mr", "value")], []))


@query("tau_edge_closeness_dist", S.sql(*NEAR_REACH, S.EDGE_MEMBERS, final="SELECT x, y, closeness, COUNT(*) AS edges FROM emem GROUP BY 1, 2, 3"))
def _closeness_dist(s: SparkSession, d: str) -> DataFrame:
    g = near(s, d)
    hubs = hubs_of(g, 3)
    tags = _tags.vertices(g, hubs)
    return aggregate_pairs(tag_edges(g, tags, 3), hubs, ["closeness"], [Agg("count", None, "edges")])


query("tau_several_at_once", S.sql(*V_MEM, final="SELECT x, y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS total, COUNT(*) AS n, MAX(v_mr) AS top FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3"))(
    lambda s, d: _v_agg(s, d, [Agg("sum", "v_mr", "total"), Agg("count", None, "n"), Agg("max", "v_mr", "top")], ["v_grp"])
)
DIST = [FLOW, S.top_hubs(K), S.distances(60)]
NEAR_DIST = [NEAR, S.top_hubs(4), S.distances(30)]
DIST_SQL = S.sql(*NEAR_DIST, final="SELECT dist.x, dist.vid AS y, dist.d AS distance FROM dist JOIN h ON h.vid = dist.vid WHERE dist.x <> dist.vid")
query("tau_shortest_distance", DIST_SQL)(lambda s, d: structure.shortest_distance(near(s, d), hubs_of(near(s, d), 4)))
query("tau_shortest_distance_index", DIST_SQL)(lambda s, d: structure.shortest_distance(near(s, d), hubs_of(near(s, d), 4), index=hub_ops.all_distances(near(s, d))))
query("tau_shortest_path", S.sql(*NEAR_DIST, S.PATHS, final="SELECT x, y, path FROM back WHERE d = 0"))(
    lambda s, d: structure.shortest_path(near(s, d), hubs_of(near(s, d), 4)).select("x", "y", F.array_join(F.transform("path", lambda v: v.cast("string")), ">").alias("path"))
)
_steps = lambda start, step, how: [
    f" w0 AS (SELECT vid AS x, vid, {start} AS p FROM h)",
    *[f" w{i} AS (SELECT w.x, a.tgt AS vid, {how}({step}) AS p FROM w{i - 1} w JOIN a ON a.src = w.vid GROUP BY 1, 2)" for i in range(1, 5)],
    " wall AS (SELECT * FROM w1 UNION ALL SELECT * FROM w2 UNION ALL SELECT * FROM w3 UNION ALL SELECT * FROM w4)",
]
query(
    "tau_weighted_distance",
    S.sql(NEAR, S.top_hubs(4), " a AS (SELECT src, tgt, MIN(freq) AS w FROM e GROUP BY 1, 2)", *_steps("0::BIGINT", "w.p + a.w", "MIN"), final="SELECT x, vid AS y, MIN(p) AS distance FROM wall WHERE x <> vid AND vid IN (SELECT vid FROM h) GROUP BY 1, 2"),
)(lambda s, d: structure.weighted_distance(near(s, d), hubs_of(near(s, d), 4), "freq", 4))
TRUST = [NEAR, S.top_hubs(4), " t AS (SELECT src, SUM(freq) AS t FROM e GROUP BY src), a AS (SELECT e.src, e.tgt, e.freq / t.t AS p FROM e JOIN t USING (src))"]
for _n, _how, _f in (("tau_strength", "max_product", "MAX"), ("tau_strength_walks", "sum_walks", "SUM")):
    query(_n, S.sql(*TRUST, *_steps("1.0::DOUBLE", "w.p * a.p", _f), final=f"SELECT x, vid AS y, ROUND({_f}(p), 6) AS strength FROM wall WHERE x <> vid AND vid IN (SELECT vid FROM h) GROUP BY 1, 2"))(
        lambda s, d, how=_how: structure.relationship_strength(near(s, d), hubs_of(near(s, d), 4), combine=how)
    )
query(
    "tau_rel_type",
    S.sql(
        *NEAR_DIST, S.PATHS,
        """ p AS (SELECT x, y, string_split(path, '>') AS l FROM back WHERE d = 0),
        st AS (SELECT x, y, i, CAST(l[i] AS BIGINT) AS a, CAST(l[i + 1] AS BIGINT) AS b FROM p, UNNEST(range(1, len(l))) t(i))""",
        final="SELECT x, y, string_agg(rel, '>' ORDER BY i) AS type FROM st JOIN e ON e.src = st.a AND e.tgt = st.b GROUP BY 1, 2",
    ),
)(lambda s, d: structure.relationship_type(near(s, d), hubs_of(near(s, d), 4)))


@query("tau_min_cut")
def _cut(s: SparkSession, d: str) -> DataFrame:
    g = near(s, d)
    return q.explore(g).hubs(lambda x: hubs_of(g, 3)).between(4).summarize(q.structural("min_cut")).run(_tags).tables["min_cut"]


# -- many parts at once: baseline and sharing ---------------------------------------------------------
V_SUM = S.sql(*V_MEM, final="SELECT x, y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS sum_v_mr FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3")
E_SUM = S.sql(
    *E_MEM, final="SELECT x, y, a.v_grp AS src_v_grp, e_grp, b.v_grp AS tgt_v_grp, CAST(SUM(e_mr) AS BIGINT) AS sum_e_mr FROM emem JOIN v a ON a.vid = src JOIN v b ON b.vid = tgt GROUP BY 1, 2, 3, 4, 5"
)
VARIANTS = {
    "sn": {"method": "share_nothing"}, "sn_per_pair": {"method": "per_pair"}, "as": {}, "as_chained": {"layout": "chained"}, "as_flat": {"layout": "flat", "steps": 1}, "as_equal": {"method": "equal_tags"},
    "as_net_flat": {"objective": "net_flat", "layout": "flat"}, "as_net_chained": {"objective": "net_chained", "layout": "chained"}, "as_zero": {"merge_on_zero": True}, "auto": {"method": "auto"},
}
for _v, _o in VARIANTS.items():
    query(f"agg_vertex_{_v}", V_SUM)(lambda s, d, o=_o: _v_agg(s, d, [Agg("sum", "v_mr")], ["v_grp"], **o))
    query(f"agg_edge_{_v}", E_SUM)(lambda s, d, o=_o: _e_agg(s, d, [Agg("sum", "e_mr")], **o))
V20 = [FLOW, S.top_hubs(20), S.REACH, S.MEMBERS]
for _v in ("sn", "as"):
    query(f"agg_vertex_k20_{_v}", S.sql(*V20, final="SELECT x, y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS sum_v_mr FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3"))(
        lambda s, d, o=VARIANTS[_v]: _v_agg(s, d, [Agg("sum", "v_mr")], ["v_grp"], k=20, **o)
    )
    query(
        f"agg_vertex_k70_{_v}",  # two words of hubs
        S.sql(FLOW, S.top_hubs(70), S.REACH, S.MEMBERS, final="SELECT x, y, COUNT(*) AS n FROM mem GROUP BY 1, 2"),
    )(lambda s, d, o=VARIANTS[_v]: _v_agg(s, d, [Agg("count", None, "n")], [], k=70, **o))


@query("agg_graph_contact_as", S.sql(*NEAR_REACH, S.MEMBERS, final="SELECT x, y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS sum_v_mr FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3"))
def _contact_scc(s: SparkSession, d: str) -> DataFrame:
    """Pre-aggregated components are tagged and shared in place of their members."""
    g = near(s, d)
    hubs = hubs_of(g, 3)
    comp = saved(cycles.scc(g), "comp")
    dag, partials = cycles.condense(g, comp, ["v_grp"], [Agg("sum", "v_mr")])
    at = {r["vid"]: r["comp"] for r in comp.where(F.col("vid").isin(hubs)).collect()}
    tags = tag_vertices(dag.saved(), [at[h] for h in hubs])
    rows = partials.join(tags.withColumnRenamed("vid", "comp"), "comp")
    return aggregate_pairs(rows, hubs, ["v_grp"], [Agg("sum", "sum_v_mr", "sum_v_mr")])


@query(
    "agg_graph_rollup",
    S.sql(*E_MEM, final="SELECT x, y, a.v_grp AS src_v_grp, e_grp, CAST(SUM(e_mr) AS BIGINT) AS sum_e_mr FROM emem JOIN v a ON a.vid = src GROUP BY GROUPING SETS ((x, y, src_v_grp, e_grp), (x, y, src_v_grp), (x, y))"),
)
def _rollup(s: SparkSession, d: str) -> DataFrame:
    long = _e_agg(s, d, [Agg("sum", "e_mr")]).groupBy("x", "y", "src_v_grp", "e_grp").agg(F.sum("sum_e_mr").alias("part"))
    sets = [(c, F.lit(None).cast("long").alias(c)) for c in ("src_v_grp", "e_grp")]
    levels = [long.groupBy("x", "y", *[c for c, _ in sets[:n]]).agg(F.sum("part").alias("sum_e_mr")).select("x", "y", *[c for c, _ in sets[:n]], *[z for _, z in sets[n:]], "sum_e_mr") for n in (2, 1, 0)]
    return levels[0].unionByName(levels[1]).unionByName(levels[2])


# -- cost measures ----------------------------------------------------------------------------------------
query(
    "cost_adds_sn",
    S.sql(*FLOW_REACH, S.MEMBERS, S.EDGE_MEMBERS, final="SELECT 'vertex' AS element, COUNT(*) AS adds FROM mem UNION ALL SELECT 'edge', COUNT(*) FROM emem"),
)(lambda s, d: _adds(s, d, K).where("measure = 'share_nothing'").select("element", "adds"))


def _adds(s: SparkSession, d: str, k: int) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d, k)
    rows = []
    lifted = PropertyGraph(g.vertices, lift_edges(g.edges, g.vertices, ["v_grp"]))
    for element, tagged, dims in (("vertex", g.vertices.join(tags, "vid"), ["v_grp"]), ("edge", tag_edges(lifted, tags, k), ["src_v_grp", "e_grp", "tgt_v_grp"])):
        groups = tag_groups(combine_equal_tags(tagged, k, dims, [Agg("count")]), k)
        for layout in ("chained", "flat"):
            for by_value in (False, True):
                adds = add_operations(plan_sharing(groups, layout=layout), by_value=by_value)
                saved_share = round(1 - adds["sharing"] / adds["share_nothing"], 6) if adds["share_nothing"] else 0.0
                if layout == "chained" and not by_value:
                    rows += [(element, "share_nothing", adds["share_nothing"], 0.0), (element, "equal_tags", adds["equal_tags"], 0.0)]
                rows.append((element, f"sharing_{layout}_{'values' if by_value else 'elements'}", adds["sharing"], saved_share))
    return s.createDataFrame(rows, "element string, measure string, adds long, saved double")


query(
    "cost_adds_equal",
    S.sql(
        *FLOW_REACH, S.TAGS,
        " size AS (SELECT a.s0, b.r0, COUNT(*) AS n FROM e JOIN tags a ON a.vid = e.src JOIN tags b ON b.vid = e.tgt WHERE a.s0 <> 0 AND b.r0 <> 0 GROUP BY 1, 2 )",
        final="SELECT CAST(SUM(n + bit_count(s0) * bit_count(r0) - bit_count(s0 & r0)) AS BIGINT) AS adds FROM size",
    ),
)(lambda s, d: _adds(s, d, K).where("measure = 'equal_tags' and element = 'edge'").select("adds"))
query("cost_adds_as")(lambda s, d: _adds(s, d, 20))


@query("plan_sharing_summary")
def _plan(s: SparkSession, d: str) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d, 20)
    plan = plan_sharing(tag_groups(combine_equal_tags(g.vertices.join(tags, "vid"), 20, [], [Agg("count")]), 20))
    rows: dict[str, int] = {}
    for u in plan.units:
        rows[u.kind] = rows.get(u.kind, 0) + 1
    return s.createDataFrame([("tags", len(plan.groups)), ("clusters", len(plan.clusters)), *[(f"units_{k}", n) for k, n in sorted(rows.items())]], "what string, n long")


PIVOT_SQL = S.sql(
    NEAR, S.closeness_all(40),
    " h AS (SELECT CAST(ROW_NUMBER() OVER (ORDER BY md5(vid::VARCHAR), vid) - 1 AS INTEGER) AS i, vid FROM v ORDER BY md5(vid::VARCHAR), vid LIMIT 16)",
    S.reach_hops(40), " piv AS (SELECT vid, ROUND(COUNT(*) / SUM(d), 9) AS closeness FROM bwd WHERE d > 0 GROUP BY vid)",
    final="SELECT COUNT(*) AS n, ROUND(AVG(abs(p.closeness - c.closeness) / c.closeness), 6) AS mean_error, ROUND(MAX(abs(p.closeness - c.closeness) / c.closeness), 6) AS max_error FROM close c JOIN piv p USING (vid) WHERE c.closeness > 0",
)
query("accuracy_pivots", PIVOT_SQL)(lambda s, d: measures.relative_error(hub_ops.closeness(near(s, d)), hub_ops.pivot_closeness(near(s, d), 16), "vid", "closeness"))
query(
    "tau_group_values",
    S.sql(*V_MEM, " g AS (SELECT x, y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS t FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3)", final="SELECT x, y, string_agg(v_grp || '=' || t, ',' ORDER BY v_grp) AS groups FROM g GROUP BY 1, 2"),
)(
    lambda s, d: q.group_values(_v_agg(s, d, [Agg("sum", "v_mr", "t")], ["v_grp"]), ["v_grp"], ["t"], "groups").select(
        "x", "y", F.array_join(F.transform("groups", lambda g: F.concat(g["v_grp"].cast("string"), F.lit("="), g["t"].cast("string"))), ",").alias("groups")
    )
)


@query("agg_edge_broadcast_access", E_SUM)
def _broadcast_access(s: SparkSession, d: str) -> DataFrame:
    g, hubs, tags = _flow_tags(s, d)
    lifted = PropertyGraph(g.vertices, lift_edges(g.edges, g.vertices, ["v_grp"], access="broadcast"))
    return aggregate_pairs(tag_edges(lifted, tags, len(hubs)), hubs, ["src_v_grp", "e_grp", "tgt_v_grp"], [Agg("sum", "e_mr")])


@query("source_generator", S.sql(S.synthetic(500, 4, numbers="(SELECT o_orderkey AS id FROM orders)"), final="SELECT src, tgt, e_mr FROM e"))
def _generated(s: SparkSession, d: str) -> DataFrame:
    drawn = drawn_from(read_table(s, d, "orders").select("o_orderkey"), 500)
    return drawn.groupBy("src", "tgt").agg(F.sum(F.col("number") % 100).alias("e_mr"))


# -- whole queries, zooming, presentation ------------------------------------------------------------------
@query("hsg_performance_vertices", V_SUM)
def _performance(s: SparkSession, d: str) -> DataFrame:
    return _performance_query(s, d).tables["sum_v_mr"]


def _performance_query(s: SparkSession, d: str, k: int = K, method: str = "sharing"):  # noqa: ANN202
    g = flow(s, d)
    summaries = q.aggregate_graph([Agg("sum", "v_mr")], [Agg("sum", "e_mr")])
    return q.explore(g).hubs(lambda x: hubs_of(g, k)).between().summarize(*summaries).using(method).run(_tags)


query("hsg_performance_edges", E_SUM)(lambda s, d: _performance_query(s, d).tables["sum_e_mr"])
query("hsg_pairs", S.sql(*FLOW_REACH, final="SELECT h2.vid AS x, h.vid AS y FROM fwd f JOIN h ON h.vid = f.vid JOIN h h2 ON h2.i = f.i WHERE f.i <> h.i"))(lambda s, d: _performance_query(s, d).pairs)

RUN_SCOPE = [
    S.mutual(180).replace("    e AS (SELECT a.* FROM e0 a", "    e1 AS (SELECT a.* FROM e0 a"),
    """ wx(vid, d) AS (SELECT 0::BIGINT, 0 UNION SELECT e1.tgt, w.d + 1 FROM wx w JOIN e1 ON e1.src = w.vid WHERE w.d < 30),
    wy(vid, d) AS (SELECT 149::BIGINT, 0 UNION SELECT e1.src, w.d + 1 FROM wy w JOIN e1 ON e1.tgt = w.vid WHERE w.d < 30),
    dx AS (SELECT vid, MIN(d) AS d FROM wx GROUP BY vid), dy AS (SELECT vid, MIN(d) AS d FROM wy GROUP BY vid),
    bound AS (SELECT GREATEST(4, (SELECT MIN(d) FROM dy WHERE vid = 0)) AS b),
    e AS (SELECT e1.* FROM e1 JOIN dx ON dx.vid = e1.src JOIN dy ON dy.vid = e1.tgt, bound WHERE dx.d + 1 + dy.d <= bound.b)""",
    S.DEGREES,
    " top2 AS (SELECT vid FROM deg ORDER BY degree DESC, vid LIMIT 2), h AS (SELECT CAST(ROW_NUMBER() OVER (ORDER BY vid) - 1 AS INTEGER) AS i, vid FROM (SELECT vid FROM top2 UNION SELECT 0 UNION SELECT 149))",
    S.REACH, S.MEMBERS,
]
TEXT = "HUBS top_degree(g, 2) FROM paths_between(0, 149, 4) AS g GROUP BY between() SUMMARIZE relationship_strength(), relationship_type(), vertex_count()"
_running = lambda s, d: parse_query(TEXT, graph(s, d, "mutual_contact", max_gap_s=180)).run(_tags)
query("hsg_running", S.sql(*RUN_SCOPE, final="SELECT x, y, COUNT(*) AS vertices FROM mem GROUP BY 1, 2"))(lambda s, d: _running(s, d).tables["vertices"])
query("hsg_running_edges")(lambda s, d: _running(s, d).edges)


def _effect(s: SparkSession, d: str, hops: int | None):  # noqa: ANN202
    g = near(s, d)
    return q.explore(g).hubs(lambda x: hubs_of(g, 3)).between(hops).summarize(q.edge_count_by("closeness")).run(_tags)


query("hsg_effect_plain", S.sql(S.contact(), S.top_hubs(3), S.REACH, S.EDGE_MEMBERS, final="SELECT x, y, closeness, COUNT(*) AS edges FROM emem GROUP BY 1, 2, 3"))(
    lambda s, d: q.explore(g := graph(s, d, "contact_graph")).hubs(lambda x: hubs_of(g, 3)).between().summarize(q.edge_count_by("closeness")).run(_tags).tables["edges"]
)
for _h in (2, 3, 4):
    query(f"hsg_effect_hops{_h}", S.sql(NEAR, S.top_hubs(3), S.reach_hops(_h), S.MEMBERS, S.EDGE_MEMBERS_ENDS, final="SELECT x, y, closeness, COUNT(*) AS edges FROM emem GROUP BY 1, 2, 3"))(
        lambda s, d, h=_h: _effect(s, d, h).tables["edges"]
    )
ZOOM = [NEAR, S.top_hubs(3), S.reach_hops(4), S.MEMBERS]


@query("zoom_edge", S.sql(*ZOOM, " z AS (SELECT vid FROM mem WHERE x = (SELECT vid FROM h WHERE i = 0) AND y = (SELECT vid FROM h WHERE i = 1))", final="SELECT e.src, e.tgt FROM e WHERE src IN (SELECT vid FROM z) AND tgt IN (SELECT vid FROM z)"))
def _zoom(s: SparkSession, d: str) -> DataFrame:
    r = _effect(s, d, 4)
    return r.zoom_edge(r.hubs[0], r.hubs[1]).edges.select("src", "tgt")


@query("zoom_vertices", S.sql(*ZOOM, S.EDGE_MEMBERS_ENDS, final="SELECT DISTINCT src, tgt FROM emem WHERE x IN (SELECT vid FROM h WHERE i < 2) AND y IN (SELECT vid FROM h WHERE i < 2)"))
def _zoom_some(s: SparkSession, d: str) -> DataFrame:
    r = _effect(s, d, 4)
    return r.zoom_vertices(r.hubs[:2]).edges.select("src", "tgt")


@query("zoom_requery")
def _zoom_again(s: SparkSession, d: str) -> DataFrame:
    r = _effect(s, d, 4)
    part = r.zoom_edge(r.hubs[0], r.hubs[1]).saved()
    return q.explore(part).hubs(lambda x: hub_ops.ensure_hubs(hub_ops.top_degree(x, 2), r.hubs[:2])).between(4).summarize(q.edge_count_by("closeness"), q.vertex_count()).run().edges


query("hsg_no_hubs", S.sql(FLOW, final="SELECT CAST(NULL AS BIGINT) AS x, CAST(NULL AS BIGINT) AS y, v_grp, CAST(SUM(v_mr) AS BIGINT) AS sum_v_mr FROM v GROUP BY v_grp"))(
    lambda s, d: q.explore(flow(s, d)).hubs(lambda g: []).summarize(q.vertex_agg("sum", "v_mr", ("v_grp",))).run().tables["sum_v_mr"]
)


@query("hsg_all_hubs", S.sql(NEAR, " tc(src, tgt) AS (SELECT vid, vid FROM v UNION SELECT t.src, e.tgt FROM tc t JOIN e ON e.src = t.tgt)", final="SELECT src AS x, tgt AS y FROM tc WHERE src <> tgt"))
def _all_hubs(s: SparkSession, d: str) -> DataFrame:
    g = near(s, d)
    return q.explore(g).hubs(lambda x: [r["vid"] for r in x.vertices.select("vid").orderBy("vid").collect()]).between().run().pairs


def same_groups(g: PropertyGraph, hubs: list[int]) -> DataFrame:
    """A grouping of one's own: the part of two hubs is all vertices of either's group."""
    pairs = g.vertices.sparkSession.createDataFrame([(x, y) for x in hubs for y in hubs if x != y], "x long, y long")
    group = lambda end: F.broadcast(g.vertices.where(F.col("vid").isin(hubs)).select(F.col("vid").alias(end), F.col("v_grp").alias(f"{end}_grp")))
    either = pairs.join(group("x"), "x").join(group("y"), "y").select("x", "y", F.explode(F.array_distinct(F.array("x_grp", "y_grp"))).alias("v_grp"))
    return g.vertices.join(F.broadcast(either), "v_grp").select("x", "y", "vid")


CUSTOM = [
    S.contact(), S.top_hubs(3),
    " mem AS (SELECT DISTINCT a.vid AS x, b.vid AS y, v.vid FROM h a JOIN h b ON a.i <> b.i JOIN v va ON va.vid = a.vid JOIN v vb ON vb.vid = b.vid JOIN v ON v.v_grp IN (va.v_grp, vb.v_grp))",
    S.EDGE_MEMBERS_ENDS,
]
CUSTOM_WALK = " walk(x, y, vid, d) AS (SELECT DISTINCT x, y, x, 0 FROM mem UNION SELECT w.x, w.y, m.tgt, w.d + 1 FROM walk w JOIN emem m ON m.x = w.x AND m.y = w.y AND m.src = w.vid WHERE w.d < 30)"
_custom = lambda s, d, *what: q.explore(g := graph(s, d, "contact_graph")).hubs(lambda x: hubs_of(g, 3)).between(custom=same_groups).summarize(*what).run().tables
query("tau_vertex_custom", S.sql(*CUSTOM, final="SELECT x, y, v_grp, COUNT(*) AS n FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3"))(
    lambda s, d: _custom(s, d, q.vertex_agg("count", None, ("v_grp",), "n"))["n"]
)
query("tau_vertex_simple_paths")(
    lambda s, d: q.explore(g := graph(s, d, "mutual_contact", max_gap_s=180)).hubs(lambda x: hubs_of(g, 5)).between(simple_paths=True).summarize(q.vertex_agg("count", None, ("v_grp",), "n")).run().tables["n"]
)
query("tau_edge_custom", S.sql(*CUSTOM, final="SELECT x, y, closeness, COUNT(*) AS edges FROM emem GROUP BY 1, 2, 3"))(lambda s, d: _custom(s, d, q.edge_count_by("closeness"))["edges"])
query("tau_distance_custom", S.sql(*CUSTOM, CUSTOM_WALK, final="SELECT x, y, MIN(d) AS distance FROM walk WHERE vid = y GROUP BY 1, 2"))(
    lambda s, d: _custom(s, d, q.structural("shortest_distance"))["shortest_distance"]
)
query(
    "tau_strength_custom",
    S.sql(
        *CUSTOM, " t AS (SELECT src, SUM(freq) AS t FROM e GROUP BY src), a AS (SELECT x, y, emem.src, tgt, freq / t.t AS p FROM emem JOIN t ON t.src = emem.src)",
        " w0 AS (SELECT DISTINCT x, y, x AS vid, 1.0::DOUBLE AS p FROM mem)",
        *[f" w{i} AS (SELECT w.x, w.y, a.tgt AS vid, MAX(w.p * a.p) AS p FROM w{i - 1} w JOIN a ON a.x = w.x AND a.y = w.y AND a.src = w.vid GROUP BY 1, 2, 3)" for i in range(1, 5)],
        final="SELECT x, y, ROUND(MAX(p), 6) AS strength FROM (SELECT * FROM w1 UNION ALL SELECT * FROM w2 UNION ALL SELECT * FROM w3 UNION ALL SELECT * FROM w4) WHERE vid = y GROUP BY 1, 2",
    ),
)(lambda s, d: _custom(s, d, q.structural("relationship_strength"))["relationship_strength"])
query(
    "tau_distance_hops",
    S.sql(NEAR, S.top_hubs(3), S.reach_hops(3), S.MEMBERS, S.EDGE_MEMBERS_ENDS, CUSTOM_WALK, final="SELECT x, y, MIN(d) AS distance FROM walk WHERE vid = y GROUP BY 1, 2"),
)(lambda s, d: q.explore(near(s, d)).hubs(lambda x: hubs_of(near(s, d), 3)).between(3).summarize(q.structural("shortest_distance")).run(_tags).tables["shortest_distance"])
query("hsg_total_hops", S.sql(NEAR, S.top_hubs(3), S.reach_hops(4), " mem AS (SELECT hx.vid AS x, hy.vid AS y, f.vid FROM fwd f JOIN bwd b ON f.vid = b.vid AND f.i <> b.i AND f.d + b.d <= 4 JOIN h hx ON hx.i = f.i JOIN h hy ON hy.i = b.i)", final="SELECT x, y, v_grp, COUNT(*) AS n FROM mem JOIN v USING (vid) GROUP BY 1, 2, 3"))(
    lambda s, d: q.explore(near(s, d)).hubs(lambda x: hubs_of(near(s, d), 3)).between(4, mode="total").summarize(q.vertex_agg("count", None, ("v_grp",), "n")).run().tables["n"]
)
query("render_data_tables", S.sql(*V_MEM, final="SELECT x, y, COUNT(*) AS vertices FROM mem GROUP BY 1, 2"))(
    lambda s, d: q.explore(flow(s, d)).hubs(lambda x: hubs_of(flow(s, d), K)).between().summarize(q.vertex_count()).run(_tags).render()
)
query(
    "hsg_diff",
    S.sql(
        NEAR, S.top_hubs(3), S.reach_hops(4).replace("fwd", "f4").replace("bwd", "b4"), S.reach_hops(3).replace("fwd", "f3").replace("bwd", "b3"),
        """ a AS (SELECT hx.vid AS x, hy.vid AS y, COUNT(*) AS vertices FROM f4 f JOIN b4 b ON f.vid = b.vid AND f.i <> b.i JOIN h hx ON hx.i = f.i JOIN h hy ON hy.i = b.i GROUP BY 1, 2),
        c AS (SELECT hx.vid AS x, hy.vid AS y, COUNT(*) AS vertices FROM f3 f JOIN b3 b ON f.vid = b.vid AND f.i <> b.i JOIN h hx ON hx.i = f.i JOIN h hy ON hy.i = b.i GROUP BY 1, 2)""",
        final="SELECT *, 'left' AS side FROM (SELECT * FROM a EXCEPT SELECT * FROM c) UNION ALL SELECT *, 'right' FROM (SELECT * FROM c EXCEPT SELECT * FROM a)",
    ),
)(lambda s, d: _counted(s, d, 4).diff(_counted(s, d, 3), "vertices"))


def _counted(s: SparkSession, d: str, hops: int):  # noqa: ANN202
    g = near(s, d)
    return q.explore(g).hubs(lambda x: hubs_of(g, 3)).between(hops).summarize(q.vertex_count()).run(_tags)


query(
    "asof_enrich",
    """WITH p AS (SELECT user_id, ts, event_id, value FROM events WHERE event_type = 'purchase'), c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click')
       SELECT c.event_id, c.user_id, (SELECT p.value FROM p WHERE p.user_id = c.user_id AND p.ts <= c.ts ORDER BY p.ts DESC LIMIT 1) AS last_value FROM c""",
)(
    lambda s, d: as_of(
        read_table(s, d, "events").where("event_type = 'click'").select("event_id", "user_id", "ts"),
        read_table(s, d, "events").where("event_type = 'purchase'").select("user_id", "ts", F.col("value").alias("last_value")), "user_id", "ts", "last_value",
    ).drop("ts")
)
query(
    "contact_windows_batch",
    "SELECT epoch_us(date_trunc('hour', ts)) AS window_start, user_id, event_type, COUNT(*) AS n FROM events GROUP BY 1, 2, 3",
)(lambda s, d: contact_windows(read_table(s, d, "events")))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: both aggregates of the performance query over the small flow graph, shared; the vertex side."""
    g = graph(spark, sf_dir, "part_flow", m=1)
    return q.explore(g).hubs(lambda x: hub_ops.top_degree(x, 5)).between().summarize(q.vertex_agg("sum", "v_mr", ("v_grp",))).run(_tags).tables["sum_v_mr"]


__all__ = ["QUERIES", "SQL", "entry", "live"]
