"""Operators on small graphs, against plain Python, and the driver contract."""

import itertools
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg
from hubloom.functions.bits import cardinality
from hubloom.operators import cycles, reach_index, structure
from hubloom.operators import hubs as hub_ops
from hubloom.operators import scope as scope_ops
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.pair_aggregate import aggregate_pairs, choose_method, lift_edges, plan_in_blocks, combine_equal_tags, execute_plan
from hubloom.operators.runtime import saved
from hubloom.operators.tags import hub_pairs, tag_edges, tag_vertices
from hubloom.plans import query as q
from hubloom.plans.result import ExplorationSession
from hubloom.plans.text import QueryError, parse_query
from hubloom.queries import catalog
from hubloom.sources import graphs, tables

HUBS = [1, 2, 3, 4, 5]


def made(spark, arcs, vids=None):
    vids = sorted({v for a in arcs for v in a} | set(vids or ()))
    v = spark.createDataFrame([(x, x % 3, x + 1) for x in vids], "vid long, v_grp long, v_mr long")
    e = spark.createDataFrame([(s, t, (s + t) % 2, s * t + 1) for s, t in arcs], "src long, tgt long, e_grp long, e_mr long")
    return PropertyGraph(v, e)


def reach(arcs, start):
    seen, todo = {start}, [start]
    while todo:
        v = todo.pop()
        for s, t in arcs:
            if s == v and t not in seen:
                seen.add(t)
                todo.append(t)
    return seen


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


@pytest.fixture(scope="module")
def worked(spark):
    g = graphs.worked_example(spark).validate().saved()
    return g, saved(tag_vertices(g, HUBS), "t")


def test_worked_example_tags(worked):
    g, tags = worked
    got = {r["vid"]: (r["s0"], r["r0"], r["c"]) for r in tags.withColumn("c", cardinality(1)).collect()}
    bits = lambda *hubs: sum(1 << (h - 1) for h in hubs)
    assert got[11] == (bits(1), bits(2, 3, 4, 5), 4)
    assert got[21] == got[22] == (bits(1, 2), bits(3, 4, 5), 6)
    assert got[31] == got[32] == got[33] == (bits(1, 2, 3), bits(4, 5), 6)
    assert {h: got[h][2] for h in HUBS} == {1: 5, 2: 8, 3: 9, 4: 4, 5: 4}
    assert rows(hub_pairs(tags, HUBS), "x", "y") == sorted((x - 1, y - 1) for x, y in [(1, 2), (1, 3), (1, 4), (1, 5), (2, 3), (2, 4), (2, 5), (3, 4), (3, 5)])
    nothing = aggregate_pairs(g.vertices.join(tags, "vid"), HUBS, [], [Agg("count", None, "n")], "share_nothing")
    assert nothing.agg(F.sum("n")).first()[0] == 59
    edges = aggregate_pairs(tag_edges(g, tags, 5), HUBS, [], [Agg("count", None, "n")], "share_nothing")
    assert edges.agg(F.sum("n")).first()[0] == 62


VARIANTS = [("sharing", {}), ("sharing", {"layout": "flat"}), ("sharing", {"objective": "net_chained"}), ("sharing", {"merge_on_zero": True}), ("equal_tags", {}), ("per_pair", {}), ("auto", {})]


@pytest.mark.parametrize("seed", [1, 2])
def test_sharing_equals_share_nothing_on_random_graphs(spark, seed):
    rnd = random.Random(seed)
    arcs = sorted({(rnd.randrange(14), rnd.randrange(14)) for _ in range(30)})
    g = made(spark, arcs, range(14)).saved()
    hubs = [0, 3, 5, 9]
    tags = saved(tag_vertices(g, hubs), "t")
    ahead = {h: reach(arcs, h) for h in hubs}
    back = {h: {v for v in range(14) if h in reach(arcs, v)} for h in hubs}
    want: dict = {}
    for x, y in itertools.permutations(hubs, 2):
        for v in ahead[x] & back[y]:
            n, s, low = want.get((x, y, v % 3), (0, 0, 99))
            want[(x, y, v % 3)] = (n + 1, s + v + 1, min(low, v + 1))
    aggs = [Agg("count", None, "n"), Agg("sum", "v_mr", "s"), Agg("min", "v_mr", "low")]
    tagged = g.vertices.join(tags, "vid")
    for method, options in [("share_nothing", {}), *VARIANTS]:
        got = {tuple(r[:3]): tuple(r[3:]) for r in aggregate_pairs(tagged, hubs, ["v_grp"], aggs, method, **options).collect()}
        assert got == want, method
    sources, targets = plan_in_blocks(combine_equal_tags(tagged, 4, ["v_grp"], aggs), 4, {})
    got = {tuple(r[:3]): tuple(r[3:]) for r in execute_plan(combine_equal_tags(tagged, 4, ["v_grp"], aggs), sources, targets, hubs, ["v_grp"], aggs).collect()}
    assert got == want
    by_tag, by_ends = (rows(tag_edges(g, tags, 4, rule), "src", "tgt", "s0", "r0") for rule in ("tag", "endpoints"))
    assert by_tag == by_ends  # plain betweenness: one and the same
    plain = {tuple(r) for r in tags.where("s0 <> 0 or r0 <> 0").select("vid", "s0", "r0").collect()}
    assert {tuple(r) for r in tag_vertices(g, hubs, local_edges=0).select("vid", "s0", "r0").collect()} == plain
    assert {tuple(r) for r in reach_index.tags_from_closure(reach_index.transitive_closure(g), hubs).select("vid", "s0", "r0").collect()} == plain
    for method in reach_index.METHODS:
        assert {tuple(r) for r in reach_index.extract(g, hubs, method).select("vid", "s0", "r0").collect()} == plain, method
    comp = {r["vid"]: r["comp"] for r in cycles.scc(g).collect()}
    assert comp == {v: min(u for u in range(14) if u in reach(arcs, v) and v in reach(arcs, u)) for v in range(14)}
    assert {r["vid"]: r["comp"] for r in cycles.scc(g, local_edges=0).collect()} == comp


def test_more_than_one_word_of_hubs(spark):
    arcs = [(i, i + 1) for i in range(70)]
    g = made(spark, arcs).saved()
    hubs = list(range(66))
    tags = saved(tag_vertices(g, hubs), "t")
    for method in ("share_nothing", "sharing"):
        got = {(r["x"], r["y"]): r["n"] for r in aggregate_pairs(g.vertices.join(tags, "vid"), hubs, [], [Agg("count", None, "n")], method).collect()}
        assert got == {(x, y): y - x + 1 for x in range(66) for y in range(x + 1, 66)}


def test_nulls_floats_strings_and_holistic(spark, worked):
    g, tags = worked
    v = g.vertices.withColumn("kind", F.when(F.col("vid") > 20, F.lit("in"))).withColumn("m", F.when(F.col("vid") < 30, F.col("v_mr") / 2))
    aggs = [Agg("avg", "m"), Agg("stddev", "m"), Agg("count", "m"), Agg("count", None, "all")]
    a = sorted(map(str, aggregate_pairs(v.join(tags, "vid"), HUBS, ["kind"], aggs, "share_nothing").collect()))
    assert a == sorted(map(str, aggregate_pairs(v.join(tags, "vid"), HUBS, ["kind"], aggs, "sharing").collect()))
    with pytest.raises(ValueError, match="cannot be merged"):
        aggregate_pairs(v.join(tags, "vid"), HUBS, [], [Agg("median", "m")], "sharing")
    assert choose_method({"elements": 10, "partials": 10, "spread": 40, "nothing": 40}) == "share_nothing"


def test_edge_cases_of_hubs_and_graphs(spark):
    g = made(spark, [(1, 1), (1, 2), (2, 1)], [1, 2, 3]).saved()
    assert rows(tag_vertices(g, []), "vid") == []
    tags = tag_vertices(g, [3, 1])
    assert rows(hub_pairs(tags, [3, 1]), "x", "y") == []
    empty = made(spark, [], [7])
    assert rows(tag_vertices(PropertyGraph(empty.vertices, g.edges.limit(0)), [7]), "vid", "s0", "r0") == [(7, 1, 1)]
    with pytest.raises(ValueError):
        scope_ops.paths_between(g, 1, 1)
    with pytest.raises(ValueError, match="not there"):
        PropertyGraph(g.vertices.where("vid < 2"), g.edges).validate()
    assert hub_ops.top_degree(g, 2) == [1, 2]


def test_distance_fallback_and_hops(spark):
    g = made(spark, [(i, i + 1) for i in range(7)]).saved()
    assert len(rows(scope_ops.paths_between(g, 0, 6, 4).edges, "src")) == 6
    assert rows(scope_ops.paths_between(g, 0, 6, 4, expand_if_farther=False).edges, "src") == []
    assert rows(structure.shortest_distance(g, [0, 6]), "x", "y", "distance") == [(0, 6, 6)]
    assert [list(r["path"]) for r in structure.shortest_path(g, [0, 3]).collect()] == [[0, 1, 2, 3]]
    near, far = (rows(tag_vertices(g, [0, 6], h), "vid", "s0", "r0") for h in (2, 50))
    assert far == rows(tag_vertices(g, [0, 6]), "vid", "s0", "r0") and near != far
    with pytest.raises(ValueError, match="negative"):
        structure.weighted_distance(PropertyGraph(g.vertices, g.edges.withColumn("e_mr", F.lit(-1))), [0, 3], "e_mr")


def test_min_cut_against_brute_force():
    rnd = random.Random(4)
    for _ in range(30):
        arcs = sorted({(a, b) for a, b in ((rnd.randrange(5), rnd.randrange(5)) for _ in range(9)) if a != b})
        value, cut = structure.max_flow([(a, b, 1) for a, b in arcs], 0, 4)
        best = next(n for n in range(len(arcs) + 1) if any(4 not in reach([a for a in arcs if a not in c], 0) for c in map(set, itertools.combinations(arcs, n))))
        assert value == best == len(cut)
        assert 4 not in reach([a for a in arcs if a not in cut], 0)


def test_text_form_zoom_session_and_render(spark, worked):
    g, _ = worked
    text = "hubs explicit(g, 1, 3, 5) from whole_graph() as g group by between() summarize vertex_count(), sum_edges('e_mr'), shortest_path(), min_cut()"
    result = parse_query(text, g).run()
    got = {(r["x"], r["y"]): (r["vertices"], r["cut"]) for r in result.edges.withColumnRenamed("min_cut", "cut").collect()}
    assert got == {(1, 3): (6, 1), (3, 5): (5, 2), (1, 5): (10, 1)}
    again = result.zoom_edge(1, 3)
    assert rows(again.vertices, "vid") == [(v,) for v in (1, 2, 3, 11, 21, 22)]
    assert rows(result.zoom_vertices([1, 3]).edges, "src", "tgt") == rows(again.edges, "src", "tgt")
    session = ExplorationSession()
    session.push(result)
    session.push(q.explore(again.saved()).hubs(lambda x: [1, 3]).summarize(q.vertex_count()).run())
    assert session.back() is result and session.forward() is not result
    payload = result.render("graph")
    assert len(payload["links"]) == 3 and "chain" in payload["links"][0]["summaries"]["path"]
    assert "digraph" in result.to_dot()
    for bad, at in (("hubs top_degree(g, 2", 20), ("select", 0), ("hubs nope(g) from whole_graph() as g group by between() summarize vertex_count()", 5)):
        with pytest.raises(QueryError) as e:
            parse_query(bad, g)
        assert e.value.at == at


def test_no_hub_all_hubs_and_custom(spark, worked):
    g, _ = worked
    whole = q.explore(g).hubs(lambda x: []).summarize(q.vertex_agg("sum", "v_mr")).run()
    assert whole.tables["sum_v_mr"].first()["sum_v_mr"] == sum([1, 2, 3, 4, 5, 11, 21, 22, 31, 32, 33])
    pick = lambda gr, hubs: gr.vertices.where("vid > 20").select(F.lit(1).cast("long").alias("x"), F.lit(3).cast("long").alias("y"), "vid")
    own = q.explore(g).hubs(lambda x: [1, 3]).between(custom=pick).summarize(q.vertex_count(), q.edge_agg("count", None, name="inner")).run()
    assert [r["vertices"] for r in own.tables["vertices"].collect()] == [5]


@pytest.mark.parametrize("seed", range(3))
def test_simple_paths_against_enumeration(spark, seed):
    rnd = random.Random(seed)
    arcs = sorted({tuple(sorted(rnd.sample(range(12), 2))) for _ in range(13)}) + [(20, 21), (3, 3)]
    hubs = [0, 3, 7, 11, 20, 21]
    g = made(spark, arcs, range(12)).both_ways()
    near = {v: {b if a == v else a for a, b in arcs if v in (a, b) and a != b} for v in [*range(12), 20, 21]}
    want = set()

    def walk(path, y):
        if path[-1] == y:
            want.update((path[0], y, v) for v in path)
            return
        for u in near[path[-1]] - set(path):
            walk([*path, u], y)

    for x, y in itertools.permutations(hubs, 2):
        walk([x], y)
    got = q.simple_path_members(g, hubs)
    assert rows(got, "x", "y", "vid") == sorted(want)
    result = q.explore(g).hubs(lambda x: hubs).between(simple_paths=True).summarize(q.vertex_count()).run()
    counts = {(r["x"], r["y"]): r["vertices"] for r in result.tables["vertices"].collect()}
    assert counts == {(x, y): sum(1 for a, b, _ in want if (a, b) == (x, y)) for x, y, _ in want}
    result.validate(spark.createDataFrame(sorted(counts), "x long, y long"))
    with pytest.raises(ValueError, match="disagree"):
        result.validate(spark.createDataFrame([(0, 99)], "x long, y long"))
    with pytest.raises(ValueError, match="bound"):
        q.simple_path_members(g, hubs, local_edges=3)
    assert q.simple_path_members(made(spark, [(1, 1)]), [1]).collect() == []


def test_both_ways(spark):
    g = made(spark, [(1, 2), (2, 3), (3, 2), (4, 5)]).both_ways()
    assert rows(g.edges, "src", "tgt") == [(1, 2), (2, 1), (2, 3), (3, 2), (4, 5), (5, 4)] and not g.directed
    tags = {r["vid"]: (r["s0"], r["r0"]) for r in tag_vertices(g, [1, 3, 5]).collect()}
    # By walks, every vertex of a component is between all its hubs.
    assert all(tags[v] == (0b011, 0b011) for v in (1, 2, 3)) and all(tags[v] == (0b100, 0b100) for v in (4, 5))


def test_synthetic_graph_and_files(spark, tmp_path):
    g = graphs.synthetic_dag(spark, 300, 4).saved()
    assert g.edges.where("src >= tgt").isEmpty()
    levels = {r["vid"]: r["level"] for r in cycles.topo_levels(g).collect()}
    assert all(levels[s] < levels[t] for s, t in g.edges.select("src", "tgt").collect())
    assert {r["vid"]: r["level"] for r in cycles.topo_levels(made(spark, [(1, 2), (2, 3), (3, 2), (3, 4)]), local_edges=0).collect()} == {1: 0, 2: 1, 3: 1, 4: 2}
    tables.write_graph(g, str(tmp_path / "g"))
    assert tables.read_graph(spark, str(tmp_path / "g")).edges.count() == g.edges.count()
    (tmp_path / "e.txt").write_text("# arcs\n1 2\n2 3\n")
    assert rows(tables.read_edge_list(spark, str(tmp_path / "e.txt"), "text").edges, "src", "tgt") == [(1, 2), (2, 3)]


def test_lifted_edges(spark, worked):
    g, _ = worked
    assert set(lift_edges(g.edges, g.vertices, ["v_grp"]).columns) >= {"src_v_grp", "tgt_v_grp"}


@pytest.mark.parametrize("name", ["graph_part_flow_edges", "reach_tags_vertices", "agg_vertex_as", "agg_edge_as_flat", "hsg_effect_plain", "tau_shortest_path", "contact_windows_batch", "hubs_closeness_pivots"])
def test_queries_equal_their_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("part", "lineitem", "orders", "events"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    ours = catalog.QUERIES[name](spark, sf_dir)
    theirs = con.execute(catalog.SQL[name])
    names = [c[0] for c in theirs.description]
    assert sorted(names) == sorted(ours.columns)
    assert sorted(map(str, (tuple(r) for r in ours.select(*names).collect()))) == sorted(map(str, theirs.fetchall()))


def test_contract(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_structural_summaries_are_of_the_part(spark):
    g = made(spark, [(1, 2), (2, 4), (4, 5), (5, 3), (1, 6), (6, 3)]).saved()
    part = lambda *rows: (lambda graph, hubs: spark.createDataFrame([(1, 3, v) for v in rows], "x long, y long, vid long"))
    ask = lambda custom, name, **o: q.explore(g).hubs(lambda x: [1, 3]).between(custom=custom).summarize(q.structural(name, **o)).run().tables[name]
    assert ask(part(1, 3), "shortest_distance").collect() == []  # no path inside
    assert rows(ask(part(1, 2, 4, 5, 3), "shortest_distance"), "x", "y", "distance") == [(1, 3, 4)]
    assert rows(ask(part(1, 2, 3, 4, 5, 6), "shortest_path"), "x", "y", "path") == [(1, 3, [1, 6, 3])]
    assert rows(ask(part(1, 2, 3, 4, 5, 6), "min_cut"), "x", "y", "cut") == [(1, 3, 2)]
    assert rows(ask(part(1, 3, 6), "min_cut"), "x", "y", "cut") == [(1, 3, 1)]
    with pytest.raises(ValueError, match="none"):
        q.explore(g).hubs(lambda x: []).summarize(q.structural("min_cut")).run()
    # Bounded on each side: through 6, and not by the longer way.
    found = q.explore(g).hubs(lambda x: [1, 3]).between(2).summarize(q.structural("weighted_distance", weight="e_mr")).run().tables["weighted_distance"]
    assert rows(found, "x", "y", "distance") == [(1, 3, 7 + 19)]


def by_python(arcs, vids):
    """Distances of every reachable pair."""
    out = {}
    for x in vids:
        d, todo = {x: 0}, [x]
        for v in todo:
            for s, t in arcs:
                if s == v and t not in d:
                    d[t] = d[v] + 1
                    todo.append(t)
        out |= {(x, y): n for y, n in d.items()}
    return out


def near_by_python(d, some):
    sums = {x: [n for (a, b), n in d.items() if a == x and b in some] for x in some}
    return sorted((x, round((len(n) - 1) / sum(n), 9) if sum(n) else 0.0) for x, n in sums.items())


@pytest.mark.parametrize("limit", [16_000_000, 3])
def test_closeness_has_no_largest_graph(spark, monkeypatch, limit):
    from hubloom.operators import packed

    rnd = random.Random(6)
    vids = list(range(150))
    arcs = sorted({(rnd.randrange(140), rnd.randrange(140)) for _ in range(300)})
    g = made(spark, arcs, vids).saved()
    monkeypatch.setattr(hub_ops, "EXACT_CLOSENESS", 10, raising=False)
    monkeypatch.setattr(packed, "PACKED_ARCS", limit)
    d = by_python(arcs, vids)
    assert rows(hub_ops.closeness(g), "vid", "closeness") == near_by_python(d, set(vids))
    some = {v for v in vids if v % 3}
    found = hub_ops.distance_sums(g, sorted(some), targets=g.vertices.where("vid % 3 <> 0"))
    assert rows(found, "vid", "reached", "total") == sorted((x, sum(a == x and b in some for a, b in d), sum(n for (a, b), n in d.items() if a == x and b in some)) for x in some)


def test_vertex_groups_are_joined_where_they_are_too_many_to_broadcast(spark, worked, monkeypatch):
    from hubloom.operators import pair_aggregate

    g, _ = worked
    plain = rows(lift_edges(g.edges, g.vertices, ["v_grp"]), "src", "tgt", "src_v_grp", "tgt_v_grp")
    monkeypatch.setattr(pair_aggregate, "BROADCAST_VERTICES", 2)
    assert rows(lift_edges(g.edges, g.vertices, ["v_grp"], access="broadcast"), "src", "tgt", "src_v_grp", "tgt_v_grp") == plain


def test_bounded_closure_holds_pairs_and_not_walks(spark):
    arcs = [(x, y) for x in range(120) for y in range(120) if x != y]  # 120 ** 3 walks of three steps
    found = reach_index.closure_by_recursion(made(spark, arcs), [0, 5], 3)
    assert rows(found, "hub", "vid") == [(h, v) for h in (0, 5) for v in range(120)]


def test_closure_limit_is_of_components(spark):
    arcs = [(i, (i + 1) % 30) for i in range(30)] + [(3, 40), (40, 41)]
    g = made(spark, arcs, [50]).saved()
    d = by_python(arcs, [*range(30), 40, 41, 50])
    assert rows(reach_index.transitive_closure(g, limit=20), "src", "tgt") == sorted(d)
    assert rows(reach_index.tags_from_closure(reach_index.condensed_closure(g, 20), [3, 41]), "vid", "s0", "r0") == rows(tag_vertices(g, [3, 41]), "vid", "s0", "r0")


@pytest.mark.parametrize("name", ["graph_synthetic_edges", "source_generator"])
def test_generated_graphs_are_drawn_from_a_table(spark, sf_dir, name):
    con = duckdb.connect()
    con.execute(f"create view orders as select * from '{sf_dir}/orders.parquet'")
    ours = catalog.QUERIES[name](spark, sf_dir)
    assert any(f.endswith("orders.parquet") for f in ours.inputFiles())
    theirs = con.execute(catalog.SQL[name])
    names = [c[0] for c in theirs.description]
    assert sorted(tuple(r) for r in ours.select(*names).collect()) == sorted(theirs.fetchall())


def test_min_cut_of_a_large_part(spark):
    fan = lambda lo: spark.range(lo, lo + 110_000).selectExpr("1L as x", "2L as y", "1L as src", "id as tgt").unionAll(spark.range(lo, lo + 110_000).selectExpr("1L as x", "2L as y", "id as src", "3L as tgt"))
    last = spark.createDataFrame([(1, 2, 3, v) for v in (4, 5, 6)] + [(1, 2, v, 2) for v in (4, 5, 6, 10)] + [(1, 2, 5, 4)], "x long, y long, src long, tgt long")
    assert rows(structure.min_cut(fan(10).unionAll(last)), "x", "y", "cut") == [(1, 2, 4)]
    weighted = spark.createDataFrame([(1, 9, 1, 2, 5), (1, 9, 2, 9, 3), (1, 9, 1, 3, 2), (1, 9, 3, 2, 2), (1, 9, 3, 9, 1)], "x long, y long, src long, tgt long, w long")
    assert rows(structure.min_cut(weighted, "w"), "x", "y", "cut") == [(1, 9, 4)]


def test_labelled_indexes_count_edges_between_components(spark, monkeypatch):
    arcs = [(i, (i + 1) % 30) for i in range(30)] + [(3, 40), (40, 41), (41, 42)]
    monkeypatch.setattr(reach_index, "LABEL_EDGES", 5)
    for some, hubs in ((arcs, [3, 7, 41]), (arcs, [40, 9]), (arcs[:30], [3, 7])):  # with hubs of one component, and without an edge between
        g = made(spark, some).saved()
        plain = rows(tag_vertices(g, hubs), "vid", "s0", "r0")
        for method in ("tree_interval", "chain"):
            assert rows(reach_index.extract(g, hubs, method), "vid", "s0", "r0") == plain


def ladder(spark, n, width=3000):
    """Each vertex to those ``width`` and ``width + 1`` on: vertex v is at level ``v div width``."""
    e = spark.range(n).selectExpr("id as src", f"explode(array(id + {width}L, id + {width + 1}L)) as tgt")
    v = spark.range(n + width + 1).selectExpr("id as vid", "id % 3 as v_grp", "id + 1 as v_mr")
    return PropertyGraph(v, e).saved()


def test_levels_of_a_deep_graph_take_no_round_of_joins_each(spark, monkeypatch):
    steps = []

    def counted(df, label, **options):
        steps.append(label)
        if len(steps) > 30:
            raise AssertionError("a round of joins a level")
        return saved(df, label, **options)

    g = ladder(spark, 1_050_000)  # 2,100,000 arcs, 350 levels
    monkeypatch.setattr(cycles, "saved", counted)
    found = cycles.topo_levels(g)
    assert found.count() == 1_053_001 and found.where("level <> least(vid, 1052999L) div 3000").isEmpty()  # the last has no arc of 3000


@pytest.mark.parametrize("seed", range(12))
def test_components_and_levels_in_a_task(monkeypatch, seed):
    import numpy as np

    from hubloom.operators import dag

    rnd = random.Random(seed)
    n = rnd.choice([1, 6, 20, 40])
    arcs = [(rnd.randrange(n), rnd.randrange(n)) for _ in range(rnd.choice([0, n, 2 * n]))]
    monkeypatch.setattr(dag, "STEP_ARCS", rnd.choice([0, 3, 2_000_000]))
    monkeypatch.setattr(dag, "COLOUR_ROUNDS", rnd.choice([1, 200]))
    s, t = np.array([a for a, _ in arcs], dtype=np.int32), np.array([b for _, b in arcs], dtype=np.int32)
    ahead = {v: reach(arcs, v) for v in range(n)}
    assert dag.components(n, s, t).tolist() == [min(u for u in ahead[v] if v in ahead[u]) for v in range(n)]
    found = dag.Dag(n, s, t)
    level = found.level[found.comp]
    for v in range(n):
        before = [level[u] + 1 for u, w in arcs if v in ahead[w] and w in ahead[v] and u not in ahead[v]]
        assert level[v] == max(before, default=0)
    for index in (reach_index.TwoHop(found), reach_index.Chains(found)):  # of all vertices
        for v in range(n):
            assert set(np.flatnonzero(index.to_all(found.comp[v])[found.comp])) == ahead[v]
            assert set(np.flatnonzero(index.from_all(found.comp[v])[found.comp])) == {u for u in range(n) if v in ahead[u]}


@pytest.mark.parametrize("method", ["topological", "two_hop", "chain"])
def test_labelled_indexes_of_a_larger_graph(spark, method):
    g = ladder(spark, 300_000)  # 600,000 arcs
    back = spark.createDataFrame([(9_001, 0)], "src long, tgt long")
    g = PropertyGraph(g.vertices, g.edges.unionAll(back)).saved()
    hubs = [0, 150_007, 3_000, 400_000, 302_900]  # with two of one component, and one without an arc
    assert rows(reach_index.extract(g, hubs, method), "vid", "s0", "r0") == rows(tag_vertices(g, hubs), "vid", "s0", "r0")


@pytest.mark.parametrize("limit", [16_000_000, 0])
def test_pairs_of_many_hubs_need_no_tags(spark, monkeypatch, limit):
    from hubloom.operators import packed

    rnd = random.Random(8)
    arcs = [(i, (i + 1) % 60) for i in range(60)] + sorted({(a, b) for a, b in ((rnd.randrange(40, 110), rnd.randrange(60, 110)) for _ in range(60)) if a != b})
    g = made(spark, arcs, range(115)).saved()
    hubs = [v for v in range(115) if v % 7]
    monkeypatch.setattr(packed, "PACKED_ARCS", limit)
    made_tags = []
    monkeypatch.setattr(q.TagCache, "vertices", lambda self, graph, some, hops=None: made_tags.append(len(some)) or tag_vertices(graph, some, hops))
    result = q.explore(g).hubs(lambda x: hubs).between().run()
    d = by_python(arcs, hubs)
    assert rows(result.pairs, "x", "y") == sorted((x, y) for x, y in d if x != y and y % 7)
    assert bool(made_tags) == (limit == 0)
    ring = q.explore(made(spark, arcs[:60]).saved()).hubs(lambda x: list(range(60)) + [200, 201, 202, 203]).between().run()  # no arc between components
    assert ring.pairs.count() == 60 * 59
    inside = {v for v in range(115) if v in reach(arcs, 41) and 5 in reach(arcs, v)}
    assert {r["vid"] for r in result.zoom_edge(41, 5).vertices.collect()} == inside


def lattice_arcs():
    """A ring of 70 that 90 vertices lead to and 300 follow, most of these alone in their components."""
    rnd = random.Random(11)
    ring = [(v, (v + 1) % 70) for v in range(70)]
    return ring + [(100 + i, rnd.randrange(70)) for i in range(90)] + [(rnd.randrange(70), 200)] + sorted({tuple(sorted((rnd.randrange(200, 500), rnd.randrange(200, 500)))) for _ in range(500)})


def shuffled_by(df):
    """Whether rows of a plan are dealt or sorted after a task has made them."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return "Exchange" in plan[: plan.index("MapIn")]


def product_graph(spark, monkeypatch):
    from hubloom.operators import packed

    for name, n in (("PRODUCT_BLOCK", 128), ("STEP", 7), ("PIECE", 5), ("BATCH", 3)):
        monkeypatch.setattr(packed, name, n)
    arcs = [a for a in lattice_arcs() if a[0] != a[1]]
    g = made(spark, arcs, range(600, 610)).saved()
    return g, by_python(arcs, [r["vid"] for r in g.vertices.collect()])


def test_pairs_of_all_hubs_are_made_without_dealing_them(spark, monkeypatch):
    g, d = product_graph(spark, monkeypatch)
    hubs = sorted(r["vid"] for r in g.vertices.select("vid").collect())
    pairs = q.explore(g).hubs(lambda x: hubs).between().run().pairs
    assert rows(pairs, "x", "y") == sorted((x, y) for x, y in d if x != y)
    assert not shuffled_by(pairs)


def test_written_pairs_take_little_disk(spark, tmp_path):
    n = 25_000  # one component: places of its members fill more than the pages that a column has a dictionary for
    pairs = reach_index.pairs_of_many(PropertyGraph(spark.range(n).selectExpr("id as vid"), spark.range(n).selectExpr("id as src", f"(id + 1) % {n} as tgt")).saved(), list(range(0, n, 5)))
    pairs.write.parquet(str(tmp_path / "out"))
    assert sum(f.stat().st_size for f in (tmp_path / "out").rglob("*.parquet")) < (n // 5) ** 2  # a byte a pair
    assert spark.read.parquet(str(tmp_path / "out")).distinct().count() == (n // 5) * (n // 5 - 1)


def test_closure_is_read_without_dealing_its_pairs(spark, monkeypatch):
    g, d = product_graph(spark, monkeypatch)
    closure = reach_index.transitive_closure(g, limit=20)  # of more components than that, which is no limit of what is not kept
    assert rows(closure, "src", "tgt") == sorted(d)
    assert not shuffled_by(closure)


@pytest.mark.parametrize("arcs", [[], [(1, 2), (2, 1)]])
def test_closure_without_arcs_between_components(spark, arcs):
    g = made(spark, arcs, [1, 2, 3]).saved()
    assert rows(reach_index.transitive_closure(g), "src", "tgt") == sorted(by_python(arcs, [1, 2, 3]))


def test_tree_intervals_take_every_contact(spark, sf_dir):
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{sf_dir}/events.parquet'")
    arcs = con.execute("select distinct user_id, n from (select user_id, lead(user_id) over (order by ts, event_id) as n from events) where user_id <> n").fetchall()
    degree = {v: sum((a == v) + (b == v) for a, b in arcs) for v in {v for arc in arcs for v in arc}}
    hubs = sorted(degree, key=lambda v: (-degree[v], v))[:3]
    ahead = {v: reach(arcs, v) for v in degree}
    bits = lambda test: sum(1 << i for i, h in enumerate(hubs) if test(h))
    want = [(v, bits(lambda h: v in ahead[h]), bits(lambda h: h in ahead[v])) for v in sorted(degree)]
    found = catalog.QUERIES["extract_tree_interval"](spark, sf_dir)
    assert rows(found, "vid", "s0", "r0") == [r for r in want if r[1] or r[2]]
    assert sorted(con.execute(catalog.SQL["extract_tree_interval"]).fetchall()) == rows(found, "vid", "s0", "r0")
