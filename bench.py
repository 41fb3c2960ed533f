"""Bench: the aggregate workload by both methods over hub count, group cardinality, degree and size.

Prints one JSON line.  ``BENCH_SF_DIR`` and ``BENCH_CPUS`` choose tables and
cores.  A time is that of the aggregate query alone (tags are known, as with an
index), the mean of three runs after the first of a graph; runs of over
``LONG_S`` seconds are not repeated.  ``sn`` is the baseline, ``as`` sharing,
``eq`` its early stop at equal tags.  Cardinality counts group-by values of
vertices and edges together.  Points beyond the time budget get their counts of
add operations only.  ``phases`` splits a whole query, ``crossover`` is the
least cardinality at which the baseline is faster.
"""

from __future__ import annotations

import json
import os
import sys
import time
from collections.abc import Callable
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import DataFrame, SparkSession  # noqa: E402

from hubloom.functions.aggregates import Agg  # noqa: E402
from hubloom.operators import hubs as hub_ops  # noqa: E402
from hubloom.operators.graph import PropertyGraph  # noqa: E402
from hubloom.operators.pair_aggregate import aggregate_pairs, combine_equal_tags, lift_edges, tag_groups  # noqa: E402
from hubloom.operators.runtime import saved  # noqa: E402
from hubloom.operators.tags import tag_edges, tag_vertices  # noqa: E402
from hubloom.plans.sharing import add_operations, plan_sharing  # noqa: E402
from hubloom.sources import graphs  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = int(os.environ.get("BENCH_RUNS", "3"))
#: Seconds after which points are counted and no longer timed, and after which no more are added.
BUDGET_S = float(os.environ.get("BENCH_BUDGET_S", "420"))
LONG_S = 2.5
E_DIMS = ["src_v_grp", "e_grp", "tgt_v_grp"]


def timed(fn: Callable[[], DataFrame], runs: int = RUNS) -> float:
    """Mean seconds."""
    took: list[float] = []
    while len(took) < runs and (not took or took[-1] < LONG_S):
        start = time.perf_counter()
        fn().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - start)
    return round(sum(took) / len(took), 3)


def cards(c: int) -> tuple[int, int]:
    """Cardinalities of the vertex and edge dimension that make ``c`` group-by values: v of vertices and v * v * e of edges."""
    v = max(1, round(c ** (1 / 3)))
    return v, max(1, round((c - v) / v**2))


class Case:
    """One graph with its hubs, tagged elements and both methods."""

    def __init__(self, graph: PropertyGraph, k: int):
        start = time.perf_counter()
        self.hubs = hub_ops.top_degree(graph, k)
        tags = saved(tag_vertices(graph, self.hubs), "tags")
        self.tag_s = round(time.perf_counter() - start, 3)
        start = time.perf_counter()
        lifted = PropertyGraph(graph.vertices, lift_edges(graph.edges, graph.vertices, ["v_grp"]))
        self.vertices = saved(graph.vertices.join(tags, "vid"), "tv").cache()
        self.edges = saved(tag_edges(lifted, tags, k), "te").cache()
        self.size = self.vertices.count() + self.edges.count()
        self.extract_s = round(time.perf_counter() - start, 3)
        self.k = k

    def run(self, method: str) -> DataFrame:
        v = aggregate_pairs(self.vertices, self.hubs, ["v_grp"], [Agg("sum", "v_mr", "total")], method)
        e = aggregate_pairs(self.edges, self.hubs, E_DIMS, [Agg("sum", "e_mr", "total")], method)
        return v.select("x", "y", "total").unionAll(e.select("x", "y", "total"))

    def adds(self) -> dict[str, int]:
        out = {"share_nothing": 0, "equal_tags": 0, "sharing": 0}
        self.plan_s = 0.0
        for tagged, dims in ((self.vertices, ["v_grp"]), (self.edges, E_DIMS)):
            groups = tag_groups(combine_equal_tags(tagged, self.k, dims, [Agg("count")]), self.k)
            start = time.perf_counter()
            plan = plan_sharing(groups)
            self.plan_s += time.perf_counter() - start
            for name, n in add_operations(plan).items():
                out[name] += n
        return out

    def done(self) -> None:
        self.vertices.unpersist()
        self.edges.unpersist()


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    began, queries, adds, phases = time.perf_counter(), {}, {}, {}
    warm = Case(graphs.part_flow(spark, SF_DIR, m=12).saved(), 5)
    for method in ("share_nothing", "equal_tags", "sharing"):
        warm.run(method).count()
    left = lambda: BUDGET_S - (time.perf_counter() - began)

    def point(name: str, graph: PropertyGraph, k: int) -> None:
        if left() < -120:
            return
        case = Case(graph, k)
        if left() > 0:
            for short, method in (("sn", "share_nothing"), ("as", "sharing"), ("eq", "equal_tags")):
                queries[f"{name}_{short}"] = timed(lambda m=method: case.run(m))
        n = case.adds()
        adds[name] = n | {"saved": round(1 - n["sharing"] / max(1, n["share_nothing"]), 3)}
        phases[name] = {"tagging": case.tag_s, "extraction": case.extract_s, "planning": round(case.plan_s, 3), "aggregation": queries.get(f"{name}_as")}
        case.done()

    def drawn(n: int, degree: int, c: int) -> PropertyGraph:
        v, e = cards(c)
        return graphs.synthetic_dag(spark, n, degree, v_card=v, e_card=e, locality=0.3).saved()

    flow = graphs.part_flow(spark, SF_DIR).saved()
    point("flow_k20", flow, 20)
    point("orders_k20", graphs.order_chain(spark, SF_DIR).saved(), 20)
    sizes = {"dense": 40, "sparse": 8}  # degrees of the tables, of 30,000 vertices
    for label, degree in sizes.items():
        for c in (10, 10_000):
            g = drawn(30_000, degree, c)
            for k in (5, 10, 20, 30, 40):
                point(f"{label}_c{c}_k{k}", g, k)
    for degree in (2, 8, 20, 40, 80):
        point(f"degree{degree}_k20", drawn(10_000, degree, 10_000), 20)
    for n in (10_000, 20_000, 40_000):
        for label, degree in sizes.items():
            point(f"size{n}_{label}_k20", drawn(n, degree, 10_000), 20)
    for label in sizes:
        for c in (100, 1000, 100_000):
            point(f"{label}_c{c}_k20", drawn(30_000, sizes[label], c), 20)
    for label, most in (("sparse", 200_000), ("dense", 1_000_000)):
        g = drawn(30_000, sizes[label], most)
        for k in (5, 20):
            point(f"{label}_c{most}_k{k}", g, k)
    crossover = {}
    for label in sizes:
        for k in (5, 10, 20, 30, 40):
            cells = sorted((int(q.split("_c")[1].split("_")[0]), t, queries[q[:-3] + "_as"]) for q, t in queries.items() if q.startswith(f"{label}_c") and q.endswith(f"_k{k}_sn"))
            crossover[f"{label}_k{k}"] = next((c for c, sn, shared in cells if sn < shared), None)
    mean = lambda some: round(sum(some) / len(some), 3) if some else None
    saved_by_degree = {"sparse": mean([adds[f"degree{d}_k20"]["saved"] for d in (2, 8, 20) if f"degree{d}_k20" in adds]), "dense": mean([adds[f"degree{d}_k20"]["saved"] for d in (40, 80) if f"degree{d}_k20" in adds])}
    total = round(sum(queries.values()), 3)
    out = {"metric": "aggregate_query_seconds", "value": total, "unit": "sec", "queries": queries, "sf": SF_DIR.rsplit("sf", 1)[-1]}
    print(json.dumps(out | {"adds": adds, "phases": phases, "crossover": crossover, "saved_by_degree": saved_by_degree}))


if __name__ == "__main__":
    main()
