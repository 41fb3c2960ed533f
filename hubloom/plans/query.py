"""Exploration queries: a graph, a scope, hubs, a grouping of elements by hub pair, and summaries.

A query runs as lazy DataFrame plans but for the hubs (k ids on the driver) and
what an operator decides by; summaries of attributes of one query share tags and
one pass over the elements.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg
from hubloom.operators import hubs as hub_ops
from hubloom.operators import scope as scope_ops
from hubloom.operators import structure
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.pair_aggregate import aggregate_membership, aggregate_pairs, lift_edges
from hubloom.operators.reach_index import pairs_of_many
from hubloom.operators.runtime import saved
from hubloom.operators.tags import TagCache, between_hops_total, hub_pairs, membership, tag_edges
from hubloom.operators.simple_paths import simple_path_members
from hubloom.plans.result import HubSummaryGraph


#: Hubs of one word of bits; where only pairs are asked of more, no tags are made.
MANY_HUBS = 63


@dataclass(frozen=True)
class Grouping:
    """``between`` by reachability, ``hops`` for a bound on each side, ``total`` for one on the whole path, or ``custom``.

    ``simple_paths``: what lies on a path without repeated vertices, on graphs whose edges go both ways.
    """

    hops: int | None = None
    mode: str = "per_side"
    edge_rule: str | None = None
    custom: Callable[[PropertyGraph, list[int]], DataFrame] | None = None
    simple_paths: bool = False

    def __post_init__(self) -> None:
        if self.simple_paths:
            if self.custom is not None or self.hops is not None:
                raise ValueError("simple paths take no bound and no grouping of one's own")
            object.__setattr__(self, "custom", simple_path_members)

    @property
    def rectangular(self) -> bool:
        return self.custom is None and self.mode == "per_side"

    @property
    def rule(self) -> str:
        return self.edge_rule or ("tag" if self.hops is None else "endpoints")


@dataclass(frozen=True)
class Summary:
    """``kind``: ``vertex`` or ``edge`` aggregate (by ``dims``), or a structural one by name."""

    name: str
    kind: str
    agg: Agg | None = None
    dims: tuple[str, ...] = ()
    options: dict[str, Any] = field(default_factory=dict, hash=False)


@dataclass(frozen=True)
class ExplorationQuery:
    graph: PropertyGraph
    hubs: Callable[[PropertyGraph], list[int]]
    grouping: Grouping = Grouping()
    summaries: tuple[Summary, ...] = ()
    scope: Callable[[PropertyGraph], PropertyGraph] = scope_ops.whole_graph
    arguments: tuple[int, ...] = ()
    method: str = "sharing"

    def run(self, cache: TagCache | None = None) -> HubSummaryGraph:
        return run_query(self, cache or TagCache())


# -- summaries of a query -------------------------------------------------------------
def vertex_count(name: str = "vertices") -> Summary:
    return Summary(name, "vertex", Agg("count", None, name))


def vertex_agg(kind: str, column: str, dims: tuple[str, ...] = (), name: str = "") -> Summary:
    agg = Agg(kind, column, name)
    return Summary(agg.name, "vertex", agg, dims)


def edge_agg(kind: str, column: str | None, dims: tuple[str, ...] = (), name: str = "") -> Summary:
    agg = Agg(kind, column, name)
    return Summary(agg.name, "edge", agg, dims)


def edge_count_by(column: str, name: str = "edges") -> Summary:
    return Summary(name, "edge", Agg("count", None, name), (column,))


def structural(name: str, **options: Any) -> Summary:
    if name not in STRUCTURE:
        raise ValueError(f"unknown summary: {name}")
    return Summary(name, name, options=options)


STRUCTURE: dict[str, Callable] = {
    "shortest_distance": lambda g, h, o: structure.shortest_distance(g, h, **o),
    "shortest_path": lambda g, h, o: structure.shortest_path(g, h, **o),
    "weighted_distance": lambda g, h, o: structure.weighted_distance(g, h, **o),
    "relationship_strength": lambda g, h, o: structure.relationship_strength(g, h, **o),
    "relationship_type": lambda g, h, o: structure.relationship_type(g, h, **o),
    "min_cut": None,  # of each part: see below
}


def aggregate_graph(v_measures: list[Agg], e_measures: list[Agg], v_dims: tuple[str, ...] = ("v_grp",), e_dims: tuple[str, ...] = ("e_grp",)) -> tuple[Summary, ...]:
    """Super vertices by vertex groups, and super edges by the groups of both ends and of the edge."""
    lifted = tuple(f"src_{d}" for d in v_dims) + e_dims + tuple(f"tgt_{d}" for d in v_dims)
    return (*[Summary(a.name, "vertex", a, v_dims) for a in v_measures], *[Summary(a.name, "edge", a, lifted) for a in e_measures])


def group_values(long: DataFrame, dims: list[str], values: list[str], name: str) -> DataFrame:
    """One row a pair: its groups and their values as an ordered list."""
    return long.groupBy("x", "y").agg(F.sort_array(F.collect_list(F.struct(*dims, *values))).alias(name))


# -- running ----------------------------------------------------------------------
def run_query(query: ExplorationQuery, cache: TagCache) -> HubSummaryGraph:
    graph = query.scope(query.graph)
    found = query.hubs(graph)
    hubs = hub_ops.ensure_hubs(found, list(query.arguments))
    if not hubs:
        return _one_summary(graph, query)
    if query.grouping.custom is not None or not query.grouping.rectangular:
        return _by_membership(graph, hubs, query)
    if len(hubs) > MANY_HUBS and not query.summaries and query.grouping.hops is None:
        pairs = pairs_of_many(graph, hubs)
        if pairs is not None:
            return HubSummaryGraph(_attributes(graph, hubs), pairs, {}, hubs, graph, lambda: cache.vertices(graph, hubs, None))
    vtags = cache.vertices(graph, hubs, query.grouping.hops)
    vids = F.array(*map(F.lit, hubs))
    named = lambda d: d.select(F.element_at(vids, F.col("x") + 1).alias("x"), F.element_at(vids, F.col("y") + 1).alias("y"))
    pairs = saved(named(hub_pairs(vtags, hubs)), "pairs")
    tables: dict[str, DataFrame] = {}
    for element in ("vertex", "edge"):
        by_dims: dict[tuple[str, ...], list[Summary]] = {}
        for s in query.summaries:
            if s.kind == element:
                by_dims.setdefault(s.dims, []).append(s)
        if not by_dims:
            continue
        if element == "vertex":
            tagged = graph.vertices.join(vtags, "vid")
        else:
            lifted = sorted({d[4:] for dims in by_dims for d in dims if d[:4] in ("src_", "tgt_")})
            edges = replace(graph, edges=lift_edges(graph.edges, graph.vertices, lifted)) if lifted else graph
            tagged = tag_edges(edges, vtags, len(hubs), query.grouping.rule)
        for dims, some in by_dims.items():  # summaries by the same groups are one aggregate
            out = aggregate_pairs(tagged, hubs, list(dims), [s.agg for s in some], method=query.method)
            tables["+".join(s.name for s in some)] = out
    for s in query.summaries:
        if s.kind == "min_cut":
            etags = tag_edges(graph, vtags, len(hubs), query.grouping.rule)
            keep = ["src", "tgt", *filter(None, [s.options.get("capacity")])]
            listed = membership(etags, len(hubs), *keep)
            tables[s.name] = structure.min_cut(listed.select(F.element_at(vids, F.col("x") + 1).alias("x"), F.element_at(vids, F.col("y") + 1).alias("y"), *keep), **s.options)
        elif s.kind in STRUCTURE and query.grouping.hops is None:
            # All paths between two hubs lie in their part, so the whole graph gives what the part would.
            tables[s.name] = STRUCTURE[s.kind](graph, hubs, s.options)
    bounded = [s for s in query.summaries if s.kind in STRUCTURE and s.kind != "min_cut"] if query.grouping.hops is not None else []
    if bounded:
        at = lambda c: F.element_at(vids, F.col(c) + 1).alias(c)
        listed = membership(vtags, len(hubs), "vid").select(at("x"), at("y"), "vid")
        held = membership(tag_edges(graph, vtags, len(hubs), query.grouping.rule), len(hubs), *graph.edges.columns)
        tables |= _of_parts(graph, listed, held.select(at("x"), at("y"), *graph.edges.columns), bounded)
    return HubSummaryGraph(_attributes(graph, hubs), pairs, tables, hubs, graph, vtags, query.grouping.hops)


def _attributes(graph: PropertyGraph, hubs: list[int]) -> DataFrame:
    own = graph.vertices.sparkSession.createDataFrame([(h,) for h in hubs], "vid long")
    return graph.vertices.join(F.broadcast(own), "vid", "left_semi")


def _of_parts(graph: PropertyGraph, listed: DataFrame, inside: DataFrame, summaries: list[Summary]) -> dict[str, DataFrame]:
    """Structural summaries on the parts themselves: ``listed(x, y, vid)`` and their edges ``inside(x, y, src, tgt, ..)``."""
    tables: dict[str, DataFrame] = {}
    parts = None
    for s in summaries:
        if s.kind == "min_cut":
            tables[s.name] = structure.min_cut(inside, **s.options)
            continue
        options = dict(s.options)
        some = parts = parts or structure.Parts(listed, inside)
        if s.kind == "relationship_strength":  # trust is an edge's own, whatever part it is in
            shares = structure.trust_shares(graph.edges, options.pop("trust", "freq")).withColumnRenamed("p", "trust")
            some = structure.Parts(listed, inside.select("x", "y", "src", "tgt").join(shares, ["src", "tgt"]))
            options |= {"trust": "trust", "known": True}
        tables[s.name] = some.back(STRUCTURE[s.kind](some.graph, some.hubs, options))
    return tables


def _one_summary(graph: PropertyGraph, query: ExplorationQuery) -> HubSummaryGraph:
    """No hub: one summary of the whole graph, under a pair of nulls."""
    none = [F.lit(None).cast("long").alias("x"), F.lit(None).cast("long").alias("y")]
    tables: dict[str, DataFrame] = {}
    for s in query.summaries:
        if s.kind not in ("vertex", "edge"):
            raise ValueError(f"{s.kind} is of two hubs, and there is none")
        rows = graph.vertices if s.kind == "vertex" else lift_edges(graph.edges, graph.vertices, sorted({d[4:] for d in s.dims if d[:4] in ("src_", "tgt_")}))
        starts = [c.alias(n) for n, (c, _) in s.agg.states().items()]
        tables[s.name] = rows.groupBy(*s.dims).agg(*starts).select(*none, *s.dims, s.agg.finish())
    pairs = graph.vertices.sparkSession.range(1).select(*none)
    return HubSummaryGraph(graph.vertices.limit(0), pairs, tables, [], graph, None, None)


def _by_membership(graph: PropertyGraph, hubs: list[int], query: ExplorationQuery) -> HubSummaryGraph:
    """Any grouping of vertices by pair; edges are in a pair when both ends are."""
    if query.grouping.custom is not None:
        listed = saved(query.grouping.custom(graph, hubs), "members")
    else:
        numbered = between_hops_total(graph, hubs, query.grouping.hops)
        vids = F.array(*map(F.lit, hubs))
        listed = saved(numbered.select(F.element_at(vids, F.col("x") + 1).alias("x"), F.element_at(vids, F.col("y") + 1).alias("y"), "vid"), "members")
    pairs = listed.select("x", "y").distinct()
    tables: dict[str, DataFrame] = {}
    ends = graph.edges.select("src", "tgt").distinct()
    held = listed.select("x", "y", F.col("vid").alias("src")).join(ends, "src").join(listed.select("x", "y", F.col("vid").alias("tgt")), ["x", "y", "tgt"])
    for s in query.summaries:
        if s.kind == "vertex":
            tables[s.name] = aggregate_membership(listed, graph.vertices, "vid", list(s.dims), [s.agg])
        elif s.kind == "edge":
            edges = lift_edges(graph.edges, graph.vertices, sorted({d[4:] for d in s.dims if d[:4] in ("src_", "tgt_")}))
            both = held.select("x", "y", F.struct("src", "tgt").alias("eid"))
            tables[s.name] = aggregate_membership(both, edges.withColumn("eid", F.struct("src", "tgt")), "eid", list(s.dims), [s.agg])
    if rest := [s for s in query.summaries if s.kind in STRUCTURE]:
        tables |= _of_parts(graph, listed, held.join(graph.edges, ["src", "tgt"]), rest)
    return HubSummaryGraph(_attributes(graph, hubs), pairs, tables, hubs, graph, None, query.grouping.hops)


# -- fluent form ----------------------------------------------------------------------
@dataclass(frozen=True)
class Builder:
    query: ExplorationQuery

    def within(self, scope: Callable[[PropertyGraph], PropertyGraph], *arguments: int) -> Builder:
        return Builder(replace(self.query, scope=scope, arguments=arguments))

    def hubs(self, selector: Callable[[PropertyGraph], list[int]]) -> Builder:
        return Builder(replace(self.query, hubs=selector))

    def between(self, hops: int | None = None, **options: Any) -> Builder:
        return Builder(replace(self.query, grouping=Grouping(hops, **options)))

    def summarize(self, *summaries: Summary) -> Builder:
        return Builder(replace(self.query, summaries=(*self.query.summaries, *summaries)))

    def using(self, method: str) -> Builder:
        return Builder(replace(self.query, method=method))

    def run(self, cache: TagCache | None = None) -> HubSummaryGraph:
        return self.query.run(cache)


def explore(graph: PropertyGraph) -> Builder:
    return Builder(ExplorationQuery(graph, lambda g: hub_ops.top_degree(g, 3)))
