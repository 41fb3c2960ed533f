"""Scopes: which part of the graph a query looks at."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.functions.bits import Tag, has_hub, mask_of, n_words, names, words_of  # noqa: F401
from hubloom.operators.frontier import arrivals
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.runtime import saved


def whole_graph(graph: PropertyGraph) -> PropertyGraph:
    return graph


def attribute_subgraph(graph: PropertyGraph, predicate: Column | str) -> PropertyGraph:
    return graph.filtered(predicate)


def _distances(graph: PropertyGraph, x: int, y: int, rounds: int | None) -> tuple[DataFrame, DataFrame]:
    found = arrivals(graph, [x, y], rounds)
    away = found.where((F.col("dir") == 0) & F.col("b0").bitwiseAND(F.lit(1)).cast("boolean")).select("vid", F.col("round").alias("d"))
    back = found.where((F.col("dir") == 1) & F.col("b0").bitwiseAND(F.lit(2)).cast("boolean")).select("vid", F.col("round").alias("d"))
    return saved(away, "away"), saved(back, "back")


def paths_between(graph: PropertyGraph, x: int, y: int, max_hops: int = 4, expand_if_farther: bool = True) -> PropertyGraph:
    """Vertices and edges on paths of at most ``max_hops`` from x to y; if y is farther, their distance is the bound."""
    if x == y:
        raise ValueError("the two ends are one vertex")
    hops = max_hops
    away, back = _distances(graph, x, y, hops)
    if expand_if_farther and away.where(F.col("vid") == y).isEmpty():
        far = arrivals(graph, [x], directions=(0,)).where(F.col("vid") == y).select("round").first()
        if far is not None:
            hops = far["round"]
            away, back = _distances(graph, x, y, hops)
    on = away.withColumnRenamed("d", "da").join(back.withColumnRenamed("d", "db"), "vid").where(F.col("da") + F.col("db") <= hops)
    ea = away.select(F.col("vid").alias("src"), F.col("d").alias("da"))
    eb = back.select(F.col("vid").alias("tgt"), F.col("d").alias("db"))
    edges = graph.edges.join(ea, "src").join(eb, "tgt").where(F.col("da") + 1 + F.col("db") <= hops).select(graph.edges.columns)
    return replace(graph, vertices=graph.vertices.join(on.select("vid"), "vid", "left_semi"), edges=edges)


def _inside(xs: list[int], ys: list[int]) -> Column:
    """In a part of some pair of the two hub sets."""
    out = F.lit(False)
    for x in xs:
        for y in ys:
            if x != y:
                out = out | (has_hub("s", x) & has_hub("r", y))
    return out


def induced(graph: PropertyGraph, vtags: DataFrame, hubs: list[int], x: int, y: int) -> PropertyGraph:
    """The part between two hubs, from known tags: a filter, no traversal."""
    inside = vtags.where(_inside([hubs.index(x)], [hubs.index(y)])).select("vid")
    return graph.induced_by(inside)


def induced_union(graph: PropertyGraph, vtags: DataFrame, hubs: list[int], some: list[int]) -> PropertyGraph:
    """The union of the parts between the pairs of some hubs."""
    at = [hubs.index(h) for h in some]
    keep = _inside(at, at)
    vertices = graph.vertices.join(vtags.where(keep).select("vid"), "vid", "left_semi")
    n = n_words(len(hubs))
    cols = [*names("s", n), *names("r", n)]
    end = lambda e: vtags.select(F.col("vid").alias(e), *[F.col(c).alias(f"{e}_{c}") for c in cols])
    both = graph.edges.join(end("src"), "src").join(end("tgt"), "tgt")
    tagged = both.select(*graph.edges.columns, *[F.col(f"src_{c}").bitwiseAND(F.col(f"tgt_{c}")).alias(c) for c in cols])
    return replace(graph, vertices=vertices, edges=tagged.where(keep).select(graph.edges.columns))
