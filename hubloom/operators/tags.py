"""Tags: for each vertex or edge, the hub pairs whose in-between part it lies in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.functions.bits import any_bit, members, n_words, names
from hubloom.operators.frontier import arrivals, hub_distances
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.runtime import LOCAL_EDGES, saved


def tags_from(found: DataFrame, k: int) -> DataFrame:
    """``(vid, s0.., r0..)`` of vertices with an arrival: S, the hubs that reach it, R, the hubs it reaches."""
    side = lambda d, s: [F.coalesce(F.bit_or(F.when(F.col("dir") == d, F.col(b))), F.lit(0)).alias(f"{s}{w}") for w, b in enumerate(names("b", n_words(k)))]
    return found.groupBy("vid").agg(*side(0, "s"), *side(1, "r"))


def tag_vertices(graph: PropertyGraph, hubs: list[int], hops: int | None = None, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """Vertex tags by plain reachability, or within ``hops`` on either side."""
    return tags_from(arrivals(graph, hubs, hops, local_edges=local_edges), len(hubs))


def live(tagged: DataFrame, k: int) -> DataFrame:
    """Only what lies in some part: both sets are non-empty."""
    n = n_words(k)
    return tagged.where(any_bit("s", n) & any_bit("r", n))


def tag_edges(graph: PropertyGraph, vtags: DataFrame, k: int, rule: str = "tag") -> DataFrame:
    """Edges with tags.  ``tag``: S of the source, R of the target; ``endpoints``: the pairs both ends are in."""
    n = n_words(k)
    cols = [*names("s", n), *names("r", n)]
    at = lambda end: vtags.select(F.col("vid").alias(end), *[F.col(c).alias(f"{end}_{c}") for c in cols])
    both = graph.edges.join(at("src"), "src").join(at("tgt"), "tgt")
    if rule == "tag":
        made = [F.col(f"src_{c}").alias(c) for c in names("s", n)] + [F.col(f"tgt_{c}").alias(c) for c in names("r", n)]
    elif rule == "endpoints":
        made = [F.col(f"src_{c}").bitwiseAND(F.col(f"tgt_{c}")).alias(c) for c in cols]
    else:
        raise ValueError(f"unknown edge rule: {rule}")
    return both.select(*[F.col(c) for c in graph.edges.columns], *made)


def hub_pairs(vtags: DataFrame, hubs: list[int]) -> DataFrame:
    """``(x, y)`` hub numbers of the pairs with a non-empty part: y is among the hubs that x reaches."""
    spark = vtags.sparkSession
    numbered = spark.createDataFrame(list(enumerate(hubs)), "x int, vid long")
    return vtags.join(F.broadcast(numbered), "vid").select("x", F.explode(members("r", len(hubs))).alias("y")).where("x <> y")


def membership(tagged: DataFrame, k: int, *keep: str) -> DataFrame:
    """One row for each element and pair it is in; made on demand only."""
    one = tagged.select(*keep, F.explode(members("s", k)).alias("x"), *names("r", n_words(k)))
    return one.select(*keep, "x", F.explode(members("r", k)).alias("y")).where("x <> y")


def between_hops_total(graph: PropertyGraph, hubs: list[int], hops: int) -> DataFrame:
    """``(x, y, vid)`` with ``d(x, v) + d(v, y) <= hops``; such parts are no products, so they are listed."""
    d = saved(hub_distances(arrivals(graph, hubs, hops), len(hubs)), "dist")
    a = d.where("dir = 0").select("vid", F.col("hub").alias("x"), F.col("d").alias("d1"))
    b = d.where("dir = 1").select("vid", F.col("hub").alias("y"), F.col("d").alias("d2"))
    return a.join(b, "vid").where((F.col("x") != F.col("y")) & (F.col("d1") + F.col("d2") <= hops)).select("x", "y", "vid")


class TagCache:
    """Tags by graph, hubs and bound: a zoom or a second query on one graph traverses nothing again."""

    def __init__(self) -> None:
        self.known: dict[tuple, tuple[DataFrame, DataFrame]] = {}  # with the edges, so that their identity stays taken

    def vertices(self, graph: PropertyGraph, hubs: list[int], hops: int | None = None) -> DataFrame:
        key = (id(graph.edges), tuple(hubs), hops)
        if key not in self.known:
            self.known[key] = (graph.edges, saved(tag_vertices(graph, hubs, hops), "tags"))
        return self.known[key][1]
