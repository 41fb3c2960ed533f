"""Structural summaries of hub pairs: distances, paths, trust, path labels, minimum cuts."""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.functions.bits import members
from hubloom.operators.frontier import arrivals
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.hubs import DistanceIndex
from hubloom.operators.runtime import saved


def _hub_rows(graph: PropertyGraph, hubs: list[int]) -> DataFrame:
    return graph.vertices.sparkSession.createDataFrame([(h,) for h in hubs], "vid long")


def _vid(hubs: list[int], number: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, hubs)), number + 1)


def hub_distance_table(graph: PropertyGraph, hubs: list[int], max_hops: int | None = None) -> DataFrame:
    """``(x, vid, d)``: hop distance from each hub (by vertex id) to what it reaches; one search for all hubs."""
    found = arrivals(graph, hubs, max_hops, directions=(0,))
    return found.select(F.explode(members("b", len(hubs))).alias("i"), "vid", F.col("round").alias("d")).select(_vid(hubs, F.col("i")).alias("x"), "vid", "d")


def shortest_distance(graph: PropertyGraph, hubs: list[int], max_hops: int | None = None, index: DistanceIndex | None = None) -> DataFrame:
    """``(x, y, distance)`` of hub pairs; with ``index``, looked up among known distances."""
    at = F.broadcast(_hub_rows(graph, hubs))
    if index is not None:
        some = index.pairs(_hub_rows(graph, hubs), _hub_rows(graph, hubs))
        return some.where("src <> tgt").select(F.col("src").alias("x"), F.col("tgt").alias("y"), F.col("d").alias("distance"))
    return hub_distance_table(graph, hubs, max_hops).join(at, "vid", "left_semi").where("x <> vid").select("x", F.col("vid").alias("y"), F.col("d").alias("distance"))


def shortest_path(graph: PropertyGraph, hubs: list[int], max_hops: int | None = None) -> DataFrame:
    """``(x, y, path array<long>)``: from y back, the smallest predecessor that is one hop nearer to x."""
    dist = saved(hub_distance_table(graph, hubs, max_hops), "dist")
    at = F.broadcast(_hub_rows(graph, hubs))
    open_ = saved(dist.join(at, "vid", "left_semi").where("x <> vid").select("x", F.col("vid").alias("y"), F.col("vid").alias("node"), "d", F.array("vid").alias("path")), "walk")
    done = None
    arcs = graph.edges.select("src", "tgt")
    while not open_.isEmpty():
        ended = open_.where("d = 0").select("x", "y", "path")
        done = ended if done is None else done.unionAll(ended)
        before = dist.select(F.col("x").alias("bx"), F.col("vid").alias("src"), F.col("d").alias("bd"))
        step = (
            open_.where("d > 0").join(arcs, F.col("node") == F.col("tgt")).join(before, ["src"])
            .where((F.col("bx") == F.col("x")) & (F.col("bd") == F.col("d") - 1))
            .groupBy("x", "y", "d", "path").agg(F.min("src").alias("node"))
        )
        open_ = saved(step.select("x", "y", "node", (F.col("d") - 1).alias("d"), F.concat(F.array("node"), "path").alias("path")), "walk")
    if done is None:
        return graph.vertices.sparkSession.createDataFrame([], "x long, y long, path array<long>")
    return done


def weighted_distance(graph: PropertyGraph, hubs: list[int], weight: str, max_hops: int | None = None) -> DataFrame:
    """``(x, y, distance)`` by least sum of non-negative weights: rounds relax only what improved."""
    arcs = saved(graph.edges.groupBy("src", "tgt").agg(F.min(weight).cast("long").alias("w")), "arcs")
    if not arcs.where("w < 0").isEmpty():
        raise ValueError("weights must not be negative")
    best = saved(_hub_rows(graph, hubs).select(F.col("vid").alias("x"), "vid", F.lit(0).cast("long").alias("dist")), "best")
    fresh, rounds = best, 0
    while (max_hops is None or rounds < max_hops) and not fresh.isEmpty():
        rounds += 1
        reached = fresh.join(arcs, F.col("vid") == F.col("src")).groupBy("x", F.col("tgt").alias("vid")).agg(F.min(F.col("dist") + F.col("w")).alias("n"))
        fresh = saved(reached.join(best, ["x", "vid"], "left").where("dist is null or n < dist").select("x", "vid", F.col("n").alias("dist")), "fresh")
        best = saved(best.unionAll(fresh).groupBy("x", "vid").agg(F.min("dist").alias("dist")), "best")
    at = F.broadcast(_hub_rows(graph, hubs))
    return best.join(at, "vid", "left_semi").where("x <> vid").select("x", F.col("vid").alias("y"), F.col("dist").alias("distance"))


def trust_shares(edges: DataFrame, trust: str) -> DataFrame:
    """``(src, tgt, p)``: the share of what a source gives that goes to each target."""
    arcs = edges.groupBy("src", "tgt").agg(F.sum(trust).alias("w"))
    total = arcs.groupBy("src").agg(F.sum("w").alias("t"))
    return arcs.join(total, "src").select("src", "tgt", (F.col("w") / F.col("t")).alias("p"))


class Parts:
    """Listed parts as one graph of disjoint copies, so that an operator on graphs works on every part by itself.

    ``members(x, y, vid)`` and ``inside(x, y, src, tgt, ..)``; the copy of a vertex
    is its id and its pair's number in one integer, in the order of ids.
    """

    def __init__(self, members: DataFrame, inside: DataFrame):
        spark = members.sparkSession
        pairs = sorted(tuple(r) for r in members.select("x", "y").distinct().collect())  # pairs of hubs
        ends = members.agg(F.least(F.min("vid"), F.min("x"), F.min("y")), F.greatest(F.max("vid"), F.max("x"), F.max("y"))).first()
        self.least, most = (ends[0], ends[1]) if pairs else (0, 0)
        self.span = most - self.least + 1
        if self.span * (len(pairs) + 1) >= 2**63:
            raise ValueError("ids and pairs do not fit in one integer")
        numbered = F.broadcast(spark.createDataFrame([(i, x, y) for i, (x, y) in enumerate(pairs)], "part long, x long, y long"))
        at = lambda c: (F.col("part") * self.span + F.col(c) - self.least).alias(c)
        rest = [c for c in inside.columns if c not in ("x", "y", "src", "tgt")]
        vertices = members.join(numbered, ["x", "y"]).select(at("vid"))
        edges = inside.join(numbered, ["x", "y"]).select(at("src"), at("tgt"), *rest)
        self.graph = PropertyGraph(vertices, edges, name="parts").saved()
        self.hubs = [i * self.span + v - self.least for i, (x, y) in enumerate(pairs) for v in (x, y)]

    def back(self, found: DataFrame) -> DataFrame:
        """A result by pair of copies as one by pair of hubs, from the first hub of a part to its second."""
        own = lambda c: F.col(c) % self.span + self.least
        keep = [c for c in found.columns if c not in ("x", "y")]
        known = F.broadcast(found.sparkSession.createDataFrame(list(zip(self.hubs[::2], self.hubs[1::2], strict=True)), "x long, y long"))
        one = lambda c: F.transform(c, lambda v: v % self.span + self.least).alias(c) if c == "path" else F.col(c)
        return found.join(known, ["x", "y"], "left_semi").select(own("x").alias("x"), own("y").alias("y"), *[one(c) for c in keep])


def relationship_strength(graph: PropertyGraph, hubs: list[int], trust: str = "freq", combine: str = "max_product", max_hops: int = 4, known: bool = False) -> DataFrame:
    """``(x, y, strength)``: trust of an edge is its share of what its source gives; a path's is the product.

    ``known``: the column ``trust`` holds such shares already (of a larger graph).

    ``max_product`` takes the best path of at most ``max_hops``, ``sum_walks``
    adds all walks of at most that length.
    """
    arcs = saved(graph.edges.groupBy("src", "tgt").agg(F.max(trust).alias("p")) if known else trust_shares(graph.edges, trust), "trust")
    how = F.max if combine == "max_product" else F.sum
    if combine not in ("max_product", "sum_walks"):
        raise ValueError(f"unknown combination: {combine}")
    front = _hub_rows(graph, hubs).select(F.col("vid").alias("x"), "vid", F.lit(1.0).alias("p"))
    found = None
    for _ in range(max_hops):
        step = front.join(arcs.withColumnRenamed("p", "q"), F.col("vid") == F.col("src"))
        front = saved(step.groupBy("x", F.col("tgt").alias("vid")).agg(how(F.col("p") * F.col("q")).alias("p")), "front")
        found = front if found is None else found.unionAll(front)
    at = F.broadcast(_hub_rows(graph, hubs))
    return found.join(at, "vid", "left_semi").where("x <> vid").groupBy("x", F.col("vid").alias("y")).agg(F.round(how("p"), 6).alias("strength"))


def relationship_type(graph: PropertyGraph, hubs: list[int], label: str = "rel", sep: str = ">", max_hops: int | None = None) -> DataFrame:
    """``(x, y, type)``: labels along the shortest path, in order."""
    paths = shortest_path(graph, hubs, max_hops)
    steps = paths.select("x", "y", F.posexplode(F.arrays_zip(F.slice("path", 1, F.size("path") - 1).alias("a"), F.slice("path", 2, F.size("path") - 1).alias("b"))).alias("at", "step"))
    arcs = graph.edges.groupBy("src", "tgt").agg(F.min(label).alias("label"))
    named = steps.join(arcs, (F.col("step.a") == F.col("src")) & (F.col("step.b") == F.col("tgt")))
    ordered = F.transform(F.sort_array(F.collect_list(F.struct("at", "label"))), lambda s: s["label"])
    return named.groupBy("x", "y").agg(F.array_join(ordered, sep).alias("type"))


def max_flow(arcs: list[tuple[int, int, int]], x: int, y: int) -> tuple[int, list[tuple[int, int]]]:
    """Value of a minimum cut between x and y, and its arcs, by blocking flows on level graphs."""
    a, b, c = (np.array([arc[i] for arc in arcs], dtype=np.int64) for i in range(3))
    flow, cut = _flow(a, b, c, x, y)
    return flow, [(int(a[i]), int(b[i])) for i in cut]


def _flow(a: np.ndarray, b: np.ndarray, c: np.ndarray, x: int, y: int) -> tuple[int, np.ndarray]:
    """The same on arrays: value, and places of the cut's arcs.  Python steps over arcs of shortest paths only."""
    vids, code = np.unique(np.concatenate([a, b, [x, y]]), return_inverse=True)
    m, source, sink = len(a), int(code[-2]), int(code[-1])
    tail, head = code[:m].astype(np.int32), code[m : 2 * m].astype(np.int32)
    room, back, flow = c.copy(), np.zeros(m, np.int64), 0
    while True:
        level, r = np.full(len(vids), -1), 0
        level[source] = 0
        while level[sink] < 0:
            hot = level == r
            found = np.concatenate([head[hot[tail] & (room > 0)], tail[hot[head] & (back > 0)]])
            found = found[level[found] < 0]
            if not len(found):
                break
            r += 1
            level[found] = r
        if level[sink] < 0:
            return flow, np.flatnonzero((level[tail] >= 0) & (level[head] < 0) & (c > 0))
        out: dict[int, list[tuple[int, int, int]]] = defaultdict(list)  # (to, arc, 1 along it or -1)
        keep = np.zeros(len(vids), bool)
        keep[sink] = True
        for depth in range(r, 0, -1):
            near, far = level == depth - 1, keep & (level == depth)
            for u, v, free, way in ((tail, head, room, 1), (head, tail, back, -1)):
                some = np.flatnonzero(near[u] & far[v] & (free > 0))
                keep[u[some]] = True
                for i, p, q in zip(some.tolist(), u[some].tolist(), v[some].tolist(), strict=True):
                    out[p].append((q, i, way))
        free = lambda i, way: int(room[i] if way > 0 else back[i])
        path: list[tuple[int, int, int]] = []  # (from, arc, way)
        u = source
        while True:
            if u == sink:
                push = min(free(i, way) for _, i, way in path)
                flow += push
                for _, i, way in path:
                    room[i] -= push * way
                    back[i] += push * way
                path, u = [], source
            elif out[u]:
                v, i, way = out[u][-1]
                if free(i, way) > 0:
                    path.append((u, i, way))
                    u = v
                else:
                    out[u].pop()
            elif path:
                u, _, _ = path.pop()
                out[u].pop()
            else:
                break


def min_cut(edge_members: DataFrame, capacity: str | None = None) -> DataFrame:
    """``(x, y, cut)`` from edges listed by pair: ``(x, y, src, tgt[, capacity])``, x and y being vertex ids; a task holds the edges of a pair."""
    cap = F.lit(1) if capacity is None else F.col(capacity)
    arcs = edge_members.groupBy("x", "y", "src", "tgt").agg(F.sum(cap).cast("long").alias("c"))

    def cut(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        value, _ = _flow(pdf["src"].to_numpy(), pdf["tgt"].to_numpy(), pdf["c"].to_numpy(), int(key[0]), int(key[1]))
        return pd.DataFrame({"x": [key[0]], "y": [key[1]], "cut": [value]})

    return arcs.groupBy("x", "y").applyInPandas(cut, "x long, y long, cut long")
