"""Reachability indexes, and extraction of tags from them.

All answer the same question as the frontier; they trade building time and space
for look-ups without a traversal.  The closure is built by joins; the labelled
indexes are built in one task over the condensation, up to the arcs that a task
holds (tree intervals: ``LABEL_EDGES``), and refuse larger graphs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg
from hubloom.functions.bits import members, n_words, names, words_of
from hubloom.operators.cycles import condense, scc
from hubloom.operators.dag import TASK_ARCS, Dag, gathered
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.packed import fits, reached
from hubloom.operators.runtime import saved

#: Pairs of components in a closure, and edges of an index of tree intervals, whose outside edges are closed pair by pair.
CLOSURE_ROWS = 200_000_000
LABEL_EDGES = 500_000


@dataclass(frozen=True)
class Closure:
    """Components ``(vid, comp)`` and the pairs ``(a, b)`` of components of which the first reaches the second, itself included.

    The members of a component reach alike, so pairs of vertices are made when they are read.
    """

    comp: DataFrame
    pairs: DataFrame

    def rows(self, sources: DataFrame | None = None, targets: DataFrame | None = None) -> DataFrame:
        """``(src, tgt)`` of every reachable pair, each vertex reaching itself; of the given ``vid`` only."""
        side = lambda some, vid, comp: (self.comp if some is None else self.comp.join(F.broadcast(some.select("vid")), "vid", "left_semi")).select(F.col("vid").alias(vid), F.col("comp").alias(comp))
        return self.pairs.join(side(sources, "src", "a"), "a").join(side(targets, "tgt", "b"), "b").select("src", "tgt")


def condensed_closure(graph: PropertyGraph, limit: int = CLOSURE_ROWS) -> Closure:
    """The closure over components, by doubling the path length."""
    comp = saved(scc(graph), "comp")
    dag, _ = condense(graph, comp, [], [Agg("count")])
    own = dag.vertices.select(F.col("vid").alias("a"), F.col("vid").alias("b"))
    paths = saved(own.unionAll(dag.edges.select(F.col("src").alias("a"), F.col("tgt").alias("b"))).distinct(), "tc")
    n = paths.count()
    while True:
        if n > limit:
            raise ValueError("the closure of the components is over its size limit: use hub tags instead")
        longer = paths.select("a", F.col("b").alias("mid")).join(paths.select(F.col("a").alias("mid"), "b"), "mid").select("a", "b")
        paths = saved(longer.distinct(), "tc")
        n, before = paths.count(), n
        if n == before:
            return Closure(comp, paths)


def transitive_closure(graph: PropertyGraph, limit: int = CLOSURE_ROWS) -> DataFrame:
    """``(src, tgt)`` of every reachable pair, each vertex reaching itself, made when they are read.

    ``limit`` is of pairs of components where the arcs between these are too many to pack, and the closure is joined.
    """
    comp, dag = _condensed(graph)
    if not fits(dag):
        return condensed_closure(graph, limit).rows()
    return reached(dag, comp, comp).select(F.col("x").alias("src"), F.col("y").alias("tgt"))


def pairs_of_many(graph: PropertyGraph, hubs: list[int]) -> DataFrame | None:
    """``(x, y)`` of the hubs of which the first reaches the other, made when they are read; None where arcs between components are too many to pack.

    Components that hold hubs are searched from, and their hubs paired; no tag is made.
    """
    some = graph.vertices.sparkSession.createDataFrame(pd.DataFrame({"vid": np.unique(np.array(hubs, dtype=np.int64))}))
    comp, dag = _condensed(graph)
    if not fits(dag):
        return None
    own = saved(comp.join(F.broadcast(some), "vid", "left_semi"), "own")
    return reached(dag, own, own).where("x <> y")


def _condensed(graph: PropertyGraph) -> tuple[DataFrame, PropertyGraph]:
    comp = saved(scc(graph), "comp")
    dag, _ = condense(graph, comp, [], [Agg("count")])
    return comp, replace(dag, edges=saved(dag.edges.select("src", "tgt"), "arcs"))


def closure_by_recursion(graph: PropertyGraph, hubs: list[int], max_hops: int) -> DataFrame:
    """``(hub, vid)`` within a bound, as one SQL query whose steps are written out: a step holds each pair once, not each walk."""
    spark = graph.vertices.sparkSession
    start = spark.createDataFrame([(int(h), int(h)) for h in hubs], "hub long, vid long")
    arcs = graph.edges.select("src", "tgt")
    steps = ["w0 as (select hub, vid from {start})"]
    steps += [f"w{i} as (select distinct hub, tgt as vid from w{i - 1} join {{arcs}} on vid = src)" for i in range(1, int(max_hops) + 1)]
    every = " union ".join(f"select hub, vid from w{i}" for i in range(int(max_hops) + 1))
    return spark.sql(f"with {', '.join(steps)} {every}", start=start, arcs=arcs)


def tags_from_closure(closure: Closure | DataFrame, hubs: list[int]) -> DataFrame:
    """Vertex tags by two look-ups for each vertex and hub: semi-joins of the index, or of its pairs ``(src, tgt)``, with the hubs."""
    whole = isinstance(closure, Closure)
    spark, n = (closure.comp if whole else closure).sparkSession, n_words(len(hubs))
    numbered = F.broadcast(spark.createDataFrame(list(enumerate(hubs)), "i int, hub long"))
    some = numbered.select(F.col("hub").alias("vid"))
    from_hubs, to_hubs = (closure.rows(sources=some), closure.rows(targets=some)) if whole else (closure, closure)
    ahead = from_hubs.join(numbered, F.col("src") == F.col("hub")).select(F.col("tgt").alias("vid"), "i", F.lit(0).alias("dir"))
    behind = to_hubs.join(numbered, F.col("tgt") == F.col("hub")).select(F.col("src").alias("vid"), "i", F.lit(1).alias("dir"))
    return _tags(ahead.unionAll(behind), n)


def _tags(found: DataFrame, n: int) -> DataFrame:
    bit = lambda w: F.when(F.col("i").between(63 * w, 63 * w + 62), F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("i") - 63 * w).cast("int"))).otherwise(0)
    cols = [
        F.coalesce(F.bit_or(F.when(F.col("dir") == d, bit(w))), F.lit(0)).cast("long").alias(c)
        for d, side in ((0, "s"), (1, "r"))
        for w, c in enumerate(names(side, n))
    ]
    return found.groupBy("vid").agg(*cols)


# -- labelled indexes -----------------------------------------------------------
class TwoHop:
    """Pruned labels: u reaches v when a label of u's out-list is in v's in-list.

    Labels are exact whatever the order of their roots, and a look-up with a root
    at an end meets no later root's label.  So the vertices that are asked for come
    first, by degrees; without them every vertex is a root.
    """

    def __init__(self, dag: Dag, asked: np.ndarray | None = None):
        up = dag.up()
        weight = (np.diff(dag.down.start) + 1) * (np.diff(up.start) + 1)
        roots = np.arange(dag.m) if asked is None else np.unique(asked)
        roots = roots[np.argsort(-weight[roots], kind="stable")]
        self.out, self.into = (np.zeros((dag.m, n_words(len(roots))), dtype=np.int64) for _ in range(2))
        for i, root in enumerate(roots):
            for arcs, mine, theirs in ((dag.down, self.out, self.into), (up, self.into, self.out)):
                seen, now = np.zeros(dag.m, dtype=bool), np.array([root])
                seen[root] = True
                while len(now):
                    now = now[~(mine[root] & theirs[now]).any(axis=1)]  # others are known through an earlier root
                    theirs[now, i // 63] |= np.int64(1 << i % 63)
                    heads = arcs.of(now)[0]
                    now = np.unique(heads[~seen[heads]])
                    seen[now] = True

    def from_all(self, v: int) -> np.ndarray:
        """Which vertices reach ``v``."""
        return (self.out & self.into[v]).any(axis=1)

    def to_all(self, u: int) -> np.ndarray:
        """Which vertices ``u`` reaches."""
        return (self.out[u] & self.into).any(axis=1)


class Chains:
    """A cover by paths; for each vertex the first place of a path that it reaches, and the last that reaches it.

    These are kept for the paths of the vertices that are asked for, or for all.
    """

    def __init__(self, dag: Dag, asked: np.ndarray | None = None):
        self.chain, self.place = self._cover(dag)
        kept = np.unique(self.chain if asked is None else self.chain[asked])
        self.column = np.full(dag.m, -1)
        rows = np.flatnonzero(np.isin(self.chain, kept))
        self.column[rows] = np.searchsorted(kept, self.chain[rows])
        self.first = np.full((dag.m, len(kept)), np.iinfo(np.int32).max, dtype=np.int32)
        self.last = np.full((dag.m, len(kept)), -1, dtype=np.int32)
        self.first[rows, self.column[rows]] = self.last[rows, self.column[rows]] = self.place[rows]
        dag.pull(self.first, np.minimum)
        dag.push(self.last, np.maximum)

    @staticmethod
    def _cover(dag: Dag) -> tuple[np.ndarray, np.ndarray]:
        """Each vertex goes on where a parent ends a path, or starts one; a level's vertices choose at once."""
        up, found = dag.up(), 0
        chain, place = np.zeros(dag.m, np.int64), np.zeros(dag.m, np.int64)
        before, ends = np.full(dag.m, -1), np.ones(dag.m, dtype=bool)
        for now in dag.by_level():
            parents, n = up.of(now)
            child = np.repeat(now, n)
            while True:
                free = ends[parents] & (before[child] < 0)
                parents, child = parents[free], child[free]
                if not len(child):
                    break
                first = np.flatnonzero(np.r_[True, child[1:] != child[:-1]])
                many = np.diff(np.r_[first, len(child)])
                one = first + child[first] * 2_654_435_761 % (1 << 32) % many  # spread, so that few choose the same
                taken, i = np.unique(parents[one], return_index=True)
                before[child[one[i]]], ends[taken] = taken, False
            starts = before[now] < 0
            chain[now[starts]] = np.arange(found, found := found + int(starts.sum()))
            on, back = now[~starts], before[now[~starts]]
            chain[on], place[on] = chain[back], place[back] + 1
        return chain, place

    def from_all(self, v: int) -> np.ndarray:
        return self.first[:, self.column[v]] <= self.place[v]

    def to_all(self, u: int) -> np.ndarray:
        return self.last[:, self.column[u]] >= self.place[u]


class TreeIntervals:
    """Intervals of a spanning forest, and the closure of the edges outside it."""

    def __init__(self, down: list[list[int]], up: list[list[int]], order: list[int]):
        m = len(down)
        parent = [up[v][0] if up[v] else -1 for v in range(m)]
        kids: list[list[int]] = [[] for _ in range(m)]
        for v in range(m):
            if parent[v] >= 0:
                kids[parent[v]].append(v)
        self.low, self.high, count = [0] * m, [0] * m, 0
        for root in (v for v in range(m) if parent[v] < 0):
            work = [(root, False)]
            while work:
                v, closing = work.pop()
                if closing:
                    self.high[v] = count
                    continue
                self.low[v] = count
                count += 1
                work.append((v, True))
                work += [(w, False) for w in kids[v]]
        extra = [(a, b) for a in range(m) for b in down[a] if parent[b] != a]
        # Which outside edges can follow which; then what each reaches through others.
        rank = {v: i for i, v in enumerate(order)}
        extra.sort(key=lambda e: -rank[e[0]])
        self.extra, self.after = extra, []
        for i, (_, b) in enumerate(extra):
            reach = 1 << i
            for j in range(i):
                if self._in_tree(b, extra[j][0]):
                    reach |= self.after[j]
            self.after.append(reach)

    def _in_tree(self, u: int, v: int) -> bool:
        return self.low[u] <= self.low[v] < self.high[u]

    def reaches(self, u: int, v: int) -> bool:
        if self._in_tree(u, v):
            return True
        reach = 0
        for i, (a, _) in enumerate(self.extra):
            if self._in_tree(u, a):
                reach |= self.after[i]
        return any(reach >> j & 1 and self._in_tree(self.extra[j][1], v) for j in range(len(self.extra)))

    def sets(self, hubs: list[int]) -> tuple[list[int], list[int]]:
        """For every vertex, bits of the hubs that reach it and that it reaches."""
        m = len(self.low)
        before, after = [0] * m, [0] * m
        for i, h in enumerate(hubs):
            through = 0
            for e, (a, _) in enumerate(self.extra):
                if self._in_tree(h, a):
                    through |= self.after[e]
            heads = [h, *[b for e, (_, b) in enumerate(self.extra) if through >> e & 1]]
            into = 0
            for e, (_, b) in enumerate(self.extra):
                if self._in_tree(b, h):
                    into |= 1 << e
            tails = [self.extra[e][0] for e in range(len(self.extra)) if self.after[e] & into]
            for v in range(m):
                if any(self._in_tree(x, v) for x in heads):
                    before[v] |= 1 << i
                if self._in_tree(v, h) or any(self._in_tree(v, x) for x in tails):
                    after[v] |= 1 << i
        return before, after


def _bits(sides: Iterator[np.ndarray], m: int, k: int) -> np.ndarray:
    """Columns of bits as words of 63."""
    words = np.zeros((m, n_words(k)), dtype=np.int64)
    for i, side in enumerate(sides):
        words[:, i // 63] |= side.astype(np.int64) << (i % 63)
    return words


def _by_tests(index: TwoHop | Chains, m: int, hubs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return _bits((index.to_all(h) for h in hubs), m, len(hubs)), _bits((index.from_all(h) for h in hubs), m, len(hubs))


def _pushed(dag: Dag, hubs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Without an index: hub lists pushed forward and backward in topological order."""
    before = _bits((np.arange(dag.m) == h for h in hubs), dag.m, len(hubs))
    after = before.copy()
    dag.push(before, np.bitwise_or)
    dag.pull(after, np.bitwise_or)
    return before, after


def _by_intervals(dag: Dag, hubs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    down: list[list[int]] = [[] for _ in range(dag.m)]
    up: list[list[int]] = [[] for _ in range(dag.m)]
    for a, b in sorted(set(zip(dag.a.tolist(), dag.b.tolist(), strict=True))):
        down[a].append(b)
        up[b].append(a)
    sides = TreeIntervals(down, up, np.argsort(dag.level, kind="stable").tolist()).sets(hubs.tolist())
    return tuple(_bits((np.array([x >> i & 1 for x in side], dtype=bool) for i in range(len(hubs))), dag.m, len(hubs)) for side in sides)


METHODS: dict[str, Callable] = {
    "two_hop": lambda dag, hubs: _by_tests(TwoHop(dag, hubs), dag.m, hubs),
    "chain": lambda dag, hubs: _by_tests(Chains(dag, hubs), dag.m, hubs),
    "tree_interval": _by_intervals,
    "topological": _pushed,
}


def extract(graph: PropertyGraph, hubs: list[int], method: str) -> DataFrame:
    """Vertex tags by ``two_hop``, ``chain``, ``tree_interval`` or ``topological``; cycles are condensed first.

    The limit is of edges between components: a larger graph is condensed before its edges are gathered.
    """
    arcs, limit = graph.edges.select("src", "tgt"), LABEL_EDGES if method == "tree_interval" else TASK_ARCS
    if arcs.count() <= limit:
        return _extracted(arcs, hubs, method)
    comp = saved(scc(graph), "comp")
    between = saved(condense(graph, comp, [], [Agg("count")])[0].edges.select("src", "tgt"), "arcs")
    if between.count() > limit:
        raise ValueError("too many edges between components for a labelled index: use the frontier")
    at = {r["vid"]: r["comp"] for r in comp.where(F.col("vid").isin(hubs)).collect()}
    own = list(dict.fromkeys(at.get(h, h) for h in hubs))
    tags = _extracted(between, own, method)
    if between.isEmpty():  # components reach themselves
        n = n_words(len(own))
        tags = graph.vertices.sparkSession.createDataFrame([(c, *words_of(1 << i, n), *words_of(1 << i, n)) for i, c in enumerate(own)], tags.schema)
    if own == [at.get(h, h) for h in hubs]:
        found = tags
    else:  # hubs of one component share its bit
        k = len(own)
        each = F.explode(members("s", k)).alias("c"), F.lit(0).alias("dir")
        bits = tags.select("vid", *each).unionAll(tags.select("vid", F.explode(members("r", k)), F.lit(1)))
        numbered = F.broadcast(graph.vertices.sparkSession.createDataFrame([(i, own.index(at.get(h, h))) for i, h in enumerate(hubs)], "i int, c int"))
        found = _tags(bits.join(numbered, "c").select("vid", "i", "dir"), n_words(len(hubs)))
    return comp.join(found.withColumnRenamed("vid", "comp"), "comp").select("vid", *[c for c in found.columns if c != "vid"])


def _extracted(arcs: DataFrame, hubs: list[int], method: str) -> DataFrame:
    n = n_words(len(hubs))
    work = METHODS[method]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vids, s, t = gathered(frames)
        own = np.array(hubs, dtype=np.int64)
        lone = np.setdiff1d(own, vids)  # hubs without an edge
        dag = Dag(len(vids) + len(lone), s, t)
        every = np.concatenate([vids, lone])
        order = np.argsort(every)
        before, after = work(dag, dag.comp[order[np.searchsorted(every, own, sorter=order)]])
        some = np.flatnonzero((before.any(axis=1) | after.any(axis=1))[dag.comp])
        at = dag.comp[some]
        yield pd.DataFrame({"vid": every[some]} | {c: before[at, w] for w, c in enumerate(names("s", n))} | {c: after[at, w] for w, c in enumerate(names("r", n))})

    shape = "vid long, " + ", ".join(f"{c} long" for c in [*names("s", n), *names("r", n)])
    return arcs.repartition(1).mapInPandas(run, shape)
