"""Searches from many vertices: the arcs as packed arrays in every task, blocks of sources dealt to tasks.

A search takes 64 sources at a time, a bit each.  The arcs are packed by one task
(8 bytes an arc) and sent to the tasks by a broadcast join, up to ``PACKED_ARCS``;
a caller has another way beyond.

Pairs of an acyclic graph's members travel as products ``(xs, ys)``, what a block
of sources reaches alike, and are made when they are read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import pairwise

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.operators.dag import Arcs, levels
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.runtime import saved

#: Arcs that are packed and broadcast: 128 MB in each task.
PACKED_ARCS = 16_000_000
#: Sources of one block: the unit that is dealt to tasks.
BLOCK = 2_048
#: Sources of a block of products, bytes of its bits, arcs taken at once, targets of a product (whose pairs Spark holds together), products sent at once.
PRODUCT_BLOCK, STATE_BYTES, STEP, PIECE, BATCH = 512, 1 << 27, 500_000, 64, 1_024


class Search:
    """Breadth-first rounds from up to 64 vertices; ``src`` and ``tgt`` are places in ``vids``, ordered by ``tgt``."""

    def __init__(self, vids: np.ndarray, src: np.ndarray, tgt: np.ndarray):
        self.vids, self.src = vids, src
        self.first = np.flatnonzero(np.r_[True, tgt[1:] != tgt[:-1]]) if len(tgt) else np.zeros(0, np.int64)
        self.heads = tgt[self.first]

    def places(self, some: np.ndarray) -> np.ndarray:
        """The places of ids, -1 for ids without an arc."""
        if not len(self.vids):
            return np.full(len(some), -1)
        at = np.minimum(np.searchsorted(self.vids, some), len(self.vids) - 1)
        return np.where(self.vids[at] == some, at, -1)

    def rounds(self, starts: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """``(round, bits)``: for each vertex the sources (by number) that reach it first in this round."""
        new = np.zeros(len(self.vids), dtype=np.uint64)
        np.bitwise_or.at(new, starts, np.uint64(1) << np.arange(len(starts), dtype=np.uint64))
        had, r = np.zeros_like(new), 0
        while new.any():
            yield r, new
            had |= new
            sent = np.zeros_like(new)
            if len(self.heads):
                sent[self.heads] = np.bitwise_or.reduceat(new[self.src], self.first)
            new, r = sent & ~had, r + 1


def bit_table(words: np.ndarray, n: int) -> np.ndarray:
    """Words of 64 bits as rows of their first ``n`` bits."""
    return np.unpackbits(words.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, :n]


def bit_counts(words: np.ndarray, n: int) -> np.ndarray:
    """How many words have each of the first ``n`` bits; 255 rows are added as bytes."""
    table = bit_table(words, 64)
    whole = len(table) // 255 * 255
    sums = table[:whole].reshape(-1, 255, 64).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return (sums + table[whole:].sum(axis=0, dtype=np.int64))[:n]


def fits(graph: PropertyGraph, limit: int | None = None) -> bool:
    limit = PACKED_ARCS if limit is None else limit
    return graph.edges.limit(limit + 1).count() <= limit


def pack(graph: PropertyGraph, direction: int = 0) -> DataFrame:
    """One row ``(vids, src, tgt)``: the sorted ids, and the ends of all arcs as places, by target."""
    tail, head = ("src", "tgt") if direction == 0 else ("tgt", "src")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parts = [(f["a"].to_numpy(), f["b"].to_numpy()) for f in frames if len(f)]
        a, b = (np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, np.int64) for i in (0, 1))
        vids = np.unique(np.concatenate([np.unique(a), np.unique(b)]))
        s, t = np.searchsorted(vids, a).astype(np.int32), np.searchsorted(vids, b).astype(np.int32)
        order = np.argsort(t, kind="stable")
        yield pd.DataFrame({"vids": [vids.tobytes()], "src": [s[order].tobytes()], "tgt": [t[order].tobytes()]})

    some = graph.edges.select(F.col(tail).alias("a"), F.col(head).alias("b"))
    return saved(some.repartition(1).mapInPandas(run, "vids binary, src binary, tgt binary"), "packed")


def search_all(graph: PropertyGraph, sources: DataFrame, direction: int, work: Callable[[Search, np.ndarray], Iterator[pd.DataFrame]], shape: str) -> DataFrame:
    """``work(search, ids)`` for each block of ``sources(vid)``, with all arcs at hand."""
    parts = max(1, -(-sources.count() // BLOCK))

    def block(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        some = [f["vid"].to_numpy() for f in frames if len(f)]
        if some:
            yield pd.DataFrame({"block": [np.sort(np.concatenate(some)).tobytes()]})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for ids, vids, s, t in zip(f["block"], f["vids"], f["src"], f["tgt"], strict=True):
                yield from work(Search(np.frombuffer(vids, np.int64), np.frombuffer(s, np.int32), np.frombuffer(t, np.int32)), np.frombuffer(ids, np.int64))

    blocks = sources.select("vid").distinct().repartition(parts, "vid").mapInPandas(block, "block binary")
    return blocks.crossJoin(F.broadcast(pack(graph, direction))).mapInPandas(run, shape)  # one row on the right


class Products:
    """What many sources reach in an acyclic graph: a row of bits for each component, merged a level at a time.

    ``src`` and ``tgt`` are places in ``comps``, ordered by the level of ``tgt`` and by ``tgt``; arcs between two
    ``cuts`` have their ends apart.  The members of component i are ``vids[start[i]:start[i + 1]]``.
    """

    shape = "comps binary, src binary, tgt binary, cuts binary, start binary, vids binary"

    def __init__(self, comps: bytes, src: bytes, tgt: bytes, cuts: bytes, start: bytes, vids: bytes):
        self.comps, self.cuts, self.start, self.vids = (np.frombuffer(x, np.int64) for x in (comps, cuts, start, vids))
        self.src, self.tgt = (np.frombuffer(x, np.int32) for x in (src, tgt))

    @classmethod
    def packed(cls, arcs: tuple[np.ndarray, np.ndarray], members: tuple[np.ndarray, np.ndarray]) -> pd.DataFrame:
        comps = np.unique(np.concatenate([*arcs, members[0]]))
        n, (s, t, at) = len(comps), (np.searchsorted(comps, x) for x in (*arcs, members[0]))
        level = levels(n, Arcs(n, s, t), np.bincount(t, minlength=n))
        order = np.lexsort((t, level[t]))
        s, t = s[order].astype(np.int32), t[order].astype(np.int32)
        rise = np.flatnonzero(np.diff(level[t])) + 1
        cuts = np.unique(np.concatenate([[0, len(t)], rise, np.arange(0, len(t), STEP)]))
        vids = members[1][np.lexsort((members[1], at))]
        start = np.concatenate([[0], np.cumsum(np.bincount(at, minlength=n))])
        return pd.DataFrame({c: [x.tobytes()] for c, x in zip(("comps", "src", "tgt", "cuts", "start", "vids"), (comps, s, t, cuts, start, vids), strict=True)})

    def of(self, ids: np.ndarray, comps: np.ndarray) -> Iterator[pa.RecordBatch]:
        """``(xs, ys)`` of the sources ``ids``, members of ``comps``: each pair of both lists is one that is reached."""
        at = np.minimum(np.searchsorted(self.comps, comps), len(self.comps) - 1)
        known = self.comps[at] == comps
        ids, at = ids[known], at[known]
        most = 64 * max(1, min(PRODUCT_BLOCK // 64, STATE_BYTES // (8 * len(self.comps))))
        for lo in range(0, len(ids), most):
            yield from self._block(ids[lo : lo + most], at[lo : lo + most])

    def _block(self, ids: np.ndarray, at: np.ndarray) -> Iterator[pa.RecordBatch]:
        number = np.arange(len(ids), dtype=np.uint64)
        had = np.zeros((len(self.comps), -(-len(ids) // 64)), dtype=np.uint64)
        np.bitwise_or.at(had, (at, (number // 64).astype(np.int64)), np.uint64(1) << number % 64)
        for lo, hi in pairwise(self.cuts):
            heads = self.tgt[lo:hi]
            first = np.flatnonzero(np.r_[True, heads[1:] != heads[:-1]])
            had[heads[first]] |= np.bitwise_or.reduceat(had[self.src[lo:hi]], first, axis=0)
        # Components that the same sources reach are one list of targets.
        some = np.flatnonzero(had.any(axis=1) & (np.diff(self.start) > 0))
        if not len(some):
            return
        some = some[np.lexsort(had[some].T)]
        had = had[some]
        fresh = np.flatnonzero(np.r_[True, (had[1:] != had[:-1]).any(axis=1)])
        n = self.start[some + 1] - self.start[some]
        before = np.cumsum(n) - n
        ys = self.vids[np.repeat(self.start[some] - before, n) + np.arange(n.sum())]
        piece = np.unique(np.concatenate([before[fresh], np.arange(0, len(ys), PIECE)]))
        sets = had[fresh[np.searchsorted(before[fresh], piece, side="right") - 1]]
        ends = np.r_[piece, len(ys)]
        for lo in range(0, len(piece), BATCH):
            bits = bit_table(sets[lo : lo + BATCH].reshape(-1), 64).reshape(-1, 64 * sets.shape[1])
            xs, to = np.r_[0, np.cumsum(bits.sum(axis=1, dtype=np.int64))], ends[lo : lo + BATCH + 1]
            lists = (xs, ids[np.nonzero(bits)[1]]), (to - to[0], ys[to[0] : to[-1]])
            yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(i, pa.int32()), pa.array(v, pa.int64())) for i, v in lists], ["xs", "ys"])


def reached(dag: PropertyGraph, sources: DataFrame, targets: DataFrame) -> DataFrame:
    """``(x, y)``: members ``vid`` of sources ``(vid, comp)`` and the members of targets ``(vid, comp)`` whose component theirs reaches.

    No pair is written or dealt: a task makes those of its sources when they are read, all ``x`` of a ``y`` together.
    """
    parts = max(1, -(-sources.count() // PRODUCT_BLOCK))

    def pack(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        found: tuple = ([], []), ([], [])
        for f in frames:
            for kind in (0, 1):
                own = f[f["kind"] == kind]
                for c, to in zip("ab", found[kind], strict=True):
                    to.append(own[c].to_numpy())
        yield Products.packed(*(tuple(np.concatenate([np.zeros(0, np.int64), *x]) for x in both) for both in found))

    def block(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        some = [f for f in frames if len(f)]
        if some:
            own = pd.concat(some).sort_values(["comp", "vid"])
            yield pd.DataFrame({"ids": [own["vid"].to_numpy().tobytes()], "own": [own["comp"].to_numpy().tobytes()]})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                ids, own = (np.frombuffer(r.pop(c), np.int64) for c in ("ids", "own"))
                yield from Products(**r).of(ids, own)

    rows = dag.edges.select(F.lit(0).alias("kind"), F.col("src").alias("a"), F.col("tgt").alias("b")).unionAll(targets.select(F.lit(1), "comp", "vid"))
    packed = saved(rows.repartition(1).mapInPandas(pack, Products.shape), "packed")
    blocks = sources.select("vid", "comp").repartitionByRange(parts, "comp", "vid").mapInPandas(block, "ids binary, own binary")
    made = blocks.crossJoin(F.broadcast(packed)).mapInArrow(run, "xs array<bigint>, ys array<bigint>")  # one row on the right
    return made.select("xs", F.explode("ys").alias("y")).select(F.explode("xs").alias("x"), "y")
