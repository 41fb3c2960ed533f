"""Hub selectors: by degree, attribute, centrality (static or recomputed), or named."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.functions.bits import members, n_words
from hubloom.operators.frontier import arrivals
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.packed import Search, bit_counts, bit_table, fits, search_all
from hubloom.operators.runtime import saved


def _vids(rows: DataFrame, k: int) -> list[int]:
    return [r["vid"] for r in rows.limit(k).collect()]


def top_degree(graph: PropertyGraph, k: int, direction: str = "total", where: Column | str | None = None) -> list[int]:
    """The k vertices of largest degree; ties go to the smaller id."""
    column = {"total": "degree", "in": "in_degree", "out": "out_degree"}[direction]
    ranked = graph.degrees()
    if where is not None:
        ranked = ranked.join(graph.vertices.where(where).select("vid"), "vid", "left_semi")
    return _vids(ranked.orderBy(F.desc(column), "vid"), k)


def by_attribute(graph: PropertyGraph, predicate: Column | str, limit: int | None = None) -> list[int]:
    rows = graph.vertices.where(predicate).select("vid").orderBy("vid")
    return [r["vid"] for r in (rows if limit is None else rows.limit(limit)).collect()]


def explicit(vids: list[int]) -> list[int]:
    return list(dict.fromkeys(vids))


def ensure_hubs(hubs: list[int], arguments: list[int]) -> list[int]:
    """The arguments of the scope are hubs too."""
    return explicit([*hubs, *arguments])


def distance_sums(graph: PropertyGraph, sources: DataFrame | list[int], direction: int = 0, targets: DataFrame | None = None, batch: int = 63) -> DataFrame:
    """``(vid, reached, total)`` of the sources: vertices reached and the sum of their distances.

    ``targets(vid)``: only these count as reached; paths go anywhere.  Sources are
    searched from in parallel where the arcs can be packed, else in batches by joins.
    """
    spark = graph.vertices.sparkSession
    if isinstance(sources, list):
        sources = spark.createDataFrame([(int(v),) for v in sources], "vid long")
    shape = "vid long, reached long, total long"
    if graph.edges.isEmpty() or not fits(graph):
        return _sums_by_joins(graph, sources, direction, targets, batch)
    wanted = None if targets is None else np.array([r["vid"] for r in targets.select("vid").distinct().collect()], dtype=np.int64)  # ids of a packed graph

    def work(search: Search, ids: np.ndarray) -> Iterator[pd.DataFrame]:
        at, reached, total = search.places(ids), np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
        among = slice(None) if wanted is None else (p := search.places(np.sort(wanted)))[p >= 0]
        linked = np.flatnonzero(at >= 0)
        for lo in range(0, len(linked), 64):
            some = linked[lo : lo + 64]
            for r, bits in search.rounds(at[some]):
                hits = bits[among]
                n = bit_counts(hits[hits != 0], len(some))
                reached[some] += n
                total[some] += n * r
        lone = at < 0  # a vertex without an arc reaches itself
        reached[lone] = 1 if wanted is None else np.isin(ids[lone], wanted)
        yield pd.DataFrame({"vid": ids, "reached": reached, "total": total})

    return search_all(graph, sources, direction, work, shape)


def _sums_by_joins(graph: PropertyGraph, sources: DataFrame, direction: int, targets: DataFrame | None, batch: int) -> DataFrame:
    """The same by rounds of joins, a batch of sources at a time; steps are written, so nothing but ids is on the driver."""
    out = None
    vids = [r["vid"] for r in sources.select("vid").distinct().orderBy("vid").collect()]
    for lo in range(0, len(vids), batch):
        part = vids[lo : lo + batch]
        found = arrivals(graph, part, directions=(direction,))
        if targets is not None:
            found = found.join(targets.select("vid").distinct(), "vid", "left_semi")
        sums = found.select(F.explode(members("b", len(part))).alias("i"), "round").groupBy("i").agg(F.count("*").alias("reached"), F.sum("round").cast("long").alias("total"))
        named = saved(sums.select(F.element_at(F.array(*map(F.lit, part)), F.col("i") + 1).alias("vid"), "reached", "total"), "sums")
        out = named if out is None else out.unionAll(named)
    if out is None:
        return graph.vertices.sparkSession.createDataFrame([], "vid long, reached long, total long")
    return out


def closeness(graph: PropertyGraph, sources: list[int] | None = None, direction: int = 0) -> DataFrame:
    """``(vid, closeness)``: vertices reached besides itself, over the sum of their distances."""
    return _closeness(distance_sums(graph, graph.vertices.select("vid") if sources is None else sources, direction))


def _closeness(sums: DataFrame) -> DataFrame:
    return sums.select("vid", F.when(F.col("total") > 0, F.round((F.col("reached") - 1) / F.col("total"), 9)).otherwise(0.0).alias("closeness"))


def pivots(graph: PropertyGraph, n: int) -> list[int]:
    """A fixed sample: the vertices of smallest md5."""
    return _vids(graph.vertices.select("vid").orderBy(F.md5(F.col("vid").cast("string")), "vid"), n)


def pivot_closeness(graph: PropertyGraph, n: int) -> DataFrame:
    """Closeness estimated from the distances to a fixed number of pivots."""
    chosen = pivots(graph, n)
    found = arrivals(graph, chosen, directions=(1,))  # who reaches the pivots, and how far they are
    each = found.select("vid", F.bit_count("b0").alias("c"), "round") if n_words(len(chosen)) == 1 else found.select("vid", F.size(members("b", len(chosen))).alias("c"), "round")
    sums = each.where("round > 0").groupBy("vid").agg(F.sum("c").alias("met"), F.sum(F.col("c") * F.col("round")).alias("total"))
    return sums.select("vid", F.round(F.col("met") / F.col("total"), 9).alias("closeness"))


class DistanceIndex:
    """The distances of all ordered pairs of vertices, a written row for each source: a number for each place of ``vids``.

    A byte (more in graphs of long paths) a pair, with the largest value where there is no path; 64 sources are searched from at
    once.  Look-ups read the rows of their sources only.
    """

    def __init__(self, rows: DataFrame, vids: np.ndarray):
        self.rows, self.vids = rows, vids

    def _places(self, targets: DataFrame) -> tuple[np.ndarray, np.ndarray]:
        some = np.sort(np.array([r["vid"] for r in targets.select("vid").distinct().collect()], dtype=np.int64))
        at = np.searchsorted(self.vids, some)
        held = at < len(self.vids)
        held[held] = self.vids[at[held]] == some[held]
        return some[held], at[held]

    def _read(self, sources: DataFrame, targets: DataFrame, each: Callable, shape: str) -> DataFrame:
        ids, at = self._places(targets)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                for src, width, packed in zip(f["src"], f["width"], f["d"], strict=True):
                    kind = np.dtype(f"u{width}")
                    d = np.frombuffer(packed, kind)[at]
                    found = d != np.iinfo(kind).max
                    yield each(src, ids[found], d[found].astype(np.int64))

        return self.rows.join(sources.select(F.col("vid").alias("src")).distinct(), "src", "left_semi").mapInPandas(run, shape)

    def pairs(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """``(src, tgt, d)`` of reachable pairs."""
        return self._read(sources, targets, lambda src, ids, d: pd.DataFrame({"src": src, "tgt": ids, "d": d}), "src long, tgt long, d int")

    def sums(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """``(vid, reached, total)`` of sources over the targets they reach."""
        return self._read(sources, targets, lambda src, ids, d: pd.DataFrame({"vid": [src], "reached": [len(d)], "total": [d.sum()]}), "vid long, reached long, total long")


def all_distances(graph: PropertyGraph) -> DistanceIndex:
    """An index of the distances of every pair; for graphs whose arcs can be packed."""
    if not fits(graph):
        raise ValueError("too many edges for an index of all distances: search from the vertices asked for")
    every = graph.vertices.select("vid")
    vids = np.array([r["vid"] for r in every.distinct().orderBy("vid").collect()], dtype=np.int64)

    def work(search: Search, ids: np.ndarray) -> Iterator[pd.DataFrame]:
        at, own, where = search.places(ids), np.searchsorted(vids, ids), np.searchsorted(vids, search.vids)
        for lo in range(0, len(ids), 64):
            some = np.arange(lo, min(lo + 64, len(ids)))
            linked = some[at[some] >= 0]
            d, had = np.zeros((len(search.vids), len(linked)), np.uint8), np.zeros(len(search.vids), np.uint64)
            for r, bits in search.rounds(at[linked]):
                if r and r + 1 == np.iinfo(d.dtype).max:
                    d = d.astype(np.uint16 if d.itemsize == 1 else np.uint32)
                had |= bits
                d += bit_table(~had, len(linked))  # what is not reached yet is farther by one
            d[bit_table(~had, len(linked)) == 1] = np.iinfo(d.dtype).max
            by_source, out = iter(np.ascontiguousarray(d.T)), []
            for i in some:
                row = np.full(len(vids), np.iinfo(d.dtype).max, d.dtype)
                if at[i] >= 0:
                    row[where] = next(by_source)
                row[own[i]] = 0
                out.append((int(ids[i]), d.itemsize, row.tobytes()))
            yield pd.DataFrame(out, columns=["src", "width", "d"])

    if graph.edges.isEmpty():
        rows = every.distinct().mapInPandas(lambda frames: (f for g in frames for f in work(Search(np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0, np.int32)), g["vid"].to_numpy())), "src long, width int, d binary")
    else:
        rows = search_all(graph, every, 0, work, "src long, width int, d binary")
    return DistanceIndex(saved(rows, "apsp", compression="zstd"), vids)


def closeness_from_distances(dist: DistanceIndex, vertices: DataFrame) -> DataFrame:
    """Closeness inside an induced part, from distances of the whole: parts hold the shortest paths between their vertices."""
    return _closeness(dist.sums(vertices, vertices))


def top_by(measure: DataFrame, column: str, k: int, ascending: bool = False, among: DataFrame | None = None) -> list[int]:
    """The k vertices of largest (or smallest) measure, optionally among the ids of ``among``."""
    rows = measure if among is None else measure.join(among.select("vid"), "vid", "left_semi")
    return _vids(rows.orderBy(F.col(column).asc() if ascending else F.col(column).desc(), "vid"), k)


def pagerank(graph: PropertyGraph, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """``(vid, rank)`` after a fixed number of rounds; ranks of vertices without an out-edge are not passed on."""
    out = graph.edges.groupBy("src").agg(F.count("*").alias("deg"))
    arcs = saved(graph.edges.join(out, "src").select("src", "tgt", "deg"), "arcs")
    base = saved(graph.vertices.select("vid", F.lit(1.0).alias("rank")), "rank")
    rank = base
    for _ in range(rounds):
        sent = arcs.join(rank, F.col("src") == F.col("vid")).groupBy("tgt").agg(F.sum(F.col("rank") / F.col("deg")).alias("got"))
        rank = saved(base.select("vid").join(sent, F.col("vid") == F.col("tgt"), "left").select("vid", (1 - damping + damping * F.coalesce("got", F.lit(0.0))).alias("rank")), "rank")
    return rank


def build_measure_index(measure: DataFrame, column: str, path: str, files: int = 8) -> None:
    """A static measure in order: files by range of it, sorted, so look-ups read the row groups they need."""
    measure.repartitionByRange(files, F.desc(column), "vid").sortWithinPartitions(F.desc(column), "vid").write.mode("overwrite").parquet(path)


def lookup_measure(spark, path: str, column: str, k: int, where: Column | str | None = None, among: DataFrame | None = None) -> list[int]:  # noqa: ANN001
    rows = spark.read.parquet(path)
    return top_by(rows if where is None else rows.where(where), column, k, among=among)
