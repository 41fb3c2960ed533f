"""Near-duplicate components by exact shingle Jaccard over SimHash candidates.

A text's set of distinct word shingles is a class of its own; the fingerprint is
a vote of that set, so its angle follows the same set that is verified.  Classes
within ``radius`` bits that share a sampled band are candidates, and a candidate
links only when the Jaccard similarity of both shingle sets (64-bit hashes) is
``least`` at least.  Components are of such links alone.

Verification is in two passes, so that a large group of copies is never paired
with itself: first, over a few bands, each class is tried against one candidate of
its bucket, that with most candidates itself, which joins most copies; then all bands give every candidate pair
whose ends are not joined yet.  The second pass leaves no candidate untried.

Null texts are empty, and texts without words are one class.  Null ids come after
all others, and rows of equal id in the order of a hash of their text; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import connected_components, release_shuffles, saved
from hubloom.llm.simhash import SEED, _mixed, within_radius

#: Classes of a bucket that meet in one group; a larger bucket is cut into cells, and every two cells meet.
CELL = 512
#: Classes that are compared at once; bounds the memory of a task.
ROWS = 20_000


def row_key() -> Column:
    """What stands for a row: its id with its text; a null text is empty."""
    return F.xxhash64(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63))), F.coalesce("text", F.lit("")))


def shingle_set(text: str, shingle: int) -> np.ndarray:
    """Sorted distinct hashes of the word shingles; a text of fewer words is one shingle."""
    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
    k = min(shingle, len(words))
    starts, stops = [0, *(ends[: len(words) - k] + 1).tolist()], ends[k - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)], dtype=np.uint64))


def set_fingerprint(hashes: np.ndarray, lanes: int) -> bytes:
    if not len(hashes):
        return bytes(8 * lanes)
    votes = np.zeros(64 * lanes, dtype=np.int64)
    for lo in range(0, len(hashes), 16384):
        h = hashes[lo : lo + 16384]
        for lane in range(lanes):
            bits = np.unpackbits(_mixed(h, lane).astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            votes[64 * lane : 64 * lane + 64] += bits.sum(axis=0, dtype=np.int64)
    return np.packbits(2 * votes > len(hashes)).tobytes()


def bucket_pairs(prints: np.ndarray, run_of: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """All pairs (row, earlier row) within ``radius`` in each run of rows."""
    n = len(prints)
    first = np.flatnonzero(np.r_[True, run_of[1:] != run_of[:-1]])
    size = np.diff(np.r_[first, n])
    words = -(-size // 64)
    word0 = np.cumsum(words) - words
    run = np.repeat(np.arange(len(first)), size)
    lane = np.arange(n) - first[run]
    bits = np.unpackbits(prints, axis=1)
    planes = np.zeros((bits.shape[1], int(words.sum())), dtype=np.uint64)
    at_word, at_bit = word0[run] + lane // 64, np.uint64(1) << (lane % 64).astype(np.uint64)
    for b in range(bits.shape[1]):
        on = bits[:, b] == 1
        np.bitwise_or.at(planes[b], at_word[on], at_bit[on])
    out_a, out_b = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)]
    for k in range(int(words.max())):  # the k-th word of each run, against its rows from there on
        rows = np.flatnonzero((words[run] > k) & (lane >= 64 * k))
        for lo in range(0, len(rows), ROWS):
            part = rows[lo : lo + ROWS]
            mask = within_radius(bits[part], np.arange(len(part)), word0[run[part]] + k, planes, radius)
            own = lane[part] // 64 == k  # only earlier lanes of the row's own word
            mask[own] &= at_bit[part][own] - np.uint64(1)
            hit = np.flatnonzero(mask)
            i, j = np.nonzero(np.unpackbits(mask[hit].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
            out_a.append(part[hit[i]]), out_b.append(first[run[part[hit[i]]]] + 64 * k + j)
    return np.concatenate(out_a), np.concatenate(out_b)


def busiest(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of the pairs of each row, that with the row of most pairs."""
    degree = np.bincount(np.r_[i, j])
    a, b = np.r_[i, j], np.r_[j, i]
    order = np.lexsort((b, -degree[b], a))
    a, b = a[order], b[order]
    top = np.r_[True, a[1:] != a[:-1]] if len(a) else np.zeros(0, dtype=bool)
    return a[top], b[top]


def candidates(classes: DataFrame, bands: list[list[int]], radius: int, least: float, first_only: bool) -> DataFrame:
    """Distinct ``(a, b)`` of ``classes(c, n, label, fp)`` that meet within ``radius``, carry unlike labels and may reach ``least`` by their sizes."""

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        weights = [np.int64(1) << np.arange(len(b), dtype=np.int64) for b in bands]
        for pdf in batches:
            if not len(pdf):
                continue
            bits = np.unpackbits(np.frombuffer(b"".join(pdf["fp"]), dtype=np.uint8).reshape(len(pdf), -1), axis=1)
            for t, (band, weight) in enumerate(zip(bands, weights, strict=True)):
                yield pdf.assign(key=(np.int64(t) << 48) | (bits[:, band].astype(np.int64) @ weight))

    placed = classes.select("c", "n", "label", "fp").mapInPandas(place, "c long, n int, label long, fp binary, key long")
    hot = saved(placed.groupBy("key").agg(F.count("*").alias("m")).where(F.col("m") > CELL), "hot").select(
        "key", F.ceil(F.col("m") / (CELL // 2)).cast("int").alias("cells")
    )
    cut = placed.join(F.broadcast(hot), "key", "left").withColumn("cell", F.expr("if(cells is null, 0, pmod(xxhash64(fp, 11), cells))"))
    paired = cut.withColumn("other", F.explode(F.expr("if(cells is null, array(0), sequence(0, cells - 1))"))).select(
        "key", F.least("cell", "other").cast("int").alias("lo"), F.greatest("cell", "other").cast("int").alias("hi"), "c", "n", "label", "fp"
    )

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: pd.DataFrame | None = None

        def pairs(pdf: pd.DataFrame) -> pd.DataFrame:
            mark = pdf[["key", "lo", "hi"]].to_numpy()
            run = np.cumsum(np.r_[True, (mark[1:] != mark[:-1]).any(axis=1)]) - 1
            keep = np.bincount(run)[run] > 1
            run, fps = run[keep], pdf["fp"].to_numpy()[keep]
            c, n, label = (pdf[x].to_numpy()[keep] for x in ("c", "n", "label"))
            if not len(run):
                return pd.DataFrame({"a": [], "b": []}, dtype="int64")
            i, j = bucket_pairs(np.frombuffer(b"".join(fps), dtype=np.uint8).reshape(len(fps), -1), run, radius)
            may = (label[i] != label[j]) & (np.minimum(n[i], n[j]) >= least * np.maximum(n[i], n[j]))
            i, j = busiest(i[may], j[may]) if first_only else (i[may], j[may])
            return pd.DataFrame({"a": np.minimum(c[i], c[j]), "b": np.maximum(c[i], c[j])}).drop_duplicates()

        for pdf in batches:
            if held is not None:
                pdf = pd.concat([held, pdf], ignore_index=True)
            if not len(pdf):
                continue
            last = pdf[["key", "lo", "hi"]].iloc[-1]
            tail = ((pdf["key"] == last["key"]) & (pdf["lo"] == last["lo"]) & (pdf["hi"] == last["hi"])).to_numpy()
            held, done = pdf[tail], pdf[~tail]  # a run may go on in the next batch
            if len(done):
                yield pairs(done)
        if held is not None and len(held):
            yield pairs(held)

    met = paired.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi", "c").mapInPandas(compare, "a long, b long")
    return met.distinct()


def verified(pairs: DataFrame, rows: DataFrame, marked: DataFrame, shingle: int, least: float) -> DataFrame:
    """The ``pairs(a, b)`` whose shingle sets have a Jaccard similarity of ``least`` at least; ``rows(row, text)``."""
    asked = pairs.select(F.explode(F.array("a", "b")).alias("c")).distinct()
    one = marked.groupBy("c").agg(F.min("row").alias("row")).join(asked.hint("merge"), "c")

    def hashed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield pd.DataFrame({"c": pdf["c"], "set": [shingle_set(t, shingle).tobytes() for t in pdf["text"]]})

    # Repeated rows have one text, so any of them serves.
    texts = rows.join(one.hint("merge"), "row").select("c", "text")
    sets = saved(texts.mapInPandas(hashed, "c long, set binary").dropDuplicates(["c"]), "sets")

    def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            keep = []
            for x, y in zip(pdf["x"], pdf["y"], strict=True):
                x, y = np.frombuffer(x, dtype=np.uint64), np.frombuffer(y, dtype=np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(both >= least * (len(x) + len(y) - both))
            yield pdf.loc[np.array(keep, dtype=bool), ["a", "b"]]

    left = pairs.join(sets.select(F.col("c").alias("a"), F.col("set").alias("x")).hint("merge"), "a")
    return left.join(sets.select(F.col("c").alias("b"), F.col("set").alias("y")).hint("merge"), "b").select("a", "b", "x", "y").mapInPandas(judge, "a long, b long")


def near_copy_components(docs: DataFrame, shingle: int, lanes: int, radius: int, bands: list[list[int]], first_bands: list[list[int]], least: float) -> DataFrame:
    """``(row, doc_id, component_id, stays)`` for ``docs(doc_id, text)``: components of links of Jaccard similarity ``least`` at least.

    ``row`` is the ``row_key()``; one distinct row of a component ``stays``, that of the least id.
    """
    spark = docs.sparkSession
    rows = docs.withColumn("row", row_key())

    def mark(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for text in pdf["text"]:
                h = shingle_set(text, shingle)
                out.append((np.uint64(xxhash.xxh64_intdigest(h.tobytes(), SEED)).astype(np.int64), len(h), set_fingerprint(h, lanes)))
            yield pdf[["row", "doc_id"]].assign(c=[x for x, _, _ in out], n=[x for _, x, _ in out], fp=[x for _, _, x in out]).astype({"doc_id": "Int64"})

    marked = saved(rows.select("row", "doc_id", "text").mapInPandas(mark, "row long, doc_id long, c long, n int, fp binary"), "prints")
    classes = saved(marked.groupBy("c").agg(F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "row")).alias("rep"), F.first("n").alias("n"), F.first("fp").alias("fp")), "classes")
    texts = rows.select("row", "text")

    early = saved(candidates(classes.withColumn("label", F.col("c")), first_bands, radius, least, True), "early")
    roots = saved(connected_components(saved(verified(early, texts, marked, shingle, least), "tight")), "roots")
    release_shuffles(spark)
    named = classes.join(roots.hint("merge"), F.col("c") == F.col("node"), "left").withColumn("label", F.coalesce("root", "c"))
    rest = saved(candidates(named, bands, radius, least, False), "rest")
    release_shuffles(spark)
    links = saved(verified(rest, texts, marked, shingle, least), "links")
    roots = saved(connected_components(links.unionByName(roots.select(F.col("node").alias("a"), F.col("root").alias("b")))), "components")
    release_shuffles(spark)

    named = classes.join(roots.hint("merge"), F.col("c") == F.col("node"), "left").select("c", "rep", F.coalesce("root", "c").alias("root"))
    first = named.groupBy("root").agg(F.min("rep").alias("first"))
    ids = named.join(first.hint("merge"), "root").select("c", "first")
    return marked.join(ids.hint("merge"), "c").select("row", "doc_id", F.col("first.doc_id").alias("component_id"), (F.col("row") == F.col("first.row")).alias("stays"))
