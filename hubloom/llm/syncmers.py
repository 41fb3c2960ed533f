"""Document fingerprints from closed syncmers.

A k-mer of code points is an anchor when the smallest of its inner s-mers lies
at its first or last place.  Whether a k-mer is an anchor depends on nothing
around it, so an edit only touches the anchors it overlaps.  A fingerprint keeps
the anchors of smallest hash with their positions; two fingerprints are alike by
the share of the smallest joint anchors that both have at a consistent offset.

Texts shorter than a k-mer have one anchor, the whole text; empty (or null)
texts have the empty fingerprint.  Equal texts have equal fingerprints.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

K, S = 16, 8
#: Anchors kept of a text.
KEPT = 64
#: Matching anchors may drift this many code points from the best offset.
DRIFT = 256
CHUNK_CHARS = 1 << 20


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4")


def _stretch(h: np.ndarray, span: int, factor: int) -> np.ndarray:
    """Hashes of windows twice as wide, from those of two adjoining ones."""
    return h[:-span] * np.uint64(factor) + h[span:]


def _scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def anchors(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and start positions of all closed syncmers of one run of code points."""
    n = len(points)
    if n == 0:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    with np.errstate(over="ignore"):
        if n < K:
            h = np.uint64(n)
            for p in points:
                h = h * np.uint64(0x100000001B3) + np.uint64(p) + np.uint64(1)
            return _scramble(np.array([h])), np.zeros(1, dtype=np.int64)
        h = _scramble((points.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))
        for span, factor in ((1, 0xD6E8FEB86659FD93), (2, 0xA0761D6478BD642F), (4, 0xE7037ED1A0B428DB)):
            h = _stretch(h, span, factor)
        inner, whole = _scramble(h), _scramble(_stretch(h, S, 0x8EBC6AF09C88C6E3))
    least = inner
    for span in (1, 2, 4):
        least = np.minimum(least[:-span], least[span:])
    last = inner[K - S :]  # the inner window at the far edge of each k-mer
    least = np.minimum(least[: len(last)], last)
    at = np.flatnonzero((inner[: len(last)] == least) | (last == least))
    return whole[at], at


def sketch_many(texts: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
    """The kept anchors (32-bit hashes ascending, positions) of each text."""
    out: list[tuple[np.ndarray, np.ndarray]] = []
    for text in texts:
        h, at = anchors(_points(text))
        if len(h) > 4 * KEPT:
            # Enough of the smallest to leave KEPT distinct ones in any but odd texts.
            cut = np.partition(h, 2 * KEPT)[2 * KEPT]
            few = h <= cut
            if len(np.unique(h[few] >> np.uint64(32))) >= KEPT:
                h, at = h[few], at[few]
        short, first = np.unique(h >> np.uint64(32), return_index=True)
        order = first[:KEPT]
        out.append((short[:KEPT].astype(np.uint32), at[order].astype(np.uint32)))
    return out


def as_text(sketch: tuple[np.ndarray, np.ndarray]) -> str:
    """Sixteen hex digits an anchor: its hash, then its position."""
    return np.column_stack(sketch).astype(">u4").tobytes().hex()


def likeness(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    if not len(a[0]) or not len(b[0]):
        return float(len(a[0]) == len(b[0]))
    joint = np.union1d(a[0], b[0])[: min(KEPT, max(len(a[0]), len(b[0])))]
    both, ia, ib = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    inside = both <= joint[-1]
    if not inside.any():
        return 0.0
    offset = np.sort(a[1][ia[inside]].astype(np.int64) - b[1][ib[inside]].astype(np.int64))
    most = (np.searchsorted(offset, offset + 2 * DRIFT, side="right") - np.arange(len(offset))).max()
    return float(most) / len(joint)


def edited(text: str, following: str) -> str:
    """The last quarter of the text gives way to as much of the following one's start."""
    n = len(text) // 4
    return text[: len(text) - n] + following[:n]


def with_followers(docs: DataFrame, order: str = "ord") -> DataFrame:
    """Rows ``(bucket, tail, ord, text, ...)`` partitioned by bucket, each bucket followed by its successor's first row.

    Buckets are ranges of the order key cut at quantiles; only the P first rows
    of buckets are copied, so one shuffle of the texts gives every row its next.
    """
    spark = docs.sparkSession
    parts = 4 * max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(2000, docs.rdd.getNumPartitions()))
    cuts = docs.agg(F.percentile_approx(order, [i / parts for i in range(1, parts)], 10_000).alias("cuts")).first()["cuts"]
    cuts = sorted(set(cuts or []))
    bounds = F.array(*map(F.lit, cuts)) if cuts else F.expr("cast(array() as array<bigint>)")
    placed = docs.withColumn("bucket", F.size(F.filter(bounds, lambda b: b <= F.col(order))))
    first = {r["bucket"]: r["least"] for r in placed.groupBy("bucket").agg(F.min(order).alias("least")).collect()}  # at most P rows
    filled = sorted(first)
    before = {b: filled[i - 1] for i, b in enumerate(filled)}  # the first bucket follows the last
    heads = placed.where(F.col(order).isin([first[b] for b in filled])).groupBy("bucket", order).agg(F.min("text").alias("text"))
    moved = F.create_map(*[F.lit(x) for b in filled for x in (b, before[b])]) if filled else F.create_map(F.lit(0), F.lit(0))
    tails = heads.select(moved[F.col("bucket")].alias("bucket"), F.lit(1).alias("tail"), F.lit(None).cast("long").alias("doc_id"), order, "text")
    rows = placed.select("bucket", F.lit(0).alias("tail"), "doc_id", order, "text").unionByName(tails)
    return rows.repartition("bucket").sortWithinPartitions("bucket", "tail", order, "text")


def syncmer_fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of ``docs(doc_id, text)`` and of their edited texts, by ascending id (null ids first, equal ids by text)."""
    keyed = docs.select("doc_id", "text", F.coalesce("doc_id", F.lit(-(2**63))).alias("ord"))

    def work(group: list[tuple]) -> pd.DataFrame:
        """The first rows of the group; the last only follows."""
        own = sketch_many([t for _, t in group])
        changed = [edited(t, u) for (_, t), (_, u) in zip(group, group[1:], strict=False)]
        theirs = sketch_many(changed)
        n = len(changed)
        return pd.DataFrame(
            {
                "doc_id": pd.array([i for i, _ in group[:n]], dtype="Int64"),
                "n_chars": [len(t) for _, t in group[:n]],
                "edited_sha256": [hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in changed],
                "fingerprint": [as_text(s) for s in own[:n]],
                "edited_fingerprint": [as_text(s) for s in theirs],
                "near_edited": [likeness(a, b) for a, b in zip(own, theirs, strict=False)],
                "near_next": [likeness(a, b) for a, b in zip(own, own[1:], strict=False)],
            }
        )

    def walk(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        group: list[tuple] = []
        bucket, chars = None, 0
        for pdf in batches:
            ids = pdf["doc_id"].astype("object").where(pdf["doc_id"].notna(), None)
            for b, tail, i, text in zip(pdf["bucket"], pdf["tail"], ids, pdf["text"], strict=True):
                if b != bucket:  # the tail row closed the bucket before
                    group, bucket, chars = [], b, 0
                group.append((None if tail or i is None else int(i), text))
                chars += len(text)
                if tail or chars > CHUNK_CHARS:
                    if len(group) > 1:
                        yield work(group)
                    group, chars = [group[-1]], len(text)

    shape = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return with_followers(keyed).mapInPandas(walk, shape)
