"""Quality classification by importance resampling.

Two generative models of hashed n-grams - of the target texts (labelled good and
not toxic) and of the raw corpus - give each n-gram a log ratio, and a text the
sum of those of its n-grams.  The corpus is resampled without replacement by
Gumbel top-k: the k documents of largest ``log weight + Gumbel noise``, k being
the number of documents whose weight favours the target.  Documents outside the
sample are rejected.

``weigh="ratio"`` takes the sum as the log weight, as it is.  A long text with a
few words of the worst kind then still has a large sum, and many are kept; so
``weigh="calibrated"``, the default, fits the weight by what the ratios of a
text say - their mean, the mass of strongly raw-only words, its share, and the
strongest - on a bounded sample of labelled rows, and scales the noise down to
the size of such log odds.

The raw model covers all rows; a task sends one dense vector of ``BUCKETS``
counts for each model, never an n-gram.  Labels are read by a bounded sample, the
``SAMPLE_ROWS`` of least hashed id, which is small enough to broadcast: three
quarters of it make the target model, one quarter the calibration.

Null texts are empty; an empty text has neutral ratios.  Noise is a function of
id and text, so repeated rows tie and are kept or rejected together: at the k-th
key all tied rows are kept.  Rows that repeat a labelled id count once in the
calibration, by the least hash of their text.  Labels without a document, and
null labels, are left out; of contradicting labels the worst counts.  Without
labels of both kinds every document is kept; without documents none is.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import saved

#: Hash buckets of the n-gram models.
BUCKETS = 1 << 19
HALF = BUCKETS // 2
#: Weight, in expected counts, of the prior that pulls a rare bucket to ratio one.
PRIOR = 2.0
#: Log ratios below this are evidence against the target.
AGAINST = -1.5
#: Labelled rows that are read at most (id and one flag each: under a megabyte).
SAMPLE_ROWS = 40_000
#: Standard deviations of Gumbel noise are small beside calibrated log odds; this scales them.
TEMPERATURE = 0.25
CACHE_ENTRIES = 300_000

_PIECES = re.compile(r"\w+|[^\w\s]+")


class _Hashes(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


_hashes = _Hashes()


def ngram_buckets(text: str) -> tuple[np.ndarray, int]:
    """Buckets of all words (and runs of marks), then of all pairs of neighbours; and how many are words."""
    words = _PIECES.findall(text.lower())
    h = np.array(list(map(_hashes.__getitem__, words)), dtype=np.uint64)
    with np.errstate(over="ignore"):
        pairs = (h[:-1] * np.uint64(0x9E3779B97F4A7C15)) ^ (h[1:] + np.uint64(0x632BE59BD9B4E019))
        both = np.concatenate([h, pairs * np.uint64(0xD6E8FEB86659FD93)]) if len(h) > 1 else h
    # Words and pairs have a half of the buckets each, so that rare pairs don't blur telling words.
    buckets = (both >> np.uint64(64 - HALF.bit_length() + 1)).astype(np.int64)
    buckets[len(h) :] += HALF
    return buckets, len(h)


def bucket_counts(rows: DataFrame, target_ids: Broadcast) -> tuple[np.ndarray, np.ndarray]:
    """Counts over all of ``rows(doc_id, text)``: of the target's texts, and of all."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        target, raw = np.zeros(BUCKETS, dtype=np.int64), np.zeros(BUCKETS, dtype=np.int64)
        for pdf in batches:
            for i, text in zip(pdf["doc_id"], pdf["text"], strict=True):
                grams, _ = ngram_buckets(text)
                np.add.at(raw, grams, 1)
                if i in target_ids.value:
                    np.add.at(target, grams, 1)
        at = np.flatnonzero(raw)
        yield pd.DataFrame({"bucket": at, "target": target[at], "raw": raw[at]})

    parts = rows.select("doc_id", "text").mapInPandas(count, "bucket int, target long, raw long")
    sums = parts.groupBy("bucket").agg(F.sum("target").alias("target"), F.sum("raw").alias("raw")).toPandas()  # at most BUCKETS rows
    target, raw = np.zeros(BUCKETS), np.zeros(BUCKETS)
    target[sums["bucket"]], raw[sums["bucket"]] = sums["target"], sums["raw"]
    return target, raw


def log_ratios(target: np.ndarray, raw: np.ndarray) -> np.ndarray:
    """log p(bucket | target) / p(bucket | raw), shrunk to zero where little is expected."""
    expected = raw * (target.sum() / max(raw.sum(), 1.0))
    return np.log((target + PRIOR) / (expected + PRIOR))


FEATURES = ["mean", "against", "share", "worst"]


def _features(lr: np.ndarray, words: int) -> tuple[float, ...]:
    """Mean ratio; evidence against the target of single words: its mass, its share, and the strongest."""
    if not len(lr):
        return 0.0, 0.0, 0.0, 0.0
    single = lr[:words]
    against = float(np.maximum(AGAINST - single, 0).sum())
    return float(lr.mean()), float(np.log1p(against)), float(np.sqrt(against / words)), float(single.min())


def calibrate(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the last coefficient is the constant."""
    x = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * w
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _kth_largest(keys: DataFrame, k: int) -> float | None:
    """The k-th largest of ``keys(key double)``: histograms of ever narrower ranges, no global sort."""
    lo, hi, n = keys.agg(F.min("key"), F.max("key"), F.count("key")).first()
    if not n or k <= 0:
        return None
    if k >= n:
        return lo
    while lo < hi:
        width = (hi - lo) / 4096
        if width <= abs(hi) * 1e-15 or width == 0:
            break
        slot = F.least(F.floor((F.col("key") - lo) / width), F.lit(4095)).cast("int")
        inside = keys.where((F.col("key") >= lo) & (F.col("key") <= hi))
        rows = inside.groupBy(slot.alias("slot")).agg(F.count("*").alias("n"), F.min("key").alias("lo"), F.max("key").alias("hi")).collect()  # at most 4096
        above = 0
        for r in sorted(rows, key=lambda r: -r["slot"]):
            if above + r["n"] >= k:
                lo, hi, k = r["lo"], r["hi"], k - above
                break
            above += r["n"]
    return lo


def label_sample(labels: DataFrame, rows: int = SAMPLE_ROWS) -> pd.DataFrame:
    """At most ``rows`` labelled ids: ``(doc_id, good, fit)``; ``fit`` marks the quarter for the calibration."""
    judged = (
        labels.where("doc_id is not null and quality is not null and toxic is not null")
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.min((F.col("quality") == 1) & (F.col("toxic") == 0)).alias("good"))
    )
    hashed = judged.withColumn("h", F.xxhash64("doc_id")).orderBy("h", "doc_id").limit(rows)
    return hashed.select("doc_id", "good", (F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(4)) == 0).alias("fit")).toPandas()


def score_documents(docs: DataFrame, labels: DataFrame, weigh: str = "calibrated") -> DataFrame:
    """``(doc_id, row, log_ratio, log_weight, key)`` of every row of ``docs(doc_id, text)``."""
    if weigh not in ("calibrated", "ratio"):
        raise ValueError(f"unknown weight: {weigh}")
    spark = docs.sparkSession
    sample = label_sample(labels)
    target_ids = spark.sparkContext.broadcast(frozenset(sample.loc[sample["good"] & ~sample["fit"], "doc_id"].tolist()))
    target, raw = bucket_counts(docs, target_ids)
    ratios = spark.sparkContext.broadcast(log_ratios(target, raw).astype(np.float32))  # BUCKETS numbers

    def measure(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = []
            for text in pdf["text"]:
                grams, words = ngram_buckets(text)
                rows.append((len(grams), *_features(ratios.value[grams], words)))
            out = pd.DataFrame(rows, columns=["grams", *FEATURES])
            yield pd.concat([pdf[["doc_id", "row"]].reset_index(drop=True), out], axis=1)

    row = F.xxhash64(F.coalesce(F.col("doc_id"), F.lit(-(2**63))), F.col("text")).alias("row")
    shape = "doc_id long, row long, grams long, " + ", ".join(f"{f} double" for f in FEATURES)
    seen = saved(docs.select("doc_id", row, "text").mapInPandas(measure, shape), "quality")
    log_ratio = F.col("mean") * F.col("grams")
    log_weight, scale = log_ratio, 1.0
    if weigh == "calibrated":
        fit = spark.createDataFrame(sample.loc[sample["fit"], ["doc_id", "good"]].reset_index(drop=True), "doc_id long, good boolean")
        once = seen.join(F.broadcast(fit), "doc_id").groupBy("doc_id", "good").agg(F.min_by(F.struct(*FEATURES), "row").alias("f"))  # at most a row a label
        known = once.orderBy("doc_id").select("good", "f.*").toPandas()
        weights = np.array([0.0] * len(FEATURES) + [1.0])
        if known["good"].nunique() == 2:
            weights = calibrate(known[FEATURES].to_numpy(), known["good"].astype(float).to_numpy())
        log_weight, scale = F.lit(float(weights[-1])), TEMPERATURE
        for f, w in zip(FEATURES, weights, strict=False):
            log_weight = log_weight + F.lit(float(w)) * F.col(f)
    elif sample["good"].nunique() < 2:
        log_weight = F.lit(1.0)
    return seen.select("doc_id", "row", log_ratio.alias("log_ratio"), log_weight.alias("log_weight"), (log_weight + gumbel(F.col("row")) * scale).alias("key"))


def gumbel(row: Column) -> Column:
    """Gumbel noise of a row's hash: a uniform number in (0, 1), then -log(-log(u))."""
    u = (F.pmod(F.xxhash64(row, F.lit(2024)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    return -F.log(-F.log(u))


def resample(docs: DataFrame, labels: DataFrame, k: int | None = None, weigh: str = "calibrated") -> DataFrame:
    """Scores of the documents that importance resampling keeps (``k`` of them; by default those its weights favour)."""
    scores = saved(score_documents(docs, labels, weigh), "scores")
    if k is None:
        k = scores.where("log_weight > 0").count()
    least = _kth_largest(scores.select("key"), k)
    return scores.where(F.lit(False) if least is None else F.col("key") >= F.lit(least))
