"""Measures of methods against each other: operations saved, crossover, agreement of rankings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def saved_fraction(adds: list[tuple[int, int]]) -> float:
    """Mean share of additions that sharing saves, over (share-nothing, sharing) pairs of a sweep."""
    shares = [1 - shared / nothing for nothing, shared in adds if nothing]
    return sum(shares) / len(shares) if shares else 0.0


def crossover(times: dict[int, tuple[float, float]]) -> int | None:
    """The smallest group cardinality from which share-nothing is no slower, up to the end of the sweep."""
    at = None
    for c in sorted(times, reverse=True):
        nothing, shared = times[c]
        if nothing > shared:
            break
        at = c
    return at


def topk_overlap(exact: list[int], approximate: list[int]) -> float:
    """Share of the exact top that the approximate top has."""
    return len(set(exact) & set(approximate)) / len(exact) if exact else 1.0


def relative_error(exact: DataFrame, approximate: DataFrame, key: str, column: str) -> DataFrame:
    """``(n, mean_error, max_error)`` of an approximate measure where the exact one is positive."""
    both = exact.select(key, F.col(column).alias("a")).join(approximate.select(key, F.col(column).alias("b")), key).where("a > 0")
    error = F.abs(F.col("b") - F.col("a")) / F.col("a")
    return both.agg(F.count("*").alias("n"), F.round(F.avg(error), 6).alias("mean_error"), F.round(F.max(error), 6).alias("max_error"))


def phase_shares(seconds: dict[str, float]) -> dict[str, float]:
    total = sum(seconds.values())
    return {k: round(v / total, 4) if total else 0.0 for k, v in seconds.items()}
