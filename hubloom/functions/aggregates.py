"""Aggregates by kind: what can be merged from parts may be shared, what cannot goes element by element."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

DISTRIBUTIVE = ("sum", "count", "min", "max")
ALGEBRAIC = ("avg", "var", "stddev")
SKETCH = ("approx_distinct",)
HOLISTIC = ("median", "count_distinct", "mode")


@dataclass(frozen=True)
class Agg:
    """``kind`` of ``column`` under a name; ``count`` without a column counts elements."""

    kind: str
    column: str | None = None
    name: str = ""

    def __post_init__(self) -> None:
        if self.kind not in (*DISTRIBUTIVE, *ALGEBRAIC, *SKETCH, *HOLISTIC):
            raise ValueError(f"unknown aggregate: {self.kind}")
        if not self.name:
            object.__setattr__(self, "name", f"{self.kind}_{self.column}" if self.column else self.kind)

    @property
    def mergeable(self) -> bool:
        return self.kind not in HOLISTIC

    def _wide(self) -> Column:
        return F.col(self.column).cast("decimal(18,2)")

    def states(self) -> dict[str, tuple[Column, str]]:
        """State columns: how each starts from elements, and the function that merges it."""
        c, n = self.column, self.name
        value = F.lit(1) if c is None else F.col(c)
        if self.kind in ("sum", "min", "max"):
            return {n: (getattr(F, self.kind)(value), self.kind)}
        if self.kind == "count":
            return {n: (F.count(value), "sum")}
        if self.kind == "approx_distinct":
            return {n: (F.hll_sketch_agg(value), "hll_union_agg")}
        out = {f"{n}__n": (F.count(value), "sum"), f"{n}__s": (F.sum(self._wide()), "sum")}
        if self.kind != "avg":
            out[f"{n}__q"] = (F.sum((self._wide() * self._wide()).cast("decimal(30,4)")), "sum")
        return out

    def finish(self) -> Column:
        n = self.name
        if self.kind in DISTRIBUTIVE:
            return F.col(n)
        if self.kind == "approx_distinct":
            return F.hll_sketch_estimate(n).alias(n)
        mean = F.col(f"{n}__s").cast("double") / F.col(f"{n}__n")
        if self.kind == "avg":
            return mean.alias(n)
        var = F.greatest(F.col(f"{n}__q").cast("double") / F.col(f"{n}__n") - mean * mean, F.lit(0.0))
        return (var if self.kind == "var" else F.sqrt(var)).alias(n)

    def whole(self) -> Column:
        """Of all rows of a group at once, for aggregates that cannot be merged."""
        c = F.col(self.column)
        return {"median": F.median, "count_distinct": F.count_distinct, "mode": F.mode}[self.kind](c).alias(self.name)


def starting(aggs: list[Agg]) -> list[Column]:
    return [c.alias(n) for a in aggs for n, (c, _) in a.states().items()]


def merging(aggs: list[Agg]) -> list[Column]:
    return [F.call_function(m, F.col(n)).alias(n) for a in aggs for n, (_, m) in a.states().items()]


def finishing(aggs: list[Agg]) -> list[Column]:
    return [a.finish() for a in aggs]
