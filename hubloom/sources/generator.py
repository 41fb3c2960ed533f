"""The random acyclic graph as a batch source: ``spark.read.format("hubloom_dag").options(n=..., degree=...)``.

Partitions are ranges of edge numbers, so a graph of any size is drawn in
parallel and a lost partition is drawn again alike.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import LongType, StructField, StructType


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__(lo)
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.degree = int(options.get("n", 1000)), int(options.get("degree", 8))
        self.seed, self.parts = options.get("seed", "1"), int(options.get("partitions", 8))

    def partitions(self) -> list[_Range]:
        total = self.n * self.degree
        step = max(1, -(-total // self.parts))
        return [_Range(lo, min(total, lo + step)) for lo in range(0, total, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        return _drawn(range(partition.lo, partition.hi), self.n, self.seed)


def _drawn(numbers: Iterable[int], n: int, seed: str) -> Iterator[tuple]:
    draw = lambda tag, i: int(hashlib.md5(f"{seed}{tag}{i}".encode()).hexdigest()[:8], 16) % n
    for i in numbers:
        a, b = draw("a", i), draw("b", i)
        if a != b:
            yield (min(a, b), max(a, b), i)


def drawn_from(numbers: DataFrame, n: int, seed: str = "1") -> DataFrame:
    """The same edges ``(src, tgt, number)``, one for each of the numbers in a table's only column."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield pd.DataFrame(_drawn(f.iloc[:, 0].tolist(), n, seed), columns=["src", "tgt", "number"])

    return numbers.mapInPandas(run, "src long, tgt long, number long")


class DagSource(DataSource):
    """Rows ``(src, tgt, number)``: drawn edges from lower to higher ids, repeats included."""

    @classmethod
    def name(cls) -> str:
        return "hubloom_dag"

    def schema(self) -> StructType:
        return StructType([StructField("src", LongType()), StructField("tgt", LongType()), StructField("number", LongType())])

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(DagSource)
