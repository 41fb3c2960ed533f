"""Sources and sinks of tables, edge lists and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hubloom.operators.graph import PropertyGraph

EDGE_SCHEMA = T.StructType([T.StructField("src", T.LongType()), T.StructField("tgt", T.LongType()), T.StructField("e_grp", T.LongType()), T.StructField("e_mr", T.LongType())])


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", schema: T.StructType = EDGE_SCHEMA, **options: str) -> PropertyGraph:
    """A graph from an edge list (csv, json, orc, parquet, or text ``src tgt``); its vertices are the ends."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        edges = spark.read.text(path).where(~F.col("value").startswith("#") & (F.trim("value") != "")).select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("tgt"))
    else:
        edges = spark.read.format(fmt).schema(schema).options(**options).load(path)
    vertices = edges.select(F.explode(F.array("src", "tgt")).alias("vid")).distinct()
    return PropertyGraph(vertices, edges, name=path)


def write_graph(graph: PropertyGraph, path: str, buckets: int | None = None, prefix: str | None = None) -> None:
    """Parquet files; with ``buckets``, tables bucketed by id (two copies of the edges, one for each direction)."""
    if buckets is None:
        graph.vertices.write.parquet(f"{path}/vertices")
        graph.edges.write.parquet(f"{path}/edges")
        return
    name = prefix or graph.name
    graph.vertices.write.bucketBy(buckets, "vid").sortBy("vid").option("path", f"{path}/vertices").saveAsTable(f"{name}_vertices")
    for by in ("src", "tgt"):
        graph.edges.write.bucketBy(buckets, by).sortBy(by).option("path", f"{path}/edges_by_{by}").saveAsTable(f"{name}_edges_by_{by}")


def read_graph(spark: SparkSession, path: str) -> PropertyGraph:
    return PropertyGraph(spark.read.parquet(f"{path}/vertices"), spark.read.parquet(f"{path}/edges"), name=path)
