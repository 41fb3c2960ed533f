"""Where iterative operators keep their steps: tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Up to this many edges a whole-graph loop runs as one task (16 bytes an edge); above it, as joins.
LOCAL_EDGES = 2_000_000

_made: list[tuple[SparkSession, str]] = []


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` where the session names it; a folder of our own only where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    current = spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if current is None:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("name a folder that all executors share in spark.checkpoint.dir")
        own = tempfile.mkdtemp(prefix="hubloom-")
        atexit.register(shutil.rmtree, own, True)
        spark.sparkContext.setCheckpointDir("file://" + own)
        current = spark.sparkContext.getCheckpointDir()
    return current.rstrip("/")


def saved(df: DataFrame, label: str, **options: str) -> DataFrame:
    """Write a step and read it back: lineage is cut, and a lost executor loses nothing of it."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/hubloom-{label}-{uuid.uuid4().hex[:12]}"
    if not _made:
        atexit.register(_at_exit)
    _made.append((spark, path))
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Delete the steps written so far; lazy results that read one must be saved first."""
    while _made:
        _, path = _made.pop()
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def _at_exit() -> None:
    try:
        if _made:
            release(_made[-1][0])
    except Exception:  # the JVM may have ended first
        pass
