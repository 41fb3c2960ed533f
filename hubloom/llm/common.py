"""Shared plumbing: table reading, shared scratch space, connected components."""

from __future__ import annotations

import atexit
import gc
import inspect
import shutil
import tempfile
import time
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_scratch_made: list = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Just the key and the text (null text: empty), so that no other column can clash."""
    return docs.select(
        F.col(key).cast("long").alias("doc_id"),
        F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"),
    )


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir`` where the session names one.

    Only when it is unset (tests, a laptop) a folder of our own is chosen.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    sc = spark.sparkContext
    current = sc.getCheckpointDir()
    if named:
        if current is None:
            sc.setCheckpointDir(named)
        return named.rstrip("/")
    if current is None:
        if sc.master.split("[")[0] != "local":
            raise ValueError("name a folder that all executors share in spark.checkpoint.dir")
        own = tempfile.mkdtemp(prefix="hubloom-")
        atexit.register(shutil.rmtree, own, True)
        sc.setCheckpointDir("file://" + own)
        current = sc.getCheckpointDir()
    return current.rstrip("/")


def scratch_dir(spark: SparkSession, label: str) -> str:
    path = f"{shared_root(spark)}/hubloom-{label}-{uuid.uuid4().hex[:12]}"
    if not _scratch_made:
        atexit.register(_release_all)
    _scratch_made.append((spark, path))
    return path


def release_scratch(spark: SparkSession) -> None:
    """Delete every scratch table written so far; results that still read one must be saved first."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    while _scratch_made:
        _, path = _scratch_made.pop()
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(conf).delete(p, True)


def _release_all() -> None:
    try:
        if _scratch_made:
            release_scratch(_scratch_made[-1][0])
    except Exception:  # the JVM may be gone at interpreter exit
        pass


def saved(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch_dir(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Buckets of a table at most (Spark's own limit is 100,000).
MOST_BUCKETS = 50_000


def even_homes(docs: DataFrame) -> list[int]:
    """A number for each partition of ``docs`` (or for ``MOST_BUCKETS`` of them), each in a bucket of its own."""
    n = max(1, min(docs.rdd.getNumPartitions(), MOST_BUCKETS))
    many = n * (20 + 2 * n.bit_length())
    number = F.col("id").cast("int")
    found = docs.sparkSession.range(many).groupBy(F.pmod(F.hash(number), F.lit(n)).alias("bucket")).agg(F.min(number).alias("home")).collect()
    by_bucket = {r["bucket"]: r["home"] for r in found}
    return [by_bucket.get(b, many + b) for b in range(n)]


def first_batch(homes: list[int]) -> int:
    """Number of the first batch of this task: its home above 32 bits, then room for 65,536 batches."""
    from pyspark import TaskContext

    part = TaskContext.get().partitionId()
    return homes[part % len(homes)] << 32 | part // len(homes) << 16


def saved_in_place(df: DataFrame, homes: list[int], label: str) -> DataFrame:
    """Like ``saved``, as a table bucketed by the home of ``batch`` (as ``home``): a later join on it alone does not shuffle these rows."""
    spark = df.sparkSession
    path = scratch_dir(spark, label)
    name = f"hubloom_{label}_{path[-12:]}"
    df.select(F.shiftright("batch", 32).cast("int").alias("home"), "*").write.bucketBy(len(homes), "home").option("path", path).saveAsTable(name)
    return spark.table(name)


def with_answers(batches: DataFrame, answers: DataFrame, how: str = "inner") -> DataFrame:
    """Rows of ``saved_in_place`` with the ``answers(batch, ..)`` to them, which alone are shuffled."""
    theirs = answers.select(F.shiftright("batch", 32).cast("int").alias("home"), F.col("batch").alias("of"), *[c for c in answers.columns if c != "batch"])
    return batches.join(theirs, (batches["home"] == theirs["home"]) & (batches["batch"] - theirs["of"] == 0), how).drop(theirs["home"])


def release_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished steps: their owners are garbage once their result is saved.

    Without it, files stay until the driver happens to collect its garbage.
    """
    for _ in range(2):  # the second finds what the first has let go
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.5)


def trimmed(work: Callable) -> Callable:
    """A function of Pandas frames (an iterator's or a group's) after which its worker gives freed memory back: workers wait for tasks with what they hold."""

    def give_back() -> None:
        import ctypes

        import pyarrow as pa

        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # where the C library has it
            trim(0)

    def each(frames):  # noqa: ANN001, ANN202
        yield from work(frames)
        give_back()

    def group(pdf):  # noqa: ANN001, ANN202
        out = work(pdf)
        give_back()
        return out

    return each if inspect.isgeneratorfunction(work) else group


def sha256_hex(col: Column) -> Column:
    return F.sha2(col, 256)


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable id for each vertex of ``edges(a long, b long)``: rows ``(node, root)``.

    Alternating large-star / small-star contraction: both are grouped minima
    (combined map-side) joined back to the edge list.  No neighbour list is
    gathered, but the edges of a large star share a join key: they stream through
    a merge join, which adaptive execution splits where it is skewed.  Rounds stop
    when the edge list no longer changes (a stable star forest).  Vertices
    without an edge do not occur in the result.
    """
    e = saved(
        edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct(),
        "cc0",
    )
    seen = None
    for i in range(max_rounds):
        # Each vertex points at the least of itself and its neighbours.
        sym = e.select(F.col("hi").alias("v"), F.col("lo").alias("u")).unionAll(
            e.select(F.col("lo").alias("v"), F.col("hi").alias("u"))
        )
        least = sym.groupBy("v").agg(F.min("u").alias("m")).select("v", F.least("v", "m").alias("m"))
        # Large star: larger neighbours of v move to v's minimum.
        large = sym.where("u > v").join(least, "v").select(F.col("u").alias("hi"), F.col("m").alias("lo"))
        large = large.where("hi <> lo").distinct()
        # Small star: smaller neighbours of v, and v itself, move to the least of them.
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = (
            large.join(low, "hi")
            .select(F.explode(F.array(F.col("lo"), F.col("hi"))).alias("hi"), F.col("m").alias("lo"))
            .where("hi <> lo")
            .distinct()
        )
        e = saved(small, f"cc{i + 1}")
        mark = e.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if seen == tuple(mark):
            break
        seen = tuple(mark)
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionAll(
        e.select("lo", "lo").toDF("node", "root").distinct()
    )
