"""A contact network kept fresh from a stream of events."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def event_stream(spark: SparkSession, path: str, schema_of: DataFrame, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema_of.schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def _timed(events: DataFrame, watermark: str | None) -> DataFrame:
    """Event times as instants, with a watermark where the input is a stream."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", watermark) if events.isStreaming and watermark else timed


def contact_windows(events: DataFrame, window: str = "1 hour", slide: str | None = None, watermark: str | None = "2 hours") -> DataFrame:
    """Events and distinct-kind counts of each user and kind by time window; works on streams and tables alike."""
    timed = _timed(events, watermark)
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return timed.groupBy(span.alias("w"), "user_id", "event_type").agg(F.count("*").alias("n")).select(
        F.unix_micros("w.start").alias("window_start"), "user_id", "event_type", "n"
    )


def session_windows(events: DataFrame, gap: str = "30 minutes", watermark: str | None = "2 hours") -> DataFrame:
    timed = _timed(events, watermark)
    return timed.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("window_start"), "user_id", "n")


def hand_off_stream(events: DataFrame, channel: str = "event_type") -> DataFrame:
    """``(src, tgt, channel)`` of each event and the one before it in its channel, whose last user is the state."""

    def follow(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for user in rows["user_id"].tolist():
            if last is not None and last != user:
                out.append((last, user, key[0]))
            last = user
        if last is not None:
            state.update((last,))
        yield pd.DataFrame(out, columns=["src", "tgt", "channel"])

    return events.groupBy(channel).applyInPandasWithState(
        follow, "src long, tgt long, channel string", "last long", "append", GroupStateTimeout.NoTimeout
    )


def merge_windows(table: str):  # noqa: ANN201
    """A ``foreachBatch`` sink that adds a batch's window counts to a parquet table as one more part (counts are summed on read)."""

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{table}/batch={number}")

    return write


def as_of(events: DataFrame, states: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """The last known ``value`` of a key at or before each event, by one window over the union of both sides."""
    from pyspark.sql.window import Window

    a = events.select("*", F.lit(None).cast(states.schema[value].dataType).alias(value), F.lit(1).alias("_side"))
    b = states.select(*[F.col(c) if c in (key, at) else F.lit(None).cast(events.schema[c].dataType).alias(c) for c in events.columns], value, F.lit(0).alias("_side"))
    upto = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last(value, ignorenulls=True).over(upto)).where("_side = 1").drop("_side")
