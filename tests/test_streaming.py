from pyspark.sql import functions as F

from hubloom.streaming.contacts import contact_windows, event_stream, hand_off_stream, merge_windows


def test_stream_windows_equal_the_table(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    src = str(tmp_path / "in")
    events.withColumn("ts", F.col("ts").cast("timestamp")).repartition(2).write.parquet(src)
    base = spark.read.parquet(src)
    stream = contact_windows(event_stream(spark, src, base), watermark=None)
    run = stream.writeStream.format("memory").queryName("w").outputMode("complete").trigger(availableNow=True).start()
    run.awaitTermination(120)
    assert sorted(map(tuple, spark.table("w").collect())) == sorted(map(tuple, contact_windows(base).collect()))


def test_stateful_hand_offs_and_sink(spark, sf_dir, tmp_path):
    src = str(tmp_path / "in")
    spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(src)
    base = spark.read.parquet(src)
    run = hand_off_stream(event_stream(spark, src, base)).writeStream.foreachBatch(merge_windows(str(tmp_path / "out"))).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    run.awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out")).select("src", "tgt", "channel").collect()
    want, last = [], {}
    for r in base.orderBy("ts", "event_id").collect():
        before = last.get(r["event_type"])
        if before is not None and before != r["user_id"]:
            want.append((before, r["user_id"], r["event_type"]))
        last[r["event_type"]] = r["user_id"]
    assert sorted(map(tuple, got)) == sorted(want)
