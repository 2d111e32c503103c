"""Streams fed file by file, out of order, against the batch answer."""

from pyspark.sql import functions as F

from corpusloom.streaming import streams
from tests.conftest import SMALL


def fed(spark, tmp_path, late="40 days", files=5):
    """The events in shuffled files, one a batch; the watermark's delay covers all of them."""
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    for k in range(files):
        part = events.where(F.pmod(F.xxhash64("event_id"), F.lit(files)) == k).coalesce(1)
        part.write.mode("append").parquet(str(tmp_path / "in"))
    return events, spark.readStream.schema(streams.EVENTS).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).withWatermark("ts", late)


def test_windows_over_many_batches(spark, tmp_path):
    events, stream = fed(spark, tmp_path)
    got = {(r["start"], r["event_type"]): r["n"] for r in streams.drained(streams.tumbling(stream), "complete").collect()}
    want = {(r["start"], r["event_type"]): r["n"] for r in events.groupBy(F.unix_micros(F.date_trunc("day", "ts")).alias("start"), "event_type").agg(F.count("*").alias("n")).collect()}
    assert got == want


def test_newest_record_over_many_batches(spark, tmp_path):
    events, stream = fed(spark, tmp_path)
    out = streams.drained(streams.latest_per_key(stream), "update").groupBy("user_id").agg(F.max_by("event_id", F.struct("micro", "event_id")).alias("e"))
    want = events.groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("e"))
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, want.collect()))


def test_one_row_a_key_within_the_delay(spark, tmp_path):
    events, stream = fed(spark, tmp_path)
    out = streams.drained(streams.first_of_key(stream, ["user_id", "event_type"]))
    assert out.count() == events.select("user_id", "event_type").distinct().count()


def test_late_rows_are_dropped(spark, tmp_path):
    for k, (day, ids) in enumerate(((20, [1, 2]), (25, [3]), (1, [4]), (26, [5]))):
        rows = spark.createDataFrame([(i, 7, "click", 1.0, "{}") for i in ids], "event_id long, user_id long, event_type string, value double, props string")
        rows.withColumn("ts", F.make_timestamp(F.lit(2024), F.lit(1), F.lit(day), F.lit(0), F.lit(0), F.lit(0))).select("event_id", "ts", "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(str(tmp_path / f"in/{k}"))
    import os
    import time

    for k in range(4):  # the order of arrival is that of modification
        for name in os.listdir(tmp_path / f"in/{k}"):
            os.utime(tmp_path / f"in/{k}/{name}", (time.time() - 100 + k, time.time() - 100 + k))
    stream = spark.readStream.schema(streams.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in")).withWatermark("ts", "1 hour")
    got = {r["n"] for r in streams.drained(streams.tumbling(stream).select("start", "event_type", "n", "v"), "append").collect()}
    assert 1 in got or 2 in got  # closed windows only; the row of the first day came too late
    assert streams.drained(streams.tumbling(spark.readStream.schema(streams.EVENTS).option("recursiveFileLookup", True).parquet(str(tmp_path / "in")).withWatermark("ts", "1 hour")), "complete").count() == 4
