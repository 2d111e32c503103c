"""The arrival stream: windows, late rows, online URL dedup, newest record per key, interval joins."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from uuid import uuid4

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from corpusloom.runtime import ensure_importable, shared_dir

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def arrivals(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    """Events as they arrive, with a watermark."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withWatermark("ts", late)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now and gives its output as a table.

    Output and progress go to the shared folder. Complete mode replaces the output at each batch; append adds to it.
    """
    spark = df.sparkSession
    folder = f"{shared_dir(spark)}/stream-{uuid4().hex}"

    def put(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out" if mode == "complete" else f"{folder}/out/batch={k}")

    q = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.read.schema(df.schema).parquet(f"{folder}/out")
    return out.select(*df.columns)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    w = F.window("ts", width)
    return events.groupBy(w, "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("v")).select(F.unix_micros("window.start").alias("start"), "event_type", "n", F.round("v", 2).alias("v"))


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    s = F.session_window("ts", gap)
    return events.groupBy(s, "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_micros("session_window.start").alias("start"), "n")


def first_of_key(events: DataFrame, keys: list[str]) -> DataFrame:
    """One row for each key within the watermark's delay: URL dedup online, with state that ends."""
    return events.dropDuplicatesWithinWatermark(keys)


def latest_per_key(events: DataFrame) -> DataFrame:
    """(user_id, event_id, ts): the newest event of each user, by state that Python keeps for it; update mode."""
    ensure_importable(events.sparkSession)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else (pd.Timestamp.min.value // 1000, -1)
        for f in frames:
            micro = f["ts"].astype("datetime64[us]").astype("int64")
            best = max(best, max(zip(micro.tolist(), f["event_id"].tolist(), strict=True)))
        state.update(best)
        yield pd.DataFrame({"user_id": [key[0]], "event_id": [best[1]], "micro": [best[0]]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, event_id bigint, micro bigint", "micro bigint, event_id bigint", "update", GroupStateTimeout.NoTimeout)


def interval_join(events: DataFrame, other: DataFrame, within: str = "1 hour") -> DataFrame:
    """(purchase, click): a user's purchases with clicks up to `within` before; state ends with the watermark."""
    p = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    c = other.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return p.join(c, F.expr(f"u1 = u2 AND t2 <= t1 AND t2 >= t1 - interval {within}")).select("purchase", "click")


def run(build: Callable[[DataFrame], DataFrame], mode: str = "append") -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: drained(build(arrivals(spark, sf)), mode)
