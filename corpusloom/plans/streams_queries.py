"""Streaming queries, run over what is there and read back as tables."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpusloom.plans.registry import query
from corpusloom.runtime import table
from corpusloom.streaming import streams

query("st_tumbling", "SELECT epoch_us(date_trunc('day', ts)) AS start, event_type, count(*) AS n, round(sum(value), 2) AS v FROM events GROUP BY ALL")(streams.run(streams.tumbling, "complete"))
query("st_sliding", "SELECT epoch_us(s) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS s FROM events) GROUP BY ALL")(streams.run(streams.sliding, "complete"))
query("st_session", "WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM g GROUP BY user_id, k")(streams.run(streams.sessions, "complete"))


@query("st_dedup_watermark", "SELECT event_type, count(DISTINCT user_id) AS n FROM events GROUP BY event_type")
def dedup(spark, sf):
    """One event of each user and type within the delay: all rows arrive in one batch here."""
    return streams.drained(streams.first_of_key(streams.arrivals(spark, sf), ["user_id", "event_type"])).groupBy("event_type").agg(F.count("*").alias("n"))


@query("st_latest_per_key", "SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id, epoch_us(max(ts)) AS micro FROM events GROUP BY user_id")
def latest(spark, sf):
    out = streams.drained(streams.latest_per_key(streams.arrivals(spark, sf)), "update")
    return out.groupBy("user_id").agg(F.max_by("event_id", F.struct("micro", "event_id")).alias("event_id"), F.max("micro").alias("micro"))


@query("st_interval_join", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
def interval(spark, sf):
    return streams.drained(streams.interval_join(streams.arrivals(spark, sf), streams.arrivals(spark, sf)))


@query("w19_stream_equals_batch", "SELECT count(DISTINCT user_id) AS keys, count(DISTINCT user_id) AS same FROM events")
def w19(spark, sf):
    """The stream's newest record of each user against the batch's."""
    stream = latest(spark, sf).select("user_id", F.col("event_id").alias("s"))
    w = W.partitionBy("user_id").orderBy(F.col("ts").desc(), F.col("event_id").desc())
    batch = table(spark, sf, "events").select("user_id", "event_id", "ts").withColumn("n", F.row_number().over(w)).where("n = 1")
    return batch.join(stream, "user_id", "full").agg(F.count("*").alias("keys"), F.sum((F.col("event_id") == F.col("s")).cast("long")).alias("same"))
