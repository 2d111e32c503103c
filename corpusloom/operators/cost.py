"""What running a frame costs: seconds, rows, and the shuffled and spilled bytes that Spark's own status store has."""

from __future__ import annotations

import time
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "stage string, rows long, seconds double, rows_per_second double, cpu_seconds double, shuffle_bytes long, spilled_bytes long"


def measured(spark: SparkSession, name: str, rows: int, df: DataFrame) -> tuple:
    """One row of SCHEMA for writing df to nowhere. The jobs are told apart by a group of their own."""
    sc, group = spark.sparkContext, f"cost-{uuid4().hex}"
    before = sc.getLocalProperty("spark.jobGroup.id")
    sc.setLocalProperty("spark.jobGroup.id", group)
    try:
        begun = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        seconds = time.perf_counter() - begun
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    stages = {s for job in tracker.getJobIdsForGroup(group) if (info := tracker.getJobInfo(job)) for s in info.stageIds}
    found = [store.lastStageAttempt(s) for s in stages]
    spilled = sum(s.memoryBytesSpilled() + s.diskBytesSpilled() for s in found)
    return name, rows, round(seconds, 3), round(rows / seconds, 1), round(sum(s.executorCpuTime() for s in found) / 1e9, 3), sum(s.shuffleWriteBytes() for s in found), spilled
