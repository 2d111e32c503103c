"""What every operator needs from the session it is given."""

from __future__ import annotations

import os
import sys

from pyspark.sql import DataFrame, SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ensure_importable(spark: SparkSession) -> None:
    """Let Python workers on this machine import the package; on a cluster ship it with --py-files."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *paths])
    if ROOT not in sys.path:
        sys.path.insert(0, ROOT)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the checkpoint folder set in the session.

    Without either, a session on one machine gets a folder below its warehouse; a cluster gets an error, as no local
    folder would do.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = f"{spark.conf.get('spark.sql.warehouse.dir')}/corpusloom-checkpoints"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def remove(spark: SparkSession, folder: str) -> None:
    """Deletes a folder of stored results, wherever it is; none is no error."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def cut(df: DataFrame, batch: int | None = None) -> DataFrame:
    """Store a narrow result in the shared folder and cut its lineage, so that a lost executor costs one read.

    batch, where given, is the number of rows that cross to Python at once while this result is made: fewer where rows
    are whole texts. The session's own number is put back.
    """
    spark = df.sparkSession
    shared_dir(spark)
    if batch is None:
        return df.checkpoint(eager=True)
    before = spark.conf.get(_BATCH)
    spark.conf.set(_BATCH, str(min(batch, int(before))))
    try:
        return df.checkpoint(eager=True)
    finally:
        spark.conf.set(_BATCH, before)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of input a core below which a table in few files is dealt out, and bytes that are worth a task.
FEW, WORTH = 64 << 20, 256 << 10


def texts(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of texts, over all cores.

    A row group is read by one task, so a small table in few files keeps few cores busy with all that is done to its texts.
    Such a table is dealt out first; filters and column pruning pass below that exchange. A table of FEW a core or more has
    row groups enough and is read as it is, so what the exchange moves has a bound.
    """
    df, cores = table(spark, sf_dir, name), spark.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if size >= cores * FEW or (files := len(df.inputFiles())) >= cores:
        return df
    parts = min(2 * cores, size // WORTH)
    return df.repartition(parts) if parts > files else df
