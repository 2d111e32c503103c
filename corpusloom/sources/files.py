"""Readers and writers: columnar, line-based and binary files, and records of web archives."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read_jsonl(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("header", True).csv(path)


def read_orc(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).orc(path)


def read_texts(spark: SparkSession, path: str, whole: bool = False) -> DataFrame:
    """(path, text) of text files, a row for each line, or for each file."""
    return spark.read.option("wholetext", whole).text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))


def read_images(spark: SparkSession, path: str) -> DataFrame:
    """(path, length, content) of binary files."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")


def write_by_snapshot(df: DataFrame, path: str) -> None:
    """Parquet by year and snapshot, rows sorted by id within files so that later semi joins prune."""
    df.repartition("year", "snapshot_id").sortWithinPartitions("rec_id").write.mode("overwrite").partitionBy("year", "snapshot_id").parquet(path)


def write_parallel_lists(df: DataFrame, path: str) -> None:
    """JSON lines of texts and images; nulls are kept, they carry the order."""
    df.write.mode("overwrite").option("ignoreNullFields", False).json(path)


def write_orc(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("compression", "zstd").orc(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 64) -> None:
    """A table whose joins on key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def archive_records(spark: SparkSession, path: str) -> DataFrame:
    """(url, html) of text archives in which records follow each other, each with header lines, an empty line and a body.

    Hadoop's splitter cuts files at the record mark, so large files are read by many tasks.
    """
    raw = spark.read.option("lineSep", "WARC/1.0").text(path).where(F.length(F.trim("value")) > 0)
    url = F.regexp_extract("value", r"(?im)^WARC-Target-URI: *<?([^\r\n>]*)", 1)
    body = F.regexp_extract("value", r"(?s)^.*?\r?\n\r?\n(?:HTTP/.*?\r?\n\r?\n)?(.*)$", 1)
    return raw.where(F.col("value").rlike(r"(?im)^WARC-Type: *(?:response|conversion|resource)")).select(url.alias("url"), F.regexp_replace(body, r"\s+\z", "").alias("html"))


class SequenceSource(DataSource):
    """A source of crawl ids by snapshot, as an example of the data source API: spark.read.format('crawl_ids')."""

    @classmethod
    def name(cls) -> str:
        return "crawl_ids"

    def schema(self) -> str:
        return "rec_id bigint, snapshot_id int"

    def reader(self, schema) -> DataSourceReader:
        n, snapshots = int(self.options.get("rows", "100")), int(self.options.get("snapshots", "8"))

        class Reader(DataSourceReader):
            def partitions(self) -> list[InputPartition]:
                return [InputPartition(k) for k in range(snapshots)]

            def read(self, partition: InputPartition) -> Iterator[tuple]:
                return ((i * 100 + partition.value, partition.value) for i in range(partition.value, n, snapshots))

        return Reader()
