"""Derived views of the given tables, and the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusloom.runtime import table, texts

SNAPSHOTS = 8


def _crawled(df: DataFrame, key: str) -> DataFrame:
    """Each row in a snapshot, every fourth one again in a later snapshot. One scan: the second copy is exploded."""
    first = (F.col(key) % SNAPSHOTS).cast("int")
    again = F.least(F.lit(SNAPSHOTS - 1), F.col(key) % SNAPSHOTS + 1 + F.col(key) % 3).cast("int")
    at = F.explode(F.when(F.col(key) % 4 == 0, F.array(first, again)).otherwise(F.array(first)))
    day = F.expr("add_months(date'2019-01-01', 6 * snapshot_id)")
    return df.withColumn("snapshot_id", at).withColumn("snapshot_date", day).withColumn("year", F.year("snapshot_date")).withColumn("rec_id", F.col(key) * 100 + F.col("snapshot_id"))


def crawl(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _crawled(texts(spark, sf_dir, "pages"), "page_id")


def doc_crawl(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _crawled(texts(spark, sf_dir, "documents").select("doc_id", "text", "lang"), "doc_id")


def image_refs_web(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, pos, image_url): links of pages in order, absolute; they stand in for images."""
    from corpusloom.operators.extract import link_positions

    return link_positions(texts(spark, sf_dir, "pages")).select(F.col("page_id").alias("doc_id"), "pos", F.col("link").alias("image_url"))


def image_refs_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, pos, image_url): an order is a document, a part an image."""
    from pyspark.sql import Window as W

    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate")
    order = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate")
    url = F.concat(F.when(F.col("l_partkey") % 10 == 0, "http").otherwise("https"), F.lit("://img/"), F.when(F.col("l_partkey") % 17 == 0, "logo/").otherwise(""), F.col("l_partkey").cast("string"))
    return line.select(F.col("l_orderkey").alias("doc_id"), F.row_number().over(order).alias("pos"), url.alias("image_url"))


def hash28(text) -> F.Column:
    """The first seven hex digits of an md5, as a number: the same in every engine."""
    return F.conv(F.substring(F.md5(text.cast("binary") if not isinstance(text, str) else F.col(text).cast("binary")), 1, 7), 16, 10).cast("long")


def by_hash(key: str) -> F.Column:
    """An order that depends on the key alone."""
    return F.md5(F.col(key).cast("string").cast("binary"))


H28 = "('0x' || substr(md5({}), 1, 7))::BIGINT"


def _crawl_sql(name: str, source: str, key: str) -> str:
    return f"""{name} AS (SELECT *, {key} * 100 + snapshot_id AS rec_id, CAST(DATE '2019-01-01' + to_months(CAST(6 * snapshot_id AS INTEGER)) AS DATE) AS snapshot_date,
        year(DATE '2019-01-01' + to_months(CAST(6 * snapshot_id AS INTEGER))) AS year FROM (
        SELECT *, {key} % 8 AS snapshot_id FROM {source} UNION ALL SELECT *, least(7, {key} % 8 + 1 + {key} % 3) FROM {source} WHERE {key} % 4 = 0))"""


CRAWL = _crawl_sql("crawl", "pages", "page_id")
DOC_CRAWL = _crawl_sql("doc_crawl", "documents", "doc_id")
LINKS = r"""links AS (SELECT page_id, pos - 1 AS pos, CASE WHEN href LIKE 'http%' THEN href WHEN href LIKE '//%' THEN regexp_extract(url, '^https?:') || href
        WHEN href LIKE '/%' THEN regexp_extract(url, '^https?://[^/]*') || href ELSE regexp_extract(url, '^https?://[^/]*') || '/' || href END AS link
        FROM (SELECT page_id, url, unnest(l) AS href, generate_subscripts(l, 1) AS pos FROM (SELECT page_id, url, regexp_extract_all(html, '<a href="([^"]*)"', 1) AS l FROM pages)))"""
REFS_WEB = LINKS + ", refs AS (SELECT page_id AS doc_id, pos, link AS image_url FROM links)"
REFS_STAR = """refs AS (SELECT l_orderkey AS doc_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate) AS pos,
        CASE WHEN l_partkey % 10 = 0 THEN 'http' ELSE 'https' END || '://img/' || CASE WHEN l_partkey % 17 = 0 THEN 'logo/' ELSE '' END || l_partkey AS image_url FROM lineitem)"""
