"""Joins that Spark has no operator for: as-of, range, neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left (key, at) with the latest right value at or before it. One shuffle of both sides' union, no pairs of rows."""
    both = left.select(key, at, F.lit(1).alias("__l"), F.lit(None).cast(right.schema[value].dataType).alias(value)).unionByName(right.select(key, at, F.lit(0).alias("__l"), value))
    order = W.partitionBy(key).orderBy(at, "__l").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(order)).where("__l = 1").drop("__l")


def in_range(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """points joined to the ranges that hold them (both ends included), as an equi join on cells of the given width.

    A range is repeated for each cell it touches; width is best near the usual range's length.
    """
    p = points.withColumn("__cell", F.floor(F.col(at) / width))
    r = ranges.withColumn("__cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(r, "__cell").where(F.col(at).between(F.col(low), F.col(high))).drop("__cell")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An inner join whose left side is skewed: its rows are dealt over salts, the right side is repeated for each."""
    spread = left.withColumn("__s", F.pmod(F.xxhash64(F.struct(*left.columns)), F.lit(salts)))
    return spread.join(right.withColumn("__s", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long")))), [key, "__s"]).drop("__s")
