"""Set membership by a small bit filter that is broadcast, with an exact join behind it.

The filter has at most 2^FILTER_BITS bits whatever the data; sets too large for that are joined by shuffling. False hits
cost a shuffled row and never change a result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: 2^27 bits are 2^21 rows of two longs.
FILTER_BITS = 27


def bits_for(n: int, most: int = FILTER_BITS) -> int | None:
    """Bits for n members, None if a filter that large isn't allowed."""
    return None if 16 * n > 1 << most else max(10, math.ceil(math.log2(max(1, 16 * n))))


def flag(rows: DataFrame, h: Column, members: DataFrame, bits: int, name: str = "__maybe") -> DataFrame:
    """rows with a boolean: false means that no member (column h, a long) equals the row's h."""
    spot = lambda x: x.bitwiseAND(F.lit((1 << bits) - 1))
    words = members.select(F.shiftright(spot(F.col("h")), 6).alias("__word"), F.expr("shiftleft(1L, cast(h & 63 as int))").alias("bit")).groupBy("__word").agg(F.bit_or("bit").alias("__set"))
    marked = rows.withColumn("__h", h).withColumn("__word", F.shiftright(spot(F.col("__h")), 6)).join(F.broadcast(words), "__word", "left")
    met = F.coalesce(F.expr("(shiftright(__set, cast(__h & 63 as int)) & 1) = 1"), F.lit(False))
    return marked.withColumn(name, met).drop("__h", "__word", "__set")


def wrapped(rows: DataFrame, **more: Column) -> DataFrame:
    """(__row, more...): rows as one struct beside working columns, so that no name of theirs clashes with one of ours."""
    return rows.select(F.struct(*(F.col(f"`{c}`") for c in rows.columns)).alias("__row"), *(c.alias(name) for name, c in more.items()))


def unwrapped(rows: DataFrame) -> DataFrame:
    return rows.select("__row.*")


def without(rows: DataFrame, lost: DataFrame, keys: list[str], most: int = FILTER_BITS) -> DataFrame:
    """rows without those whose keys are in lost (distinct keys; null equals null). Only rows that the filter flags are shuffled."""
    n = lost.count()
    if not n:
        return rows
    own = [f"__k{i}" for i in range(len(keys))]
    lost = lost.select(*(F.col(k).alias(f"__l{i}") for i, k in enumerate(keys)))
    inside = wrapped(rows, **{name: F.col(f"`{k}`") for name, k in zip(own, keys, strict=True)})
    on = [F.col(f"__k{i}").eqNullSafe(F.col(f"__l{i}")) for i in range(len(keys))]
    if (bits := bits_for(n, most)) is None:
        return unwrapped(inside.join(lost, on, "left_anti"))
    marked = flag(inside, F.xxhash64(*own), lost.select(F.xxhash64(*(f"__l{i}" for i in range(len(keys)))).alias("h")), bits)
    return unwrapped(marked.where("not __maybe").select("__row")).unionByName(unwrapped(marked.where("__maybe").join(lost, on, "left_anti")))
