"""Samples that depend on keys alone, so that any engine draws the same."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.sources.views import by_hash, hash28


def exact_k(df: DataFrame, k: int, key: str, bins: int = 1 << 16) -> DataFrame:
    """k rows in the order of the key's hash, without a sort of k rows anywhere.

    Rows are counted by the hash's first 16 bits; whole bins below the one that holds the k-th row are taken by a
    filter, and only that bin, a 65,536th of the rows, is ordered and trimmed. Rows with a null key come last.
    """
    place = F.coalesce(F.conv(F.substring(by_hash(key), 1, 4), 16, 10).cast("int"), F.lit(bins))
    counts = sorted((r["bin"], r["n"]) for r in df.groupBy(place.alias("bin")).agg(F.count("*").alias("n")).collect())
    below = 0
    for last, n in counts:
        if below + n >= k:
            break
        below += n
    else:
        return df
    edge = df.where(place == last).orderBy(by_hash(key).asc_nulls_last(), key).limit(k - below)
    return df.where(place < last).unionByName(edge)


def bernoulli(df: DataFrame, share: float, key: str) -> DataFrame:
    return df.where(hash28(F.col(key).cast("string")) % 1000 < round(share * 1000))


def balanced(pos: DataFrame, neg: DataFrame, k: int, key: str = "doc_id") -> DataFrame:
    """k rows of each, with y 1 and 0."""
    return exact_k(pos, k, key).withColumn("y", F.lit(1)).unionByName(exact_k(neg, k, key).withColumn("y", F.lit(0)))


def split(df: DataFrame, key: str, test_share: float = 0.2) -> DataFrame:
    return df.withColumn("split", F.when(hash28(F.col(key).cast("string")) % 1000 < round(test_share * 1000), "test").otherwise("train"))


def from_scores(df: DataFrame, cut: int = 6, inclusive: bool = True) -> DataFrame:
    """Rows whose score reaches the cut; scores outside 0 to 10 count for neither class."""
    good = F.col("score").between(0, 10)
    return df.where(good & (F.col("score") >= cut if inclusive else F.col("score") > cut))
