"""Connected components of an edge table by star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import cut


def _point_at_least(pairs: DataFrame) -> DataFrame:
    """(u, v, low): low is the least of u and all v beside it. Partial minima come before the shuffle."""
    low = pairs.groupBy("u").agg(F.min("v").alias("lv")).select("u", F.least("u", "lv").alias("low"))
    return pairs.join(low, "u")


def components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(node, component): component is the least node reachable; nodes without an edge to another node are left out.

    Rounds alternate two contractions until each node but the least of its component has exactly one edge, to that
    least node. The driver reads two numbers a round and never an edge. A round's edges are checkpointed.
    Null ends and loops are ignored, repeated and reversed edges count once.
    """
    now = cut(
        edges.select(F.col(src).alias("a"), F.col(dst).alias("b")).where("a is not null and b is not null and a <> b")
        .select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    )
    state = None
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        outward = _point_at_least(both).where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).where("u <> v").distinct()
        inward = _point_at_least(outward)
        now = cut(
            inward.select(F.explode(F.array(F.struct("u", F.col("low").alias("v")), F.struct(F.col("v").alias("u"), F.col("low").alias("v")))).alias("e"))
            .select("e.u", "e.v").where("u <> v").distinct()
        )
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.countDistinct("u")).first()
        if tuple(seen) == state or (seen[0] == seen[2] and now.join(now.select(F.col("u").alias("v")), "v", "left_semi").isEmpty()):
            break
        state = tuple(seen)
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
