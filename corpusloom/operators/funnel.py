"""Ledgers of stages in one pass: every row carries one flag for each stage, and a single aggregation counts them all.

Nothing is registered in the session, so a ledger leaves no trace for queries that run after it.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ledger(rows: DataFrame, stages: list[tuple[str, Column]]) -> DataFrame:
    """(step, stage, n_in, n_out, kept_frac, removed_frac) of stages in order, each a condition on a row; null counts as false.

    A row reaches a stage if it met all conditions before. Fractions are null where nothing came in.
    """
    met = [F.coalesce(kept, F.lit(False)) for _, kept in stages]
    passed = [F.lit(True), *(reduce(lambda a, b: a & b, met[: k + 1]) for k in range(len(met)))]
    one = rows.agg(*(F.coalesce(F.sum(x.cast("long")), F.lit(0)).alias(f"n{k}") for k, x in enumerate(passed)))
    each = (F.struct(F.lit(k + 1).alias("step"), F.lit(name).alias("stage"), F.col(f"n{k}").alias("n_in"), F.col(f"n{k + 1}").alias("n_out")) for k, (name, _) in enumerate(stages))
    share = F.when(F.col("n_in") > 0, F.col("n_out") / F.col("n_in"))
    return one.select(F.inline(F.array(*each))).withColumn("kept_frac", share).withColumn("removed_frac", 1 - share)
