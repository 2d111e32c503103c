"""Measures: rates on outcomes, agreement of filters, judged answers, four-way outcomes, contamination."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.operators import grams
from corpusloom.operators.dedup import words
from corpusloom.runtime import cut, ensure_importable


def positive_accuracy(scored: DataFrame, threshold: float = 0.5) -> DataFrame:
    """Share of an all-positive set that is accepted: recall by another name."""
    return scored.agg(F.count("*").alias("items"), F.avg((F.col("prob") >= threshold).cast("double")).alias("accuracy"))


def confusion(scored: DataFrame, threshold: float = 0.5) -> DataFrame:
    """tp, fp, fn, tn and rates of (prob, y) in one aggregation; rates are null where nothing is divided."""
    p, y = F.col("prob") >= threshold, F.col("y") == 1
    n = lambda c: F.sum(c.cast("long"))
    one = scored.agg(n(p & y).alias("tp"), n(p & ~y).alias("fp"), n(~p & y).alias("fn"), n(~p & ~y).alias("tn"))
    safe = lambda a, b: F.when(b > 0, a / b)
    tp, fp, fn, tn = map(F.col, ("tp", "fp", "fn", "tn"))
    return one.withColumns({"accuracy": safe(tp + tn, tp + fp + fn + tn), "precision": safe(tp, tp + fp), "recall": safe(tp, tp + fn), "f1": safe(2 * tp, 2 * tp + fp + fn)})


def auc(scored: DataFrame, bins: int = 1000) -> DataFrame:
    """Area under the curve from counts by score bin, ties by half; no global sort of rows."""
    b = scored.select(F.floor(F.col("prob") * bins).cast("int").alias("bin"), "y").groupBy("bin").agg(F.sum((F.col("y") == 1).cast("long")).alias("p"), F.sum((F.col("y") == 0).cast("long")).alias("n"))
    low = b.select(F.col("bin").alias("b2"), F.col("n").alias("n2"))
    pairs = b.crossJoin(F.broadcast(low)).where("b2 <= bin")  # at most `bins` rows on each side
    won = pairs.agg(F.sum(F.col("p") * F.col("n2") * F.when(F.col("b2") == F.col("bin"), 0.5).otherwise(1.0)).alias("won"))
    return b.agg(F.sum("p").alias("p"), F.sum("n").alias("n")).crossJoin(won).select((F.col("won") / (F.col("p") * F.col("n"))).alias("auc"))


def split_accuracy(outcomes: DataFrame, categories: list) -> DataFrame:
    """(model, c_<category>..., macro, micro) of (model, category, correct)."""
    wide = outcomes.groupBy("model").pivot("category", categories).agg(F.avg(F.col("correct").cast("double")))
    cols = [F.col(str(c)) for c in categories]
    macro = sum(cols[1:], cols[0]) / len(cols)
    micro = outcomes.groupBy("model").agg(F.avg(F.col("correct").cast("double")).alias("micro"))
    return wide.select("model", *(c.alias(f"c_{k}") for c, k in zip(cols, categories, strict=True)), macro.alias("macro")).join(micro, "model")


def four_way(outcomes: DataFrame) -> DataFrame:
    """Shares of (sub_ok, composite_ok): insufficient knowledge, inadequate generalisation, complete mastery, rote; their average and rote rate."""
    sub, top = F.col("sub_ok"), F.col("composite_ok")
    share = lambda c: F.avg(c.cast("double"))
    one = outcomes.agg(F.count("*").alias("problems"), share(~sub & ~top).alias("ik"), share(sub & ~top).alias("ig"), share(sub & top).alias("cm"), share(~sub & top).alias("rote"))
    return one.withColumn("avg", F.col("cm") + F.col("ig") / 2).withColumn("rm", F.when(F.col("rote") + F.col("cm") > 0, F.col("rote") / (F.col("rote") + F.col("cm"))))


def generate(items: DataFrame, model: Callable[[list[str]], list[str]], batch: int = 32, id_col: str = "item_id") -> DataFrame:
    """(id, response) by a model that answers a batch of texts at a time; one crossing to Python, to be stored before it is judged."""
    ensure_importable(items.sparkSession)
    kind = items.schema[id_col].dataType.simpleString()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for a in range(0, len(frame), batch):
                part = frame.iloc[a : a + batch]
                yield pd.DataFrame({id_col: part[id_col], "response": model(part["text"].fillna("").tolist())})

    return items.select(id_col, "text").mapInPandas(run, f"{id_col} {kind}, response string")


def judge(responses: DataFrame, truth: DataFrame, id_col: str = "item_id") -> DataFrame:
    """(id, extracted, truth, correct): the answer taken out of each response and compared; items without a response are wrong."""
    j = truth.select(id_col, "truth").join(responses.select(id_col, extract_answer(F.col("response")).alias("extracted")), id_col, "left")
    return j.select(id_col, "extracted", "truth", same_answer(F.col("extracted"), F.col("truth")).alias("correct"))


def extract_answer(response: Column) -> Column:
    """What follows the last 'answer is' or 'answer:', else the last choice letter in brackets, else the last number; null if none."""
    said = F.regexp_extract(response, r"(?is).*answer(?: is|:)\s*\(?([A-E]|[+-]?[0-9][0-9,]*(?:\.[0-9]+)?)\)?", 1)
    letter, number = F.regexp_extract(response, r"(?s).*\(([A-E])\)", 1), F.regexp_extract(response, r"(?s).*(?<![0-9.,])([+-]?[0-9][0-9,]*(?:\.[0-9]+)?)", 1)
    blank = lambda c: F.nullif(c, F.lit(""))
    return F.coalesce(blank(said), blank(letter), blank(number))


def same_answer(a: Column, b: Column) -> Column:
    """Equal without case, commas and brackets, or as numbers; false where nothing was found."""
    clean = lambda x: F.regexp_replace(F.upper(F.trim(x)), r"[,()\s]", "")
    num = lambda x: clean(x).try_cast("double")
    return F.coalesce((clean(a) == clean(b)) | (F.abs(num(a) - num(b)) < 1e-9), F.lit(False))


def compare_filters(a: DataFrame, b: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(in_a, in_b, n) of two kept sets."""
    x, y = a.select(id_col, F.lit(1).alias("a")), b.select(id_col, F.lit(1).alias("b"))
    return x.join(y, id_col, "full").groupBy(F.coalesce("a", F.lit(0)).alias("in_a"), F.coalesce("b", F.lit(0)).alias("in_b")).agg(F.count("*").alias("n"))


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = 8, most: int = 1 << 24) -> DataFrame:
    """(doc_id, items, grams): documents that share an n-gram of words with a benchmark item.

    Hashes of the benchmark's n-grams go to the tasks as one sorted array (at most `most` of eight bytes; a benchmark
    beyond that is met in slices), so only documents that hit one are joined.
    """
    def hashes(units: list[str], glue: str) -> np.ndarray:
        return np.unique(np.fromiter(map(grams.xx64, grams.spans(units, n, glue)), np.uint64).view(np.int64))

    mine = grams.map_units(benchmark.select("item_id", "text"), words(F.col("text")), F.lit(" "), ["item_id"], lambda u, g: hashes(u, g).tolist() if u else None, "found")
    mine = cut(mine.select("item_id", F.explode("found").alias("h")))
    distinct = mine.select("h").distinct()
    slices = max(1, -(-distinct.count() // most))
    found = []
    for k in range(slices):
        known = np.sort(distinct.where(F.pmod("h", F.lit(slices)) == k).toPandas()["h"].to_numpy(np.int64))

        def met(units: list[str], glue: str, known: np.ndarray = known) -> list[int] | None:
            own = hashes(units, glue)
            if not len(known) or not len(own):
                return None
            hit = own[known[np.minimum(np.searchsorted(known, own), len(known) - 1)] == own]
            return hit.tolist() or None

        found.append(grams.map_units(docs.select("doc_id", "text"), words(F.col("text")), F.lit(" "), ["doc_id"], met, "found"))
    hits = reduce(DataFrame.unionByName, found).select("doc_id", F.explode("found").alias("h"))
    return hits.join(mine, "h").groupBy("doc_id").agg(F.countDistinct("item_id").alias("items"), F.countDistinct("h").alias("grams"))


def ledger_row(df: DataFrame, stage: str, n_in: int) -> DataFrame:
    n = F.count("*")
    return df.agg(F.lit(stage).alias("stage"), F.lit(n_in).cast("long").alias("n_in"), n.alias("n_out"))
