"""Scores from 0 to 10 by a pluggable judge, and a deterministic stand-in."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable

#: What a judge gets: our wording of an additive scale.
PROMPT = "Rate from 0 to 10 how useful the following page is for learning mathematics. Answer with the number only.\n\n{text}"


def score(docs: DataFrame, judge: Callable[[list[str]], list[str]], batch: int = 64, id_col: str = "doc_id") -> DataFrame:
    """(id, score): judge takes prompts and gives answers, a batch at a time in each task; answers without a number from 0 to 10 are null."""
    ensure_importable(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for a in range(0, len(frame), batch):
                part = frame.iloc[a : a + batch]
                yield pd.DataFrame({id_col: part[id_col], "answer": judge([PROMPT.format(text=t or "") for t in part["text"]])})

    n = F.regexp_extract("answer", "([0-9]+)", 1).try_cast("int")
    return docs.select(id_col, "text").mapInPandas(run, f"{id_col} {kind}, answer string").select(id_col, F.when(n.between(0, 10), n).alias("score"))


def heuristic(quality: Column, toxic: Column, text: Column) -> Column:
    """The stand-in for tables with labels: six for quality, two for not toxic, two for length."""
    n = F.length(text)
    return F.greatest(F.lit(0), F.least(F.lit(10), 6 * quality + 2 * (1 - toxic) + F.when(n >= 1000, 2).when(n >= 300, 1).otherwise(0))).cast("int")


def filter(docs: DataFrame, judge: Callable[[list[str]], list[str]], cut: int = 6, id_col: str = "doc_id") -> DataFrame:
    """docs that the judge itself scores at the cut or more: the costly alternative to a classifier trained on a sample of its scores."""
    good = score(docs, judge, id_col=id_col).where(F.col("score") >= cut).select(id_col)
    return docs.join(good, id_col, "left_semi")
