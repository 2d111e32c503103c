"""The operators' functions under SQL names."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from corpusloom.operators.extract import walk
from corpusloom.runtime import ensure_importable


class Segments:
    """A table function: the segments of one page's html."""

    def eval(self, html: str) -> Iterator[tuple]:
        for pos, (kind, text, url) in enumerate(walk(html)):
            yield pos, kind, text, url


def register(spark: SparkSession) -> None:
    """html_segments(html) as a table function; html_text(html) as an Arrow function; signature_union(sig) as an aggregate."""
    ensure_importable(spark)
    spark.udtf.register("html_segments", F.udtf(Segments, returnType="pos int, kind string, text string, image_url string"))

    @F.pandas_udf("string")
    def html_text(html: pd.Series) -> pd.Series:
        return html.map(lambda h: "\n".join(t for k, t, _ in walk(h, math=False, images=False) if k == "text"))

    spark.udf.register("html_text", html_text)

    @F.pandas_udf("array<bigint>")
    def signature_union(sig: pd.Series) -> list:
        import numpy as np

        return np.min(np.stack([np.asarray(s) for s in sig]), axis=0).tolist()

    spark.udf.register("signature_union", signature_union)
