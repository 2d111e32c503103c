"""Language identification: declared, by script, and a subword model."""

from __future__ import annotations

from uuid import uuid4

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import remove, shared_dir


def declared(pages: DataFrame) -> DataFrame:
    """(page_id, lang): of the html element, else the URL's first path segment of two letters, else null."""
    tag, path = F.regexp_extract("html", '<html[^>]* lang="([a-zA-Z-]+)"', 1), F.regexp_extract("url", "^https?://[^/]+/([a-z][a-z])/", 1)
    return pages.select("page_id", F.nullif(F.coalesce(F.nullif(tag, F.lit("")), path), F.lit("")).alias("lang"))


def script_ratio(text: Column, script: str = "Han") -> Column:
    """Share of letters in a script; null without letters."""
    letters = F.regexp_count(text, F.lit(r"\p{L}"))
    return F.when(letters > 0, F.regexp_count(text, F.lit(rf"\p{{Is{script}}}")) / letters)


def keep(docs: DataFrame, languages: tuple[str, ...] = ("en", "zh"), col: str = "lang") -> DataFrame:
    return docs.where(F.col(col).isin(*languages))


def train_subword(df: DataFrame, n: int = 3, buckets: int = 1 << 14, iterations: int = 20):
    """A fitted pipeline on rows (text, lang): hashed character n-grams of whole texts, multinomial logistic regression."""
    from pyspark.ml import Pipeline, PipelineModel
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, NGram, SQLTransformer, StringIndexer

    chars = SQLTransformer(statement="SELECT *, split(lower(text), '') AS chars FROM __THIS__")
    fitted = Pipeline(stages=[StringIndexer(inputCol="lang", outputCol="y", stringOrderType="alphabetAsc"), chars, NGram(n=n, inputCol="chars", outputCol="grams"), HashingTF(inputCol="grams", outputCol="features", numFeatures=buckets), LogisticRegression(labelCol="y", maxIter=iterations, regParam=1e-3)]).fit(df)
    # A fitted model holds on to its training data and so to the session; what is read back doesn't.
    folder = f"{shared_dir(df.sparkSession)}/model-{uuid4().hex}"
    fitted.save(folder)
    read = PipelineModel.load(folder)
    remove(df.sparkSession, folder)
    return read


def predict(df: DataFrame, model, keep: list[str]) -> DataFrame:
    labels = F.array(*map(F.lit, model.stages[0].labels))
    return model.transform(df).select(*keep, F.get(labels, F.col("prediction").cast("int")).alias("predicted"))


def filter(docs: DataFrame, model, languages: tuple[str, ...] = ("en", "zh"), min_prob: float = 0.0) -> DataFrame:
    """docs whose most likely language is wanted and at least so likely; adds predicted and lang_prob. Ties go to the model's first label."""
    from pyspark.ml.functions import vector_to_array

    labels = F.array(*map(F.lit, model.stages[0].labels))
    scored = model.transform(docs).select(*docs.columns, F.get(labels, F.col("prediction").cast("int")).alias("predicted"), F.array_max(vector_to_array("probability")).alias("lang_prob"))
    return scored.where(F.col("predicted").isin(*languages) & (F.col("lang_prob") >= min_prob))
