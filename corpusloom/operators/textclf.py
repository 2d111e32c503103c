"""Linear text classifiers: naive Bayes in SQL, hashed logistic regression, averaged low-rank embeddings, scoring, cuts."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.operators import grams
from corpusloom.operators.dedup import let, words
from corpusloom.runtime import ensure_importable
from corpusloom.sources.views import H28


def nb_fit(train: DataFrame) -> DataFrame:
    """(token, weight): log-odds with add-one smoothing of rows (text, y). One shuffle of token counts."""
    t = train.select(F.explode(words(F.col("text"))).alias("token"), "y").groupBy("token").agg(F.sum((F.col("y") == 1).cast("long")).alias("n1"), F.sum((F.col("y") == 0).cast("long")).alias("n0"))
    total = t.agg(F.sum("n1").alias("t1"), F.sum("n0").alias("t0"), F.count("*").alias("v"))
    return t.crossJoin(F.broadcast(total)).select("token", (F.log((F.col("n1") + 1) / (F.col("t1") + F.col("v"))) - F.log((F.col("n0") + 1) / (F.col("t0") + F.col("v")))).alias("weight"))  # the right side is one row


#: Tokens of a model up to which it goes to every task as a table of that size (some 100 bytes each).
LOCAL_TOKENS = 2_000_000


def nb_score(docs: DataFrame, model: DataFrame, id_col: str = "doc_id", local: int = LOCAL_TOKENS) -> DataFrame:
    """(id, score, prob): mean weight of a document's known tokens, so that length doesn't decide; none give score 0.

    A model of at most `local` tokens is sent to the tasks and scoring is map-only. Beyond that, distinct tokens of each
    document are joined to it; both give the same scores.
    """
    few = model.limit(local + 1).toArrow()
    if few.num_rows <= local:
        weight = dict(zip(few["token"].to_pylist(), few["weight"].to_pylist(), strict=True))
        found = grams.weigh(docs, words(F.col("text")), [id_col], lambda ts: np.array([weight.get(t, np.nan) for t in ts]), mean=True).withColumnRenamed("total", "score")
    else:
        t = docs.select(id_col, F.explode(words(F.col("text"))).alias("token")).groupBy(id_col, "token").agg(F.count("*").alias("n"))
        found = t.join(model, "token").groupBy(id_col).agg((F.sum(F.col("n") * F.col("weight")) / F.sum("n")).alias("score"))
        found = docs.select(id_col).join(found, id_col, "left")
    score = F.coalesce("score", F.lit(0.0))
    return found.select(id_col, score.alias("score"), (1 / (1 + F.exp(-4 * score))).alias("prob"))


NB_SQL = rf"""
    lab AS (SELECT doc_id, quality AS y, CASE WHEN {H28.format("doc_id::VARCHAR")} % 1000 < 200 THEN 'test' ELSE 'train' END AS split FROM labels),
    tok AS (SELECT doc_id, unnest(list_filter(string_split(regexp_replace(lower(text), '[^\p{{L}}\p{{N}}]+', ' ', 'g'), ' '), lambda v: v <> '')) AS token FROM documents),
    cnt AS (SELECT token, sum(CAST(y = 1 AS BIGINT)) AS n1, sum(CAST(y = 0 AS BIGINT)) AS n0 FROM tok JOIN lab USING (doc_id) WHERE split = 'train' GROUP BY token),
    tot AS (SELECT sum(n1) AS t1, sum(n0) AS t0, count(*) AS v FROM cnt),
    model AS (SELECT token, ln((n1 + 1) / (t1 + v)) - ln((n0 + 1) / (t0 + v)) AS weight FROM cnt, tot),
    nb AS (SELECT d.doc_id, coalesce(s.score, 0) AS score, 1 / (1 + exp(-4 * coalesce(s.score, 0))) AS prob FROM documents d LEFT JOIN (SELECT doc_id, sum(weight) / count(*) AS score FROM tok JOIN model USING (token) GROUP BY doc_id) s USING (doc_id))"""


def score(docs: DataFrame, weights: list[float], bias: float, id_col: str = "doc_id", tokens: Column | None = None) -> DataFrame:
    """(id, prob) by a hashed linear model: the mean weight of a row's tokens, map-only and without an explode."""
    table = np.asarray(weights, np.float64)
    tokens = words(F.col("text")) if tokens is None else tokens
    found = grams.weigh(docs, tokens, [id_col], lambda ts: table[[grams.md5_prefix(t.encode()) % len(table) for t in ts]], mean=True)
    return found.select(id_col, (1 / (1 + F.exp(-(F.col("total") + F.lit(bias))))).alias("prob"))


@dataclass(frozen=True)
class Linear:
    """A fitted hashed linear model: a weight for each bucket of n-grams of tokens, and the bias."""

    weights: np.ndarray
    bias: float
    ngrams: int


def _buckets(tokens: Column, ngrams: int, buckets: int) -> Column:
    """Buckets of all n-grams up to ngrams, repeats included: the reference form of grams.buckets_of. Each slice copies the whole
    array, so a text costs the square of its words."""

    def grams_of(ts: Column) -> Column:
        def of(n: int) -> Column:  # not an argument of the lambda with a default: that would be the element's index
            at = F.when(F.size(ts) >= n, F.sequence(F.lit(1), F.size(ts) - (n - 1))).otherwise(F.array().cast("array<int>"))
            return F.transform(at, lambda i: F.array_join(F.slice(ts, i, F.lit(n)), " "))

        more = [of(n) for n in range(2, ngrams + 1)]
        return F.concat(ts, *more)

    return F.transform(let(tokens, grams_of), lambda g: F.pmod(F.xxhash64(g), F.lit(buckets)).cast("int"))


def train(df: DataFrame, ngrams: int = 2, buckets: int = 1 << 16, epochs: int = 30, reg: float = 1e-4, tokens: Column | None = None) -> Linear:
    """A logistic regression on hashed word n-grams of rows (text, y). Only its coefficients are kept, so nothing of the
    session or of the training data goes with it into later plans."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import CountVectorizerModel

    units = words(F.col("text")) if tokens is None else tokens
    found = grams.map_units(df.select("text", F.col("y").cast("double").alias("y")), units, F.lit(" "), ["y"], lambda u, _: grams.buckets_of(u, ngrams, buckets).tolist(), "ids")
    names = CountVectorizerModel.from_vocabulary([str(b) for b in range(buckets)], inputCol="ids", outputCol="features")  # bucket k is column k
    rows = names.transform(found.select(F.transform("ids", lambda b: b.cast("string")).alias("ids"), "y")).select("features", "y").persist()
    fitted = LogisticRegression(labelCol="y", maxIter=epochs, regParam=reg).fit(rows)
    rows.unpersist()
    return Linear(fitted.coefficients.toArray(), float(fitted.intercept), ngrams)


def predict(df: DataFrame, model: Linear, keep: list[str], tokens: Column | None = None) -> DataFrame:
    """(keep..., prob), map-only."""
    found = grams.weigh_grams(df, words(F.col("text")) if tokens is None else tokens, keep, model.weights, model.ngrams)
    return found.select(*keep, (1 / (1 + F.exp(-(F.col("total") + F.lit(model.bias))))).alias("prob"))


def train_low_rank(df: DataFrame, rank: int = 8, buckets: int = 4096, epochs: int = 4, rate: float = 0.5, seed: int = 7) -> tuple[np.ndarray, np.ndarray]:
    """(embeddings, output): mean embedding of hashed tokens, then a logistic unit. Each epoch, partitions step locally
    and the driver averages models, whose size is buckets x rank whatever the data."""
    ensure_importable(df.sparkSession)
    rows = df.select(F.transform(words(F.col("text")), lambda t: F.pmod(F.xxhash64(t), F.lit(buckets)).cast("int")).alias("ids"), F.col("y").cast("double").alias("y")).where(F.size("ids") > 0).persist()
    rng = np.random.default_rng(seed)
    emb, out = rng.normal(0, 0.1, (buckets, rank)), np.zeros(rank)
    for _ in range(epochs):

        def step(frames: Iterator[pd.DataFrame], emb=emb, out=out) -> Iterator[pd.DataFrame]:
            e, o, n = emb.copy(), out.copy(), 0
            for frame in frames:
                for ids, y in zip(frame["ids"], frame["y"], strict=True):
                    mean = e[ids].mean(0)
                    g = y - 1 / (1 + np.exp(-np.clip(mean @ o, -30, 30)))
                    e_step = rate * g * o / len(ids)
                    o += rate * g * mean
                    np.add.at(e, ids, e_step)
                    n += 1
            if n:
                yield pd.DataFrame({"n": [n], "m": [np.concatenate((e.ravel(), o)).astype(np.float32).tobytes()]})

        total, seen = np.zeros(buckets * rank + rank), 0
        for r in rows.mapInPandas(step, "n long, m binary").toLocalIterator():
            total += r["n"] * np.frombuffer(r["m"], np.float32)
            seen += r["n"]
        if seen:
            total /= seen
            emb, out = total[:-rank].reshape(buckets, rank), total[-rank:]
    rows.unpersist()
    return emb, out


def score_low_rank(df: DataFrame, model: tuple[np.ndarray, np.ndarray], id_col: str = "doc_id") -> DataFrame:
    """(id, prob): embedding and output unit fold into one weight for each bucket, so scoring is a mean of weights."""
    weights = model[0] @ model[1]
    ids = F.transform(words(F.col("text")), lambda t: F.pmod(F.xxhash64(t), F.lit(len(weights))).cast("int"))
    return grams.weigh(df, ids, [id_col], lambda bs: weights[bs], mean=True).select(id_col, (1 / (1 + F.exp(-F.col("total")))).alias("prob"))


def keep(scored: DataFrame, threshold: float = 0.4) -> DataFrame:
    return scored.where(F.col("prob") >= threshold)


def cut_for_volume(scored: DataFrame, target: int, exact: bool = True, accuracy: int = 10_000, bins: int = 4096) -> float:
    """The probability that about `target` rows reach; exact over all rows, or by a quantile sketch.

    The exact way counts rows in bins of the range that holds the cut and narrows it until one value is left: a few
    passes over one column, and the driver reads at most `bins` rows of each.
    """
    n = scored.count()
    if not n or target >= n:
        return 0.0
    if not exact:
        return float(scored.agg(F.percentile_approx("prob", 1 - target / n, accuracy)).first()[0])
    low, high = scored.agg(F.min("prob"), F.max("prob")).first()
    above = 0  # rows over the range
    while low < high:
        place = F.least(F.floor((F.col("prob") - low) / F.lit((high - low) / bins)), F.lit(bins - 1))
        found = scored.where(F.col("prob").between(low, high)).groupBy(place.alias("bin")).agg(F.count("*").alias("n"), F.min("prob").alias("lo"), F.max("prob").alias("hi")).collect()
        for row in sorted(found, key=lambda r: -r["bin"]):
            if above + row["n"] >= target:
                break
            above += row["n"]
        if (row["lo"], row["hi"]) == (low, high):  # neighbouring numbers: all rows of the upper value are above the lower one's
            n_high = scored.where(F.col("prob") == high).count()
            return float(high if above + n_high >= target else low)
        low, high = row["lo"], row["hi"]
    return float(low)
