"""The whole curation path over crawled pages, with its ledger.

Pages are extracted once and stored with what each row alone decides (language, first probability). Everything after
that hands on narrow rows: ids, signatures, URLs, reasons, probabilities. Only the documents that are left at the end are
read again from their html, for formulas and image places.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusloom.operators import dedup, extract, images, interleave, langid, normalise, rules, sampling, scoring, textclf
from corpusloom.runtime import cut


@dataclass(frozen=True)
class Config:
    """language: 'model' (a subword model) or 'declared'; classifier: 'logistic' or 'bayes'. Sizes are numbers of rows of each
    class (training) and of scored documents; they bound what is sampled, never what is filtered."""

    languages: tuple[str, ...] = ("en", "zh")
    language: str = "model"
    language_prob: float = 0.0
    classifier: str = "logistic"
    training_rows: int = 500_000
    recall_cut: float = 0.4
    n_bands: int = 14
    rows: int = 8
    family: str = "xxhash64"
    scored_rows: int = 1_000_000
    score_cut: int = 6
    precision_rows: int = 640_000
    precision_cut: float = 0.5
    image_cap: int = 10
    image_crowd: int = 100
    precise: bool = True


def extracted(pages: DataFrame) -> DataFrame:
    """(rec_id, url, snapshot_id, snapshot_date, year, declared, text), texts by the parser; map-only."""
    lang = F.coalesce(F.nullif(F.regexp_extract("html", '<html[^>]* lang="([a-zA-Z-]+)"', 1), F.lit("")), F.nullif(F.regexp_extract("url", "^https?://[^/]+/([a-z][a-z])/", 1), F.lit("")))
    return extract.with_text(pages.select("rec_id", "url", "snapshot_id", "snapshot_date", "year", lang.alias("declared"), "html"))


def first_filter(docs: DataFrame, positives: DataFrame, negatives: DataFrame | None, cfg: Config, id_col: str = "rec_id") -> DataFrame:
    """(id, prob) of all docs (id, text) by a classifier of positives against negatives (text), which are the crawl's own
    random texts unless given. Image links go from the negatives, so that both classes have one format."""
    if negatives is None:
        same = positives.select(F.xxhash64("text").alias("__t")).distinct()
        negatives = docs.withColumn("__t", F.xxhash64("text")).join(same, "__t", "left_anti").select("text")
    pool = lambda df: df.select("text", F.xxhash64("text").alias("key")).where("text is not null").dropDuplicates(["key"])
    train = sampling.balanced(pool(positives), pool(negatives), cfg.training_rows, "key")
    train = cut(train.select(F.when(F.col("y") == 1, F.col("text")).otherwise(extract.strip_image_links(F.col("text"))).alias("text"), "y"))
    if cfg.classifier == "bayes":
        return textclf.nb_score(docs, textclf.nb_fit(train), id_col).select(id_col, "prob")
    return textclf.predict(docs.select(id_col, "text"), textclf.train(train), [id_col])


def second_filter(docs: DataFrame, scored: DataFrame, cfg: Config, id_col: str = "rec_id") -> DataFrame:
    """(id, prob) of all docs (id, text) by a classifier of normalised texts: rows of scored (id, score) at the cut against
    as many random documents that are none of them."""
    good = cut(sampling.from_scores(scored, cfg.score_cut).select(id_col))
    k = min(cfg.precision_rows, good.count())
    pos = sampling.exact_k(good, k, id_col).withColumn("y", F.lit(1))
    neg = sampling.exact_k(docs.select(id_col).join(good, id_col, "left_anti"), k, id_col).withColumn("y", F.lit(0))
    chosen = cut(pos.unionByName(neg))
    tokens = normalise.tokens(F.col("text"))
    model = textclf.train(cut(docs.select(id_col, "text").join(chosen, id_col).select("text", "y")), ngrams=1, tokens=tokens)
    return textclf.predict(docs.select(id_col, "text"), model, [id_col], tokens)


def curate(spark: SparkSession, pages: DataFrame, positives: DataFrame, cfg: Config = Config(), negatives: DataFrame | None = None, spoken: DataFrame | None = None, judge: Callable[[list[str]], list[str]] | None = None, fetched: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Kept documents as parallel lists (rec_id, url, texts, images), and the ledger (step, stage, n_in, n_out).

    pages: rows of a crawl view; positives, negatives: (text) for the first classifier; spoken: (text, lang) that the
    language model is trained on; judge: scores prompts of the sampled documents; fetched: (image_url) that were got, the
    stand-in's if None. Steps: language, high recall, content within snapshots and between neighbours, URLs, rules, high
    precision.
    """
    texts = cut(extracted(pages), 1_000)
    if cfg.language == "declared":
        marked = texts.select("rec_id", F.col("declared").alias("lang"), F.col("declared").isin(*cfg.languages).alias("in_language"))
    else:
        model = langid.train_subword(spoken)
        kept = langid.filter(texts.select("rec_id", "text"), model, cfg.languages, cfg.language_prob).select("rec_id", F.col("predicted").alias("lang"))
        marked = texts.select("rec_id").join(kept, "rec_id", "left").select("rec_id", "lang", F.col("lang").isNotNull().alias("in_language"))
    marked = cut(marked)
    told = texts.select("rec_id", "text").join(marked.where("in_language").select("rec_id"), "rec_id", "left_semi")
    probs = first_filter(told, positives, negatives, cfg)
    marked = cut(marked.join(probs, "rec_id", "left"))
    first = cut(marked.where(F.col("in_language") & (F.col("prob") >= cfg.recall_cut)).select("rec_id", "lang"))
    # The text store of what is left: a small part of the crawl, written once.
    now = cut(texts.drop("declared").join(first, "rec_id"))
    content, two = dedup.content_two_step(now, n_bands=cfg.n_bands, rows=cfg.rows, family=cfg.family)
    facts = cut(rules.apply(now).select("rec_id", "kept", "url", "snapshot_id", "snapshot_date", "year"))
    unique = facts.join(cut(content), "rec_id", "left_semi")
    by_url = cut(dedup.url(unique))
    clean = cut(facts.where("kept").join(by_url, "rec_id", "left_semi").select("rec_id"))
    total, in_language, recalled, by_url_n, clean_n = texts.count(), marked.where("in_language").count(), first.count(), by_url.count(), clean.count()
    steps = two.orderBy("step").collect()
    counts = [("language", total, in_language), ("high_recall", in_language, recalled), *((r["stage"], r["n_in"], r["n_out"]) for r in steps), ("url_dedup", steps[-1]["n_out"], by_url_n), ("rules", by_url_n, clean_n)]
    left = clean
    if cfg.precise:
        rest = now.select("rec_id", "text").join(clean, "rec_id", "left_semi")
        sample = sampling.exact_k(clean, cfg.scored_rows, "rec_id")
        scored = cut(scoring.score(rest.join(sample, "rec_id", "left_semi"), judge or length_judge, id_col="rec_id"))
        left = cut(textclf.keep(second_filter(rest, scored, cfg), cfg.precision_cut).select("rec_id"))
        counts.append(("high_precision", clean_n, left.count()))
    kept = pages.select("rec_id", "url", "html").join(left, "rec_id", "left_semi")
    docs = interleave.to_parallel_lists(extract.interleaved(kept, "rec_id"))
    docs = images.pipeline(docs.withColumnRenamed("rec_id", "doc_id"), cfg.image_cap, cfg.image_crowd, fetched=fetched).withColumnRenamed("doc_id", "rec_id")
    return docs, spark.createDataFrame([(k, *c) for k, c in enumerate(counts, 1)], "step int, stage string, n_in long, n_out long")


def length_judge(prompts: list[str]) -> list[str]:
    """The stand-in: a point for each 150 characters, ten at most."""
    return [str(min(10, len(p) // 150)) for p in prompts]


def corpus_stats(docs: DataFrame) -> DataFrame:
    """One row of parallel-list documents: documents, text tokens by white space, image places, distinct image URLs (approximate), and means."""
    tokens = F.aggregate(F.array_compact("texts"), F.lit(0).cast("long"), lambda s, t: s + rules.n_words(t))
    one = docs.select(tokens.alias("tokens"), interleave.n_images(F.col("images")).cast("long").alias("n_images"))
    urls = docs.select(F.explode(F.array_compact("images")).alias("u")).agg(F.approx_count_distinct("u").alias("image_urls"))
    total = one.agg(F.count("*").alias("docs"), F.sum("tokens").alias("tokens"), F.sum("n_images").alias("image_places"), F.avg("tokens").alias("tokens_per_doc"), F.avg("n_images").alias("images_per_doc"))
    return total.crossJoin(urls)  # one row each
