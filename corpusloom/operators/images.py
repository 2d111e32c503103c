"""Image URLs: multiplicity caps, string rules, fetching, and the whole path with its ledger."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable
from corpusloom.sources.views import hash28

#: What an image URL must begin with, and terms it must not have.
PREFIX, TERMS = "https", ("logo", "banner", "avatar", "icon")


def unique(refs: DataFrame) -> DataFrame:
    return refs.select("image_url").distinct()


def frequency_cap(refs: DataFrame, cap: int = 10, count: str = "docs") -> DataFrame:
    """URLs that at most `cap` documents have, or that occur at most so often."""
    n = F.countDistinct("doc_id") if count == "docs" else F.count("*")
    return refs.groupBy("image_url").agg(n.alias("n")).where(F.col("n") <= cap).select("image_url")


def crowded_doc_cap(refs: DataFrame, cap: int = 100, mode: str = "any") -> DataFrame:
    """URLs without those of documents of more than `cap` images: of any such document, or of nothing but such."""
    n = refs.withColumn("n", F.count("*").over(W.partitionBy("doc_id")))
    worst = F.max("n") if mode == "any" else F.min("n")
    return n.groupBy("image_url").agg(worst.alias("n")).where(F.col("n") <= cap).select("image_url")


def string_rules(urls: DataFrame, prefix: str = PREFIX, terms: tuple[str, ...] = TERMS) -> DataFrame:
    """Substrings, in any case: 'silicon' has 'icon', which the rule accepts to lose."""
    low = F.lower("image_url")
    bad = low.rlike("|".join(terms))
    return urls.where(F.col("image_url").startswith(prefix) & ~bad)


def select(refs: DataFrame, cap: int = 10, crowd: int = 100, terms: tuple[str, ...] = TERMS, mode: str = "any") -> DataFrame:
    """(image_url, in_caps, in_rules): both caps in one aggregation of the original references."""
    n = refs.withColumn("n", F.count("*").over(W.partitionBy("doc_id")))
    by = n.groupBy("image_url").agg(F.countDistinct("doc_id").alias("docs"), (F.max("n") if mode == "any" else F.min("n")).alias("crowd"))
    caps = (F.col("docs") <= cap) & (F.col("crowd") <= crowd)
    return by.select("image_url", caps.alias("in_caps"), (caps & F.col("image_url").startswith(PREFIX) & ~F.lower("image_url").rlike("|".join(terms))).alias("in_rules"))


def manifest(urls: DataFrame, percent: int = 64) -> DataFrame:
    """(image_url, ok): a stand-in for downloading, by the URL's hash."""
    return urls.select("image_url", (hash28("image_url") % 100 < percent).alias("ok"))


def fetch(urls: DataFrame, fetcher: Callable[[str], bytes | None], tasks: int = 64, retries: int = 2) -> DataFrame:
    """(image_url, status, sha256, bytes) by a fetcher that raises or gives None on failure. URLs of one host share a
    task, so that a host isn't asked from everywhere; the result is to be stored before it is used."""
    ensure_importable(urls.sparkSession)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import hashlib

        for frame in frames:
            rows = []
            for u in frame["image_url"]:
                data, status = None, "failed"
                for _ in range(retries + 1):
                    try:
                        if (data := fetcher(u)) is not None:
                            status = "ok"
                            break
                    except Exception as e:  # a fetcher may fail in any way; the row says how
                        status = type(e).__name__
                rows.append((u, status, hashlib.sha256(data).hexdigest() if data is not None else None, data))
            yield pd.DataFrame(rows, columns=["image_url", "status", "sha256", "bytes"])

    host = F.regexp_extract("image_url", "^https?://([^/]*)", 1)
    return urls.select("image_url").repartition(tasks, host).mapInPandas(run, "image_url string, status string, sha256 string, bytes binary")


def ledger(refs: DataFrame, cap: int, crowd: int, terms: tuple[str, ...] = TERMS, mode: str = "any") -> DataFrame:
    """One row: occurrences, unique, after caps, after rules, fetched, placements."""
    flags = select(refs, cap, crowd, terms, mode)
    ok = manifest(flags.where("in_rules").select("image_url")).where("ok").select("image_url")
    n = lambda c: F.sum(c.cast("long"))
    counts = flags.agg(F.count("*").alias("unique_urls"), n(F.col("in_caps")).alias("after_caps"), n(F.col("in_rules")).alias("after_rules"))
    placed = refs.join(ok, "image_url", "left_semi").agg(F.count("*").alias("placements"))
    return refs.agg(F.count("*").alias("occurrences")).crossJoin(counts).crossJoin(ok.agg(F.count("*").alias("fetched"))).crossJoin(placed)  # one row each


def pipeline(docs: DataFrame, cap: int = 10, crowd: int = 100, terms: tuple[str, ...] = TERMS, fetched: DataFrame | None = None, missing: str = "drop") -> DataFrame:
    """docs (doc_id, texts, images) with only selected and fetched images at their places; fetched defaults to the stand-in's."""
    from corpusloom.operators.interleave import reattach

    refs = docs.select("doc_id", F.posexplode("images").alias("pos", "image_url")).where("image_url is not null")
    wanted = select(refs, cap, crowd, terms).where("in_rules").select("image_url")
    got = manifest(wanted).where("ok").select("image_url") if fetched is None else fetched.select("image_url").join(wanted, "image_url", "left_semi")
    return reattach(docs, got, missing)
