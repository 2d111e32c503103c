"""Documents as two parallel lists, one of texts and one of image URLs, and images put back at their places."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def to_parallel_lists(docs: DataFrame, segments: str = "segments") -> DataFrame:
    """docs with texts and images: equal lengths, in order, exactly one side of each index is null. Column functions only."""
    ordered = F.array_sort(F.col(segments))
    text = lambda s: F.when(s["kind"] != "image", s["text"])
    url = lambda s: F.when(s["kind"] == "image", s["image_url"])
    return docs.withColumn("texts", F.transform(ordered, text)).withColumn("images", F.transform(ordered, url)).drop(segments)


def from_parallel_lists(docs: DataFrame) -> DataFrame:
    """docs with segments (pos, kind, text, image_url) of texts and images; formulas come back as text."""
    both = F.zip_with("texts", "images", lambda t, i: F.struct(t.alias("t"), i.alias("i")))
    segment = lambda x, k: F.struct(k.cast("int").alias("pos"), F.when(x["i"].isNotNull(), "image").otherwise("text").alias("kind"), x["t"].alias("text"), x["i"].alias("image_url"))
    return docs.withColumn("segments", F.transform(both, segment)).drop("texts", "images")


def text_only(docs: DataFrame) -> DataFrame:
    """docs with text, images left out."""
    return docs.withColumn("text", F.array_join(F.array_compact("texts"), "\n")).drop("texts", "images")


def n_images(col: Column) -> Column:
    return F.size(F.array_compact(col))


def reattach(docs: DataFrame, fetched: DataFrame, missing: str = "drop", id_col: str = "doc_id") -> DataFrame:
    """docs (id, texts, images) with only images of fetched (image_url): others' places go, or become empty.

    The lists are joined as narrow rows (id, pos, url), so texts aren't shuffled twice, and every document stays.
    """
    refs = docs.select(id_col, F.posexplode("images").alias("pos", "image_url")).where("image_url is not null")
    good = refs.join(fetched.select("image_url").distinct(), "image_url", "left_semi").groupBy(id_col).agg(F.collect_list("pos").alias("__ok"))
    df = docs.join(good, id_col, "left").withColumn("__ok", F.coalesce("__ok", F.array().cast("array<int>")))
    both = F.transform(F.arrays_zip("texts", "images"), lambda x, k: F.struct(x["texts"].alias("t"), F.when(F.array_contains("__ok", k), x["images"]).alias("i"), x["images"].alias("was")))
    if missing == "drop":
        both = F.filter(both, lambda x: x["was"].isNull() | x["i"].isNotNull())
    return df.withColumn("__b", both).withColumn("texts", F.transform("__b", lambda x: x["t"])).withColumn("images", F.transform("__b", lambda x: x["i"])).drop("__b", "__ok")
