"""Exact duplicates by an exchange of Golomb-coded fingerprints.

The rows are dealt by doc_id into slices. A slice sorts its 64-bit fingerprints, cuts them at the owners' bounds (an
owner has a range of fingerprints) and sends each owner the gaps, Golomb-coded with a power of two as parameter. The
owner decodes what it was sent and answers each slice with a bitmap: bit i is set if the slice's i-th fingerprint also
came from elsewhere. Rows with a set bit, or with a twin in their own slice, are suspects. Only suspects' texts are
shuffled, after equal ones were combined in their own task, and they are compared as whole texts.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm.filters import FILTER_BITS, bits_for, flag, unwrapped, without, wrapped
from corpusloom.runtime import cut, ensure_importable

SLICE_ROWS = 1_000_000
OWNER_ROWS = 1_000_000
#: A group of copies is dealt over so many tasks when its rows meet what was found of it.
SALTS = 16


def golomb_encode(gaps: np.ndarray, k: int) -> tuple[bytes, bytes]:
    """Quotients in unary and remainders of k bits, in two streams."""
    unary = np.zeros(int((gaps >> np.uint64(k)).sum()) + len(gaps), np.uint8)
    unary[np.cumsum((gaps >> np.uint64(k)).astype(np.int64) + 1) - 1] = 1
    low = np.unpackbits(gaps.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)[:, 64 - k :] if k else np.zeros((len(gaps), 0), np.uint8)
    return np.packbits(unary).tobytes(), np.packbits(low.ravel()).tobytes()


def golomb_decode(unary: bytes, low: bytes, n: int, k: int) -> np.ndarray:
    ends = np.flatnonzero(np.unpackbits(np.frombuffer(unary, np.uint8)))[:n]
    high = np.diff(ends, prepend=-1) - 1
    rest = np.zeros((n, 64), np.uint8)
    if k:
        rest[:, 64 - k :] = np.unpackbits(np.frombuffer(low, np.uint8))[: n * k].reshape(n, k)
    return (high.astype(np.uint64) << np.uint64(k)) + np.packbits(rest, axis=1).view(">u8").ravel().astype(np.uint64)


def _segments(prints: np.ndarray, bits: int) -> Iterator[tuple[int, np.ndarray]]:
    """The owners of sorted fingerprints, each with its part."""
    owners = (prints >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(prints), np.int64)
    starts = np.flatnonzero(np.diff(owners, prepend=-1))
    for a, b in zip(starts, [*starts[1:], len(owners)], strict=True):
        yield int(owners[a]), prints[a:b]


def _sender(bits: int):
    def send(pdf: pd.DataFrame) -> pd.DataFrame:
        prints = np.unique(pdf["h"].to_numpy(np.int64).view(np.uint64))
        rows = []
        for owner, part in _segments(prints, bits):
            base = np.uint64(owner << (64 - bits) if bits else 0)
            gaps = np.diff(part - base, prepend=np.uint64(0))
            k = max(0, min(63, int(math.log2(max(1.0, 0.69 * float(part[-1] - base) / len(part))))))
            rows.append((int(pdf["slice"].iloc[0]), owner, len(part), k, *golomb_encode(gaps, k)))
        return pd.DataFrame(rows, columns=["slice", "owner", "n", "k", "high", "low"])

    return send


def _judge(pdf: pd.DataFrame) -> pd.DataFrame:
    parts = [np.cumsum(golomb_decode(r.high, r.low, r.n, r.k), dtype=np.uint64) for r in pdf.itertuples()]
    _, back, times = np.unique(np.concatenate(parts), return_inverse=True, return_counts=True)
    many = np.split(times[back] > 1, np.cumsum([len(x) for x in parts])[:-1])
    return pd.DataFrame({"slice": pdf["slice"], "owner": pdf["owner"], "bitmap": [np.packbits(x).tobytes() for x in many]})


def _receiver(bits: int):
    def receive(rows: pd.DataFrame, maps: pd.DataFrame) -> pd.DataFrame:
        if rows.empty:
            return pd.DataFrame({"h": np.zeros(0, np.int64)})
        prints, times = np.unique(rows["h"].to_numpy(np.int64).view(np.uint64), return_counts=True)
        said = dict(zip(maps["owner"], maps["bitmap"], strict=True))
        met = np.concatenate([np.unpackbits(np.frombuffer(said[o], np.uint8))[: len(part)] for o, part in _segments(prints, bits)])
        return pd.DataFrame({"h": prints[(met == 1) | (times > 1)].view(np.int64)})

    return receive


def suspects(prints: DataFrame, slice_rows: int = SLICE_ROWS, owner_rows: int = OWNER_ROWS) -> DataFrame:
    """(h), distinct: the fingerprints that more than one row of (doc_id, h) has, found by the exchange."""
    n = prints.count()
    slices, bits = max(1, math.ceil(n / slice_rows)), max(0, math.ceil(math.log2(max(1, n / owner_rows))))
    if n > 1:  # as many tasks as the session deals in, if slices stay large enough to be worth it
        slices = max(slices, min(int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(n / 2000)))
    dealt = prints.select("h", F.pmod(F.hash("doc_id", "h"), F.lit(slices)).alias("slice"))
    blobs = dealt.groupBy("slice").applyInPandas(_sender(bits), "slice int, owner int, n int, k int, high binary, low binary")
    maps = blobs.groupBy("owner").applyInPandas(_judge, "slice int, owner int, bitmap binary")
    return dealt.groupBy("slice").cogroup(maps.groupBy("slice")).applyInPandas(_receiver(bits), "h long").distinct()


def _sift(texts: DataFrame, held: DataFrame, filter_bits: int) -> DataFrame:
    """Rows of texts whose h may be in held; none that is gets lost, and groupBy on the text settles the rest."""
    bits = bits_for(held.count(), filter_bits)
    if bits is None:
        return texts.join(held, "h", "left_semi")
    return flag(texts, F.col("h"), held, bits).where("__maybe").drop("__maybe")


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slice_rows: int = SLICE_ROWS, owner_rows: int = OWNER_ROWS, filter_bits: int = FILTER_BITS) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row for each row of docs.

    A null text counts as the empty text, texts are equal when all their bytes are. Of equal texts the largest doc_id
    stays (null ids lose to any other). Rows repeated with the same id are one document to this rule: each of them says
    kept, group_size counts them all. Other columns are not read; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    ensure_importable(spark)
    texts = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).withColumn("h", F.xxhash64("text"))
    narrow = cut(texts.select("doc_id", "h", F.sha2("text", 256).alias("text_sha256")))
    held = cut(suspects(narrow.select("doc_id", "h"), slice_rows, owner_rows))
    groups = (
        _sift(texts, held, filter_bits).groupBy("text").agg(F.count("*").alias("n"), F.max("doc_id").alias("top"))
        .where("n > 1").select(F.sha2("text", 256).alias("text_sha256"), "n", "top")
    )
    salt = F.pmod(F.xxhash64("doc_id"), F.lit(SALTS))
    copies = groups.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    found = narrow.withColumn("salt", salt).join(copies, ["text_sha256", "salt"], "left")
    keep = F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("top"))
    return found.select("doc_id", keep.alias("keep_id"), F.coalesce("n", F.lit(1)).cast("long").alias("group_size"), keep.eqNullSafe(F.col("doc_id")).alias("kept"), "text_sha256")


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs without the rows that exact_duplicates() does not keep; rows repeated with the same id and text stay once."""
    found = exact_duplicates(docs, id_col, text_col, **options).where("group_size > 1")
    found = cut(found.select(F.col("doc_id").alias("__id"), F.col("text_sha256").alias("__sha"), "kept"))
    marked = wrapped(docs, __id=F.col(id_col), __sha=F.sha2(F.coalesce(F.col(text_col).cast("string"), F.lit("")), 256))
    left = without(marked, found.where("not kept").select("__id", "__sha").distinct(), ["__id", "__sha"])
    again = found.where("kept").groupBy("__id", "__sha").count().where("count > 1")
    return unwrapped(left if again.isEmpty() else left.dropDuplicates(["__id", "__sha"]))
