"""Vectorised kernels over arrays of units (words or characters) in Arrow batches: hashes of n-grams, sums of weights.

Spark splits the text; a batch crosses to Python once. A kernel's memory is bounded by blocks of grams, not by a text's length.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable

#: Grams that are held against the hash family at once: with a hundred members, what a core's cache holds.
BLOCK = 1 << 10


def spans(units: list[str], n: int, glue: str = " ") -> Iterator[bytes]:
    """The n-grams of units as bytes, repeats included; fewer units than n are one gram, none give none."""
    if not units:
        return
    raw, gap = [u.encode() for u in units], len(glue)
    line = glue.encode().join(raw)
    sizes = np.fromiter(map(len, raw), np.int64, len(raw)) + gap
    ends = np.cumsum(sizes)
    starts = (ends - sizes)[: max(1, len(units) - n + 1)].tolist()
    for a, b in zip(starts, (ends[min(n, len(units)) - 1 :] - gap).tolist(), strict=True):
        yield line[a:b]


def line_hashes(line: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct xx64 of the word n-grams of a line whose words are parted by spaces; fewer words than n are one gram, none give none."""
    raw = (line or b"").split()
    if not raw:
        return np.zeros(0, np.int64)
    line, sizes = b" ".join(raw), np.fromiter(map(len, raw), np.int64, len(raw)) + 1
    stops = np.cumsum(sizes)
    starts, stops, digest = (stops - sizes)[: max(1, len(raw) - n + 1)].tolist(), (stops[min(n, len(raw)) - 1 :] - 1).tolist(), xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(line[a:b], 42) for a, b in zip(starts, stops, strict=True)), np.uint64, len(starts)).view(np.int64))


def md5_prefix(gram: bytes) -> int:
    """The first seven hex digits of the md5, as views.hash28 has them."""
    return int.from_bytes(hashlib.md5(gram).digest()[:4], "big") >> 4


def md5_prefixes(grams: Iterator[bytes]) -> np.ndarray:
    """md5_prefix of each gram."""
    md5 = hashlib.md5
    return (np.frombuffer(b"".join([md5(g, usedforsecurity=False).digest() for g in grams]), ">u4")[::4] >> 4).astype(np.int64)


def xx64(gram: bytes) -> int:
    """The hash that Spark's xxhash64 gives a string, unsigned."""
    return xxhash.xxh64_intdigest(gram, 42)


def affine_minima(hashes: np.ndarray, family: list[tuple[int, int]], prime: int) -> np.ndarray:
    """min over the hashes of (a x + b) mod prime for each member of the family."""
    a, b = (np.array(c, np.int64) for c in zip(*family, strict=True))
    best = np.full(len(family), prime, np.int64)
    for k in range(0, len(hashes), BLOCK):
        best = np.minimum(best, ((hashes[k : k + BLOCK, None] * a + b) % prime).min(0))
    return best


def multiply_minima(hashes: np.ndarray, family: list[tuple[int, int]]) -> np.ndarray:
    """min over the hashes of the upper 62 bits of a x + b mod 2^64, a odd."""
    a, b = (np.array(c, np.uint64)[:, None] for c in zip(*family, strict=True))
    best = np.full(len(family), np.uint64(2**64 - 1))
    for k in range(0, len(hashes), BLOCK):
        x = a * hashes[k : k + BLOCK]
        x += b
        np.minimum(best, x.min(1), out=best)
    return (best >> np.uint64(2)).astype(np.int64)


def map_units(df: DataFrame, units: Column, glue: Column, keep: list[str], one: Callable[[list[str], str], list[int] | None], name: str) -> DataFrame:
    """(keep..., name array<long>): one() of each row's units, map-only. Rows for which it gives None go."""
    ensure_importable(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):  # bounds what a batch of long texts becomes in Python
                part = batch.slice(at, 512)
                found = [one(u.as_py() or [], g.as_py()) for u, g in zip(part.column(0), part.column(1), strict=True)]
                kept = part.filter(pa.array([x is not None for x in found])) if None in found else part
                yield pa.RecordBatch.from_arrays([*kept.columns[2:], pa.array([x for x in found if x is not None], pa.list_(pa.int64()))], names=[*kept.schema.names[2:], name])

    fields = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(units.alias("__units"), glue.alias("__glue"), *keep).mapInArrow(run, f"{fields}, {name} array<bigint>")


def weigh(df: DataFrame, tokens: Column, keep: list[str], value: Callable[[list], np.ndarray], mean: bool) -> DataFrame:
    """(keep..., total double, known long): sums (or means) of the values of each row's tokens, map-only.

    value turns distinct tokens into numbers; not a number means unknown, which counts for neither sum nor mean.
    """
    ensure_importable(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(0)
            flat, sizes = lists.flatten(), np.diff(lists.offsets.to_numpy())
            coded = flat.dictionary_encode()
            worth = value(coded.dictionary.to_pylist())[coded.indices.to_numpy()] if len(flat) else np.zeros(0)
            seen = ~np.isnan(worth)
            owner = np.repeat(np.arange(len(sizes)), sizes)[seen]
            known = np.bincount(owner, minlength=len(sizes))
            total = np.bincount(owner, worth[seen], len(sizes))
            if mean:
                total = total / np.maximum(known, 1)
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(total, pa.float64()), pa.array(known, pa.int64())], names=[*batch.schema.names[1:], "total", "known"])

    fields = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(F.coalesce(tokens, F.array().cast(df.select(tokens.alias("t")).schema["t"].dataType)).alias("__tokens"), *keep).mapInArrow(run, f"{fields}, total double, known bigint")


def buckets_of(units: list[str], ngrams: int, buckets: int) -> np.ndarray:
    """The bucket of each n-gram of units up to ngrams, repeats included: Spark's pmod(xxhash64(gram), buckets)."""
    if not units:
        return np.zeros(0, np.int64)
    raw = [u.encode() for u in units]
    line, sizes = b" ".join(raw), np.fromiter(map(len, raw), np.int64, len(raw)) + 1
    stops = np.cumsum(sizes)
    starts, stops, digest = (stops - sizes).tolist(), (stops - 1).tolist(), xxhash.xxh64_intdigest
    hashes = [digest(line[a:b], 42) for n in range(1, ngrams + 1) for a, b in zip(starts, stops[n - 1 :], strict=False)]
    return np.array(hashes, np.uint64).view(np.int64) % buckets


def weigh_grams(df: DataFrame, tokens: Column, keep: list[str], weights: np.ndarray, ngrams: int) -> DataFrame:
    """(keep..., total double): sums of the weights of the buckets of each row's n-grams, map-only."""
    ensure_importable(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total = [float(weights[buckets_of(u.as_py() or [], ngrams, len(weights))].sum()) for u in batch.column(0)]
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(total, pa.float64())], names=[*batch.schema.names[1:], "total"])

    fields = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(tokens.alias("__tokens"), *keep).mapInArrow(run, f"{fields}, total double")
