"""Best-fit packing with certified bin counts.

Pieces are dealt into partitions by a hash. Each partition runs best-fit decreasing and computes a lower bound of its
bin count from families of dual-feasible functions; where the two are equal no packing of that partition is better.
Partitions with a gap give up all bins that aren't full, certified ones the emptiest of those (their rests together may
save a bin), all of them the few bins with the smallest pieces. What they gave up is dealt into fewer partitions and
packed again, until one partition is left.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from itertools import count

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm import vocab
from corpusloom.llm.worker import trim
from corpusloom.runtime import cut, ensure_importable

CAPACITY = 4096
PART_PIECES = 4096
#: One bin in so many is given up for its small pieces.
DONORS = 32
BLOCK_CHARS = 3_000_000
_PLACED = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, bin int, offset long, closed boolean, bins int, bound int"


def lower_bound(sizes: np.ndarray, capacity: int = CAPACITY) -> int:
    """The best of two families of dual-feasible functions, over all their parameters that matter here."""
    if not len(sizes):
        return 0
    hist = np.bincount(sizes, minlength=capacity + 1).astype(np.int64)
    count, total = np.cumsum(hist), np.cumsum(hist * np.arange(capacity + 1))
    # Sizes under a cut count nothing, those that leave less than the cut count a whole bin, others themselves.
    lam = np.arange(0, capacity // 2 + 1)
    big = count[-1] - count[capacity - lam]
    mid = total[capacity - lam] - np.where(lam > 0, total[lam - 1], 0)
    best = int((big + -(-mid // capacity)).max())
    # Sizes are rounded down to k-ths of a bin of k + 1 steps, those on a step count themselves.
    x, n = np.flatnonzero(hist), hist[np.flatnonzero(hist)]
    for k in range(1, 100):
        on = (x * (k + 1)) % capacity == 0
        worth = np.where(on, x * k, (x * (k + 1)) // capacity * capacity)  # in k-ths of a size
        best = max(best, -(-int((worth * n).sum()) // (capacity * k)))
    return best


def best_fit_decreasing(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin and offset of each size, and the fill of each bin."""
    bins, offsets, fill = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64), []
    by_space: list[list[int]] = [[] for _ in range(capacity + 1)]
    spaces = 0  # bit s is set if a bin has s left
    for i in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[i])
        fits = spaces >> size
        if fits:
            space = size + (fits & -fits).bit_length() - 1
            at = by_space[space].pop()
            if not by_space[space]:
                spaces ^= 1 << space
        else:
            space, at = capacity, len(fill)
            fill.append(0)
        bins[i], offsets[i] = at, fill[at]
        fill[at] += size
        by_space[space - size].append(at)
        spaces |= 1 << (space - size)
    return bins, offsets, np.array(fill, np.int64)


def _packer(capacity: int, last: bool):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["length", "doc_id", "piece"], ascending=[False, True, True], kind="stable")
        sizes = pdf["length"].to_numpy(np.int64)
        bins, offsets, fill = best_fit_decreasing(sizes, capacity)
        bound = lower_bound(sizes, capacity)
        open_ = fill < capacity
        if len(fill) == bound:  # the emptiest will do
            open_[np.argsort(fill, kind="stable")[max(1, len(fill) // 8) :]] = False
        # Bins of the smallest pieces go along: what fills gaps best.
        open_[np.argsort(-np.bincount(bins, minlength=len(fill)), kind="stable")[: len(fill) // DONORS]] = True
        return pdf.assign(bin=bins, offset=offsets, closed=True if last else ~open_[bins], bins=len(fill), bound=bound)

    return run


def pack(pieces: DataFrame, capacity: int = CAPACITY, part_pieces: int = PART_PIECES, batch: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Placements (doc_id, piece, start, length, ids_crc32, sequence_id, offset), and certificates (round, part, bins, bound).

    pieces: (doc_id, piece, start, length, ids_crc32), lengths from 1 to capacity. Every row gets a place. Rounds go on until
    one partition is left, or until a round closes no sequence. batch: rows of the pieces' source that cross to Python at once.
    """
    spark = pieces.sparkSession
    ensure_importable(spark)
    pieces = cut(pieces, batch)
    columns = ["doc_id", "piece", "start", "length", "ids_crc32"]
    whole = pieces.where(F.col("length") == capacity)
    done = [whole.select(*columns, F.monotonically_increasing_id().alias("sequence_id"), F.lit(0).cast("long").alias("offset"))]
    certificates = []
    rest = pieces.where(F.col("length") < capacity).select(*columns)
    before = None
    for k in count(1):
        n = rest.count()
        parts = max(1, math.ceil(n / part_pieces))
        last = parts == 1 or n == before
        before = n
        dealt = rest.withColumn("part", F.pmod(F.xxhash64(F.monotonically_increasing_id(), F.lit(k)), F.lit(parts)).cast("int"))
        placed = cut(dealt.groupBy("part").applyInPandas(_packer(capacity, last), _PLACED))
        sequence = F.lit(k << 56) + F.col("part").cast("long") * F.lit(1 << 24) + F.col("bin")
        done.append(placed.where("closed").select(*columns, sequence.alias("sequence_id"), "offset"))
        certificates.append(placed.groupBy("part").agg(F.max("bins").alias("bins"), F.max("bound").alias("bound")).select(F.lit(k).alias("round"), "part", "bins", "bound"))
        if last:
            break
        rest = placed.where("not closed").select(*columns)
    placements, proofs = done[0], certificates[0]
    for x in done[1:]:
        placements = placements.unionByName(x)
    for x in certificates[1:]:
        proofs = proofs.unionByName(x)
    return placements, proofs


def document_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", cache: int = vocab.CACHE, block_chars: int = BLOCK_CHARS, special: bool = True) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of each document's ids and end_id; only longer ones than capacity are cut.

    A null text counts as the empty text, which is one piece of one id. The strings of special tokens stand for those
    tokens unless special is off. cache (entries, about 200 bytes each) and
    block_chars bound a worker's memory; more of either saves time and changes no result.
    """
    ensure_importable(docs.sparkSession)
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = vocab.pieces(path, cache, special).encode
        for keys, texts in vocab.blocks(batches, block_chars):
            rows: list[tuple] = []
            for key, ids in zip(keys.to_pylist(), encode(texts), strict=True):
                ids += end
                n = len(ids) // 4
                rows += [(key, k, a, min(capacity, n - a), zlib.crc32(ids[4 * a : 4 * (a + capacity)])) for k, a in enumerate(range(0, n, capacity))]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])
        trim()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")
