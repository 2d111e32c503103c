"""Pairs of sets at a Jaccard similarity t or more: candidates of lists, bounds of narrow rows, whole sets of what is left.

Sets are never stored or dealt out for all documents. Lists of documents give candidates whose sizes, and parity sketches where
rows have them, allow t; whole sets are made again, for the documents of such pairs alone, and go once to each cell of pairs
that needs them instead of once to each pair.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import cut

#: Pairs of a cell, pairs of one label from which it is dealt over several cells, ids broadcast at once.
CELL, HEAVY, IDS = 4_000, 300_000, 500_000
#: Rows of a list from which blocks of it meet in tasks of their own (found in one document of SHARE), pairs in memory at once.
BLOCK, SHARE, CHUNK = 10_000, 64, 1 << 18


def sketch(found: np.ndarray) -> bytes:
    """The parity of how many members fall to each of 64, 128... bits, as many as members at least.

    Two sets with d members of their own differ in at most d bits. Folding halves by XOR gives the shorter sketch.
    """
    width = 64
    while width < len(found):
        width *= 2
    return np.packbits(np.bincount(found & (width - 1), minlength=width).astype(np.uint8) & 1).tobytes()


def _matrix(parts: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(parts), np.uint64).reshape(len(parts), -1)


def _fold(rows: np.ndarray, words: int) -> np.ndarray:
    while rows.shape[1] > words:
        half = rows.shape[1] // 2
        rows = rows[:, :half] ^ rows[:, half:]
    return rows


def _allowed(apart: np.ndarray, sizes: np.ndarray, t: float) -> np.ndarray:
    return apart * (1 + t) <= sizes * (1 - t) + 1e-9


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables of whole runs of equal keys, of batches sorted by key."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column("key").to_numpy()
        turns = np.flatnonzero(keys[1:] != keys[:-1]) + 1
        if held and held[-1].column("key")[-1].as_py() != keys[0]:
            at = 0 if not len(turns) else int(turns[-1])
        else:
            at = int(turns[-1]) if len(turns) else -1
        if at >= 0:
            yield pa.Table.from_batches([*held, batch.slice(0, at)])
            held = []
        held.append(batch.slice(max(at, 0)))
    if held:
        yield pa.Table.from_batches(held)


def _ends(run: np.ndarray, n: np.ndarray, t: float) -> np.ndarray:
    """For each row of runs sorted by n, the first row behind those of its run whose size allows t."""
    wide = int(n.max()) + 2
    return np.searchsorted(run * wide + n, run * wide + np.minimum(np.floor(n / t + 1e-9).astype(np.int64), wide - 1), "right")


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["src", "dst"])


def _by_size(table: pa.Table, t: float) -> Iterator[pa.RecordBatch]:
    """Pairs by size. Two rows whose keys before this one are equal have met there."""
    keys, ids, n, before = (table.column(c).to_numpy() for c in ("key", "id", "n", "before"))
    run = np.concatenate(([0], np.cumsum(keys[1:] != keys[:-1])))
    at = np.arange(len(ids))
    of = _ends(run, n, t) - at - 1
    rows = np.flatnonzero(of > 0)
    total = np.cumsum(of[rows])
    begin = 0
    while begin < len(rows):
        end = max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + CHUNK, "right")))
        some = rows[begin:end]
        i = np.repeat(some, of[some])
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(of[some]) - of[some], of[some])
        new = (ids[i] != ids[j]) & ((before[i] != before[j]) | (before[i] < 0))
        if new.any():
            yield _pairs(ids[i[new]], ids[j[new]])
        begin = end


def _by_sketch(table: pa.Table, t: float, step: int = 128) -> Iterator[pa.RecordBatch]:
    """Pairs by size and sketch, list by list; rows of a list are sorted by size, so those of one width lie together."""
    keys, ids, n = (table.column(c).to_numpy() for c in ("key", "id", "n"))
    parts = table.column("sketch").to_pylist()
    widths = np.fromiter(map(len, parts), np.int64, len(parts))
    turns = np.flatnonzero(np.diff(keys) | np.diff(widths)) + 1
    bounds = [0, *turns.tolist(), len(ids)]
    run = np.concatenate(([0], np.cumsum(keys[1:] != keys[:-1])))
    ends = _ends(run, n, t)
    for k, (a, b) in enumerate(zip(bounds, bounds[1:], strict=False)):
        if int(ends[a:b].max()) <= a + 1:
            continue
        own = _matrix(parts[a:b])
        others, after = [(a, b, own)], k + 1  # and the wider ones of the same list
        while bounds[after] < int(ends[b - 1]):
            first, last = bounds[after : after + 2]
            others.append((first, last, _fold(_matrix(parts[first:last]), own.shape[1])))
            after += 1
        for x in range(a, b, step):
            y = min(x + step, b)
            for first, last, rows in others:
                for u in range(max(first, x), min(last, int(ends[y - 1])), 4 * step):
                    v = min(u + 4 * step, last, int(ends[y - 1]))
                    apart = np.zeros((y - x, v - u), np.int64)
                    for w in range(own.shape[1]):
                        apart += np.bitwise_count(own[x - a : y - a, w, None] ^ rows[None, u - first : v - first, w])
                    near = _allowed(apart, n[x:y, None] + n[None, u:v], t) & (np.arange(u, v)[None] > np.arange(x, y)[:, None]) & (ids[x:y, None] != ids[None, u:v])
                    i, j = np.nonzero(near)
                    if len(i):
                        yield _pairs(ids[x + i], ids[u + j])


def met(nodes: DataFrame, lists: Callable[[DataFrame], DataFrame], t: float) -> DataFrame:
    """(src, dst), distinct, of the lists (key, id, n and sketch or before) of nodes: what sizes, and sketches where given, leave.

    Long lists are cut into blocks; a row meets every block of its list, in the task of the two blocks.
    """
    index = lists(nodes)
    own = [c for c in index.columns if c != "key"]
    hot = cut(lists(nodes.where(F.pmod(F.xxhash64("id"), F.lit(SHARE)) == 0)).groupBy("key").agg(F.count("*").alias("of")).where(F.col("of") * SHARE > BLOCK))
    if not hot.isEmpty():
        blocks = F.broadcast(hot.select("key", F.ceil(F.col("of") * SHARE / BLOCK).cast("int").alias("g")))
        index = index.join(blocks, "key", "left").withColumn("g", F.coalesce("g", F.lit(1))).withColumn("own", F.pmod(F.xxhash64("id"), F.col("g")).cast("int"))
        index = index.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("g") - 1)))
        index = index.select(F.when(F.col("g") == 1, F.col("key")).otherwise(F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other"))).alias("key"), *own)
    kernel = _by_sketch if "sketch" in own else _by_size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _runs(batches):
            yield from kernel(table, t)

    return cut(index.repartition("key").sortWithinPartitions("key", "n").mapInArrow(run, "src long, dst long").distinct())


def settle(pairs: DataFrame, rows: Callable[[DataFrame], DataFrame], kernel: Callable[[pa.Table, pa.Table], pa.Table], schema: str) -> DataFrame:
    """What kernel gives of each cell's pairs (cell, src, dst) and of the rows (cell, id, n, found) of all their documents.

    rows makes (id, cells, n, found) of (id, cells). A pair's cell is that of the least document that its src was met with, so
    pairs of one group of near copies lie together and a document goes to few cells; heavy groups are dealt over several.
    """
    least = pairs.groupBy("dst").agg(F.min("src").alias("label")).withColumnRenamed("dst", "src")
    named = cut(pairs.join(least, "src", "left").select("src", "dst", F.coalesce("label", "src").alias("label")))
    cells = max(2 * pairs.sparkSession.sparkContext.defaultParallelism, named.count() // CELL)
    heavy = F.broadcast(named.groupBy("label").agg(F.count("*").alias("of")).where(F.col("of") > HEAVY))
    deal = F.when(F.col("of").isNull(), 0).otherwise(1 + F.pmod(F.xxhash64("src"), F.ceil(F.col("of") / HEAVY)))
    placed = cut(named.join(heavy, "label", "left").select("src", "dst", F.xxhash64(F.pmod(F.xxhash64("label"), F.lit(cells)), deal.cast("long")).alias("cell")))
    members = cut(placed.select("cell", F.explode(F.array("src", "dst")).alias("id")).distinct().groupBy("id").agg(F.collect_list("cell").alias("cells")))
    beside = rows(members).select(F.explode("cells").alias("cell"), "id", "n", "found")
    return placed.groupBy("cell").cogroup(beside.groupBy("cell")).applyInArrow(kernel, schema)


def of_members(docs: DataFrame, members: DataFrame) -> DataFrame:
    """The rows of docs whose id members have, with their cells: members are broadcast in blocks, so no text is dealt out."""
    blocks = max(1, -(-members.count() // IDS))
    return reduce(DataFrame.unionByName, (docs.join(F.broadcast(members.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == b)), "id") for b in range(blocks)))


def _places(pairs: pa.Table, members: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """src, dst, their places among members with an id once, and the rows of those members."""
    ids, at = np.unique(members.column("id").to_numpy(), return_index=True)
    src, dst = pairs.column("src").to_numpy(), pairs.column("dst").to_numpy()
    return src, dst, np.searchsorted(ids, src), np.searchsorted(ids, dst), at


def by_sketch(t: float) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """A kernel for settle: the pairs (src, dst) whose sizes and sketches (found) allow t."""

    def run(pairs: pa.Table, members: pa.Table) -> pa.Table:
        src, dst, i, j, at = _places(pairs, members)
        n, parts = members.column("n").to_numpy()[at], members.column("found").take(pa.array(at)).to_pylist()
        widths = np.fromiter(map(len, parts), np.int64, len(parts))
        place, own = np.zeros(len(at), np.int64), {}
        for w in np.unique(widths).tolist():
            some = np.flatnonzero(widths == w)
            place[some], own[w] = np.arange(len(some)), _matrix([parts[k] for k in some])
        low, high = np.where(widths[i] <= widths[j], i, j), np.where(widths[i] <= widths[j], j, i)
        good = np.zeros(len(src), bool)
        for w, rows in own.items():
            for other in (x for x in own if x >= w):
                theirs = _fold(own[other], rows.shape[1])
                some = np.flatnonzero((widths[low] == w) & (widths[high] == other))
                for x in range(0, len(some), 16_384):  # bounds memory
                    k = some[x : x + 16_384]
                    apart = np.bitwise_count(rows[place[low[k]]] ^ theirs[place[high[k]]]).sum(1, dtype=np.int64)
                    good[k] = _allowed(apart, n[i[k]] + n[j[k]], t)
        return pa.table({"src": src[good], "dst": dst[good]})

    return run


def shared(of: type) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """A kernel for settle: (src, dst, n1, n2, both), the sizes of both sets and what they have in common; found are the sets' bytes."""

    def run(pairs: pa.Table, members: pa.Table) -> pa.Table:
        src, dst, i, j, at = _places(pairs, members)
        parts = members.column("found").take(pa.array(at)).to_pylist()
        values = np.frombuffer(b"".join(parts), of)
        n = np.fromiter(map(len, parts), np.int64, len(parts)) // np.dtype(of).itemsize
        begin = np.concatenate(([0], np.cumsum(n)))
        known, local = np.unique(values, return_inverse=True)
        mark, both = np.zeros(len(known), bool), np.zeros(len(src), np.int64)
        order = np.argsort(i, kind="stable")
        turns = np.concatenate(([0], np.flatnonzero(np.diff(i[order])) + 1, [len(order)])).tolist()
        for a, b in zip(turns, turns[1:], strict=False):
            if a == b:
                continue
            one = i[order[a]]
            mark[local[begin[one] : begin[one + 1]]] = True
            for x in range(a, b, 1_024):  # bounds memory
                k = order[x : min(x + 1_024, b)]
                flat = np.concatenate([local[begin[o] : begin[o + 1]] for o in j[k].tolist()])
                both[k] = np.add.reduceat(mark[flat].astype(np.int64), np.concatenate(([0], np.cumsum(n[j[k]])[:-1])))
            mark[local[begin[one] : begin[one + 1]]] = False
        return pa.table({"src": src, "dst": dst, "n1": n[i], "n2": n[j], "both": both})

    return run


SHARED = "src long, dst long, n1 long, n2 long, both long"
