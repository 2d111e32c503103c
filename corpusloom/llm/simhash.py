"""Near-duplicates of 64-bit SimHash fingerprints, through an inverted index on byte positions.

Fingerprints with at most four different bits share at least four of their eight bytes, each at its position. A posting
list of one byte would hold a 256th of all rows, so a list is kept for three positions at once: TRIPLES are twenty
triples of positions of which any four positions contain at least one, so two linked fingerprints share some list.
Inside a list the shared bytes of a pair are tallied, pairs
under four are dropped and the rest verified by their different bits. A list gives a spanning forest of its links, not
all of them. Lists over BLOCK rows are cut into blocks, and every two blocks meet in a task of their own.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm.filters import without
from corpusloom.llm.worker import held
from corpusloom.operators.graph import components
from corpusloom.runtime import cut, ensure_importable

BLOCK = 50_000
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def covering_triples(positions: int = 8, shared: int = 4) -> list[tuple[int, ...]]:
    """Triples of byte positions of which every set of `shared` positions contains one; greedy, then checked."""
    open_sets = set(combinations(range(positions), shared))
    chosen: list[tuple[int, ...]] = []
    # Three classes: all triples within a class, and pairs of one class with one of the next, cover every four positions.
    classes = [range(0, 3), range(3, 6), range(6, 8)]
    where = {p: c for c, r in enumerate(classes) for p in r}
    for t in combinations(range(positions), 3):
        kinds = [where[p] for p in t]
        if len(set(kinds)) == 1 or any(kinds.count(c) == 2 and kinds.count((c + 1) % 3) == 1 for c in range(3)):
            chosen.append(t)
            open_sets = {s for s in open_sets if not set(t) <= set(s)}
    if open_sets:
        raise AssertionError("triples do not cover")
    return chosen


TRIPLES = covering_triples()


def fingerprint(text: str | None, size: int = 4) -> int:
    """SimHash of the word shingles of one text, repeats included; zero without words."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return 0
    if len(words) <= size:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)  # one shingle: its bits
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = (ends - np.fromiter(map(len, words), np.int64, len(words)) - 1)[: len(words) - size + 1].tolist()
    line, digest, ends = b" ".join(words), xxhash.xxh64_intdigest, (ends[size - 1 :] - 1).tolist()
    set_bits, n = np.zeros(64, np.int64), len(starts)
    for at in range(0, n, 65_536):  # bounds memory for very long texts
        hashes = np.fromiter((digest(line[a:b], 42) for a, b in zip(starts[at : at + 65_536], ends[at : at + 65_536], strict=True)), np.uint64)
        set_bits += np.unpackbits(hashes.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * set_bits > n).tobytes(), "big")


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held("fingerprints", dict)  # nothing is kept; what other operators kept goes
    for batch in batches:
        prints = np.fromiter((fingerprint(x.as_py()) for x in batch.column(1)), np.uint64, batch.num_rows).view(np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints)], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp); a null text has no words."""
    ensure_importable(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints, "doc_id long, fp long")


def _links(one: np.ndarray, many: np.ndarray, bits: int) -> np.ndarray:
    """Count filter, then the different bits."""
    x = one ^ many
    met = np.flatnonzero((x.view(np.uint8).reshape(-1, 8) == 0).sum(1) >= 8 - bits)
    return met[np.bitwise_count(x[met]) <= bits]


def spanning(prints: np.ndarray, bits: int = 4) -> Iterator[tuple[int, int]]:
    """Index pairs that span the components among prints: a search from each open print through those not reached yet."""
    open_ = np.arange(len(prints))
    while len(open_) > 1:
        front, open_ = [open_[0]], open_[1:]
        while front and len(open_):
            at = front.pop()
            met = _links(prints[at], prints[open_], bits)
            for j in open_[met]:
                yield int(at), int(j)
                front.append(j)
            open_ = np.delete(open_, met)


def _runs(keys: np.ndarray, prints: np.ndarray, reps: np.ndarray, bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links of whole runs of equal keys. Short runs are compared side by side, all at once; long ones are searched."""
    starts = np.flatnonzero(np.diff(keys, prepend=keys[0] - 1))
    sizes = np.diff(starts, append=len(keys))
    out = []
    length = np.repeat(sizes, sizes)
    place = np.arange(len(keys)) - np.repeat(starts, sizes)
    for step in range(1, 9):
        at = np.flatnonzero((length <= 8) & (place + step < length))
        if not len(at):
            break
        x = prints[at] ^ prints[at + step]
        ok = at[((x.view(np.uint8).reshape(-1, 8) == 0).sum(1) >= 8 - bits) & (np.bitwise_count(x) <= bits)]
        out.append((reps[ok], reps[ok + step]))
    for a, n in zip(starts[sizes > 8], sizes[sizes > 8], strict=True):
        if pairs := list(spanning(prints[a : a + n], bits)):
            i, j = np.array(pairs).T
            out.append((reps[a + i], reps[a + j]))
    return out


def _linker(bits: int):
    def link(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Rows come sorted by key; a run that may go on in the next batch is held back. A run has at most 2 BLOCK rows."""
        held: list[tuple[np.ndarray, ...]] = []
        for frame in frames:
            new = (frame["key"].to_numpy(np.int64), frame["fp"].to_numpy(np.int64).view(np.uint64), frame["rep"].to_numpy(np.int64))
            if not len(new[0]):
                continue
            held.append(new)
            if new[0][0] == new[0][-1] == held[0][0][-1] and held[0][0][0] == new[0][0]:
                continue
            keys, prints, reps = (np.concatenate(x) for x in zip(*held, strict=True))
            stop = np.searchsorted(keys, keys[-1])
            held = [(keys[stop:], prints[stop:], reps[stop:])]
            if stop:
                yield _pairs(_runs(keys[:stop], prints[:stop], reps[:stop], bits))
        if held:
            yield _pairs(_runs(*(np.concatenate(x) for x in zip(*held, strict=True)), bits))

    return link


def _pairs(found: list[tuple[np.ndarray, np.ndarray]]) -> pd.DataFrame:
    a, b = (np.concatenate(x) if found else np.zeros(0, np.int64) for x in (zip(*found, strict=True) if found else ((), ())))
    return pd.DataFrame({"src": a, "dst": b}).drop_duplicates()


def links(nodes: DataFrame, bits: int = 4, block: int = BLOCK) -> DataFrame:
    """(src, dst): links between the rep of nodes (fp, rep), fp distinct, that connect all that are linked at bits or fewer."""
    if bits > 4:
        raise ValueError("the index guarantees links of at most four different bits")
    byte = lambda p: f"(shiftrightunsigned(fp, {8 * p}) & 255L)"
    keys = ", ".join(f"{k}L * 16777216L + {byte(a)} * 65536L + {byte(b)} * 256L + {byte(c)}" for k, (a, b, c) in enumerate(TRIPLES))
    index = nodes.select("fp", "rep", F.expr(f"explode(array({keys}))").alias("key"))
    grid = None
    if nodes.count() > block:
        long_ = cut(index.groupBy("key").count().where(F.col("count") > block).select("key", F.ceil(F.col("count") / block).cast("int").alias("g")))
        if not long_.isEmpty():
            # g blocks; a row meets every block of its list, in the task of the two blocks.
            own = F.pmod(F.xxhash64("fp"), F.col("g")).cast("int")
            grid = (
                index.join(long_, "key").withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("g") - 1)))
                .select("fp", "rep", F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("key"))
            )
            index = index.join(long_, "key", "left_anti")
    index = index.select("key", "fp", "rep")
    # A grid key may by chance equal another key; then more rows meet than need to, and none are missed.
    index = index if grid is None else index.unionByName(grid.select("key", "fp", "rep"))
    return index.repartition("key").sortWithinPartitions("key").mapInPandas(_linker(bits), "src long, dst long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = 4, block: int = BLOCK) -> DataFrame:
    """(doc_id, fingerprint, component_id), one row for each row of docs.

    Equal fingerprints are one node, so groups of copies cost one row each. Rows without words (null, empty, white space)
    have fingerprint zero and are linked like any other. component_id is the smallest doc_id reachable. Rows with a null
    id get the component of their fingerprint, null if all its rows lack an id. Other columns are not read.
    """
    prints = cut(fingerprints(docs, id_col, text_col))
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    found = components(links(nodes.where("rep is not null"), bits, block))
    named = nodes.join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return prints.join(named, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = 4) -> DataFrame:
    """docs with one document of each component, that of the smallest id; rows with a null id stay."""
    lost = near_duplicates(docs, id_col, text_col, bits).where("component_id < doc_id").select(F.col("doc_id").alias(id_col)).distinct()
    return without(docs, cut(lost), [id_col])
