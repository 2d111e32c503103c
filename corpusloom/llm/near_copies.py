"""Near copies by the Jaccard similarity of word shingles, exactly: SimHash bytes first, then an inverted index of shingles.

Candidates come from the byte-position index of SimHash fingerprints with its count filter (see simhash.links), here of
five-word shingles. Texts at a similarity of 0.8 differ in about ten of 64 bits and many share no byte, so that index can't
reach all of them. An index whose postings are shingles themselves gives the rest. Two sets at SHARE or more have so many
shingles in common that, in one order of all shingles, the first n - ceil(SHARE n) + 1 of each contain a common one. Only
those are listed, so no pair is missed. The order puts shingles that are common in a sample last; any order gives the same
result, this one keeps lists short.

Each list first gives pairs with its least document. Of lists whose members are then still apart, short ones give all pairs of
members of different components. Long ones give a spanning forest of the pairs that sizes and bit sketches leave (neither can be
wrong): a group of near copies costs a pair a member, not all its pairs. All pairs are verified by whole sets. Where a
forest's pair fails that, its list is searched once more for all pairs of members that are still apart.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm.filters import bits_for, flag, without
from corpusloom.llm.simhash import _LOWER, links
from corpusloom.llm.worker import TEXTS, held, trim
from corpusloom.operators.graph import components
from corpusloom.runtime import cut, ensure_importable

#: The similarity, as a fraction, so that all comparisons are of whole numbers.
SHARE = (4, 5)
#: Documents whose shingles are counted for the order, shingles read of each, and shingles that the order knows.
SAMPLE, SAMPLE_SHINGLES, COMMON = 4_000, 2_000, 100_000
#: Least bits of a set's sketch, rows of a list that are searched at once, and rows of a list whose pairs are simply joined.
SKETCH, BLOCK, SHORT = 1_024, 10_000, 8


def shingles(text: str | None, size: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of one text; a text of fewer words is one shingle, one without words none."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return np.zeros(0, np.int64)
    line, lengths = b" ".join(words), np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(lengths)
    starts, ends = (ends - lengths)[: max(1, len(words) - size + 1)].tolist(), (ends[min(size, len(words)) - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(line[a:b], 42) for a, b in zip(starts, ends, strict=True)), np.uint64, len(starts)).view(np.int64))


def listed(found: np.ndarray, common: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The shingles of a set that are listed: its first ones, by count in the sample, then by hash."""
    n = len(found)
    if not n:
        return found
    rank = np.zeros(n, np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, found), len(common) - 1)
        rank = np.where(common[at] == found, counts[at], 0)
    return found[np.lexsort((found, rank))[: n - -(-SHARE[0] * n // SHARE[1]) + 1]]


def _mapper(size: int, row: Callable[[np.ndarray], tuple], schema: pa.Schema) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held("shingles", dict)  # nothing is kept; what other operators kept goes
        for batch in batches:
            for at in range(0, batch.num_rows, 256):  # bounds memory for very long texts
                part = batch.slice(at, 256)
                rows = [row(shingles(x.as_py(), size)) for x in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), list(schema)[1:], strict=True))], schema=schema)
        trim()

    return run


def _order(docs: DataFrame, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles of more than one document of a sample, sorted, and their counts; bounded by the constants above."""
    schema = pa.schema([("doc_id", pa.int64()), ("found", pa.list_(pa.int64()))])
    sample = docs.withColumn("__h", F.xxhash64("doc_id")).orderBy("__h").limit(SAMPLE).select("doc_id", "text")
    some = sample.mapInArrow(_mapper(size, lambda s: (s[:SAMPLE_SHINGLES],), schema), "doc_id long, found array<long>")
    top = some.select(F.explode("found").alias("x")).groupBy("x").count().where("count > 1").orderBy(F.desc("count"), "x").limit(COMMON).toPandas().sort_values("x")
    return top["x"].to_numpy(np.int64), top["count"].to_numpy(np.int64)


def parities(found: np.ndarray) -> list[int]:
    """A sketch of bits, each the parity of the shingles that fall to it: two sets with d shingles of their own differ in at most d bits.

    Sets of more than SKETCH shingles have 2, 4, 8... times as many bits; folding halves by XOR gives the shorter sketch.
    """
    width = SKETCH
    while width < len(found):
        width *= 2
    bits = np.bincount(found & (width - 1), minlength=width).astype(np.uint8) & 1
    return np.packbits(bits).view(np.int64).tolist()


def fingerprint(found: np.ndarray) -> int:
    """SimHash of a set of shingle hashes, as a signed number; zero for the empty set."""
    bits = np.zeros(64, np.int64)
    for at in range(0, len(found), 65_536):  # bounds memory for very long texts
        bits += np.unpackbits(found[at : at + 65_536].astype(">i8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * bits > len(found)).tobytes(), "big", signed=True)


def _fold(sketches: np.ndarray) -> np.ndarray:
    half = sketches.shape[1] // 2
    return sketches[:, :half] ^ sketches[:, half:]


def search(sizes: np.ndarray, sketches: list[np.ndarray], labels: np.ndarray, forest: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of one list that may be at SHARE or more; equal labels are joined already.

    With forest, a pair joins its ends' labels and no more pairs are given between them. Sketches are compared whole, as in _met.
    """
    labels, widths = np.unique(labels, return_inverse=True)[1], np.fromiter(map(len, sketches), np.int64, len(sketches))
    own = {w: (at := np.flatnonzero(widths == w), np.stack([sketches[k] for k in at])) for w in np.unique(widths).tolist()}
    place = np.zeros(len(sizes), np.int64)
    for at, _ in own.values():
        place[at] = np.arange(len(at))
    halves = {w: _fold(rows) for w, (_, rows) in own.items() if w // 2 in own}
    for i in range(len(sizes) - 1):
        w, met = int(widths[i]), []
        # Sizes within SHARE have sketches of the same width, or of twice it.
        for other in (w // 2, w, 2 * w):
            if other not in own:
                continue
            at, rows = own[other]
            some = np.flatnonzero((at > i) & (labels[at] != labels[i]) & (np.minimum(sizes[at], sizes[i]) * SHARE[1] >= np.maximum(sizes[at], sizes[i]) * SHARE[0]))
            if not len(some):
                continue
            mine, theirs = (halves[w] if other < w else own[w][1])[place[i]], (halves[other] if other > w else rows)[some]
            apart = np.bitwise_count(theirs ^ mine).sum(1, dtype=np.int64)
            met.append(at[some[apart * sum(SHARE) <= (sizes[at[some]] + sizes[i]) * (SHARE[1] - SHARE[0])]])
        at = np.sort(np.concatenate(met)) if met else np.zeros(0, np.int64)
        if not len(at):
            continue
        if forest:
            joined, first = np.unique(labels[at], return_index=True)
            at = at[first]
            labels[np.isin(labels, joined)] = labels[i]
        yield np.full(len(at), i), at


def _searcher(forest: bool) -> Callable[[pa.Table], pa.Table]:
    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by("rep")  # forests of lists with the same members are then alike
        keys, reps, sizes, labels = (group.column(c).to_numpy() for c in ("key", "rep", "n", "label"))
        sketches = group.column("sketch").combine_chunks()
        flat, bounds = sketches.flatten().to_numpy().view(np.uint64), np.concatenate(([0], np.cumsum(sketches.value_lengths().to_numpy())))
        pairs = list(search(sizes, [flat[a:b] for a, b in zip(bounds, bounds[1:], strict=False)], labels, forest))
        i, j = (np.concatenate(x) for x in zip(*pairs, strict=True)) if pairs else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        return pa.table({"key": keys[i], "src": reps[i], "dst": reps[j]})

    return run


def _met(docs: DataFrame, sketches: DataFrame, pairs: DataFrame, size: int) -> DataFrame:
    """The pairs (src, dst) at SHARE or more: by sizes and sketches, which lose none, then by whole sets."""
    a, b = (sketches.select(F.col("rep").alias(end), F.col("n").alias(f"{end}_n"), F.col("sketch").alias(f"{end}_sketch")) for end in ("src", "dst"))
    near = F.least("src_n", "dst_n") * SHARE[1] >= F.greatest("src_n", "dst_n") * SHARE[0]
    # Sizes within SHARE have sketches of the same width, or of twice it.
    width = F.least(F.size("src_sketch"), F.size("dst_sketch"))
    one, other = (F.when(F.size(x) == width, F.col(x)).otherwise(F.zip_with(F.slice(x, 1, width), F.slice(x, width + 1, width), lambda u, v: u.bitwiseXOR(v))) for x in ("src_sketch", "dst_sketch"))
    apart = F.aggregate(F.zip_with(one, other, lambda x, y: F.coalesce(F.bit_count(x.bitwiseXOR(y)), F.lit(0)).cast("int")), F.lit(0), lambda x, y: x + y)
    near &= apart * sum(SHARE) <= (F.col("src_n") + F.col("dst_n")) * (SHARE[1] - SHARE[0])
    pairs = cut(pairs.distinct().join(a, "src").join(b, "dst").where(near).select("src", "dst"))
    # Whole sets only of these documents. A false hit of the filter has no row to meet.
    ends = cut(pairs.select(F.explode(F.array("src", "dst")).alias("doc_id")).distinct())
    if bits := bits_for(ends.count()):
        docs = flag(docs, F.xxhash64("doc_id"), ends.select(F.xxhash64("doc_id").alias("h")), bits).where("__maybe").select("doc_id", "text")
    else:
        docs = docs.join(ends, "doc_id", "left_semi")
    schema = pa.schema([("rep", pa.int64()), ("found", pa.list_(pa.int64()))])
    sets = cut(docs.mapInArrow(_mapper(size, lambda s: (s,), schema), "rep long, found array<long>"), TEXTS)
    a, b = (sets.select(F.col("rep").alias(end), F.col("found").alias(f"{end}_set")) for end in ("src", "dst"))
    enough = F.size(F.array_intersect("src_set", "dst_set")) * sum(SHARE) >= (F.size("src_set") + F.size("dst_set")) * SHARE[0]
    return cut(pairs.join(a, "src").join(b, "dst").where(enough).select("src", "dst"))


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, block: int = BLOCK, short: int = SHORT) -> DataFrame:
    """(node, component): the documents linked at SHARE or more to others; component is the smallest id reachable. Null ids are left out."""
    ensure_importable(docs.sparkSession)
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("doc_id is not null")
    common, counts = _order(docs, size)
    schema = pa.schema([("doc_id", pa.int64()), ("same", pa.binary()), ("fp", pa.int64()), ("n", pa.int64()), ("sketch", pa.list_(pa.int64())), ("keys", pa.list_(pa.int64()))])
    row = lambda s: (xxhash.xxh3_128_digest(s.tobytes()), fingerprint(s), len(s), parities(s), listed(s, common, counts))
    rows = cut(docs.mapInArrow(_mapper(size, row, schema), "doc_id long, same binary, fp long, n long, sketch array<long>, keys array<long>"), TEXTS)
    # Equal sets are one node.
    equal = rows.groupBy("same").agg(F.min("doc_id").alias("rep"), F.count("*").alias("of")).where("of > 1")
    equal = cut(rows.select("doc_id", "same").join(equal, "same").where("doc_id <> rep").select(F.col("doc_id").alias("src"), F.col("rep").alias("dst")))
    nodes = without(rows.drop("same"), equal.select(F.col("src").alias("doc_id")).distinct(), ["doc_id"]).withColumnRenamed("doc_id", "rep")
    sketches = nodes.select("rep", "n", "sketch")
    # The byte-position index of the fingerprints; equal ones are one row of it.
    prints = cut(nodes.groupBy("fp").agg(F.min("rep").alias("rep"), F.count("*").alias("of")))
    alike = nodes.select("rep", "fp").join(prints.where("of > 1").select("fp", F.col("rep").alias("dst")), "fp").where("rep <> dst").select(F.col("rep").alias("src"), "dst")
    alike = alike.unionByName(links(prints.select("fp", "rep")))
    # A list is aggregated to its least document before its rows are joined back; most lists have one row and are filtered before that.
    index = nodes.select("rep", "n", F.explode("keys").alias("key"))
    lists = cut(index.groupBy("key").agg(F.count("*").alias("of"), F.min("rep").alias("least")).where("of > 1"))
    if bits := bits_for(lists.count()):
        index = flag(index, F.xxhash64("key"), lists.select(F.xxhash64("key").alias("h")), bits).where("__maybe").select("rep", "n", "key")
    index = cut(index.join(lists, "key"))
    stars = index.where("rep <> least").select(F.col("rep").alias("src"), F.col("least").alias("dst"))
    met = _met(docs, sketches, alike.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).unionByName(stars), size)
    # Lists of two are settled. Of the longer ones those whose members are in one component are too; of lists of the same members one is enough.
    label = components(met).select(F.col("node").alias("rep"), F.col("component").alias("label"))
    rest = index.where("of > 2").select("key", "rep", "n", "of").join(label, "rep", "left").withColumn("label", F.coalesce("label", "rep"))
    apart = rest.groupBy("key", "of").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.sum(F.xxhash64("rep").cast("decimal(38,0)")).alias("who"))
    apart = apart.where("lo <> hi").groupBy("who", "of").agg(F.min("key").alias("key"))
    rest = cut(rest.join(apart.select("key"), "key"))
    few = rest.where(F.col("of") <= short)
    other = few.select("key", F.col("rep").alias("dst"), F.col("n").alias("m"), F.col("label").alias("its"))
    few = few.join(other, "key").where("rep < dst and label <> its").where(F.least("n", "m") * SHARE[1] >= F.greatest("n", "m") * SHARE[0]).select(F.col("rep").alias("src"), "dst")
    # Long lists are cut into g blocks; a row meets every block of its list, in the task of the two blocks.
    many = rest.where(F.col("of") > short).withColumn("g", F.ceil(F.col("of") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("g")).cast("int"))
    many = many.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("g") - 1))).select("rep", "label", F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("key"))
    many = cut(many.join(sketches, "rep").select("key", "rep", "n", "label", "sketch"))
    forests = cut(many.groupBy("key").applyInArrow(_searcher(True), "key long, src long, dst long"))
    met = cut(met.unionByName(_met(docs, sketches, few.unionByName(forests.select("src", "dst")), size)))
    # A forest with a pair that isn't at SHARE may have taken members for joined that are not.
    wrong = cut(forests.join(met, ["src", "dst"], "left_anti").select("key").distinct())
    if not wrong.isEmpty():
        label = components(met).select(F.col("node").alias("rep"), F.col("component").alias("label"))
        many = many.drop("label").join(wrong, "key").join(label, "rep", "left").withColumn("label", F.coalesce("label", "rep"))
        met = met.unionByName(_met(docs, sketches, many.groupBy("key").applyInArrow(_searcher(False), "key long, src long, dst long").select("src", "dst"), size))
    return components(cut(equal.unionByName(met)))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5) -> DataFrame:
    """docs with one document of each component, that of the smallest id; rows with a null id stay."""
    lost = near_copies(docs, id_col, text_col, size).where("component < node").select(F.col("node").alias(id_col)).distinct()
    return without(docs, cut(lost), [id_col])
