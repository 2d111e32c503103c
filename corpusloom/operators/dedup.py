"""Content and URL deduplication: MinHash signatures, bands, scopes, verification, components, survivors."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpusloom.operators import grams, setjoin
from corpusloom.operators.graph import components
from corpusloom.runtime import cut, ensure_importable
from corpusloom.sources.views import H28

PRIME = 2**31 - 1


def affine_family(n: int) -> list[tuple[int, int]]:
    """Multipliers and offsets by two fixed recurrences, so that any engine can list them."""
    out, a, b = [], 48271, 11
    for _ in range(n):
        out.append((a, b))
        a, b = a * 48271 % PRIME, b * 16807 % PRIME
    return out


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value) with value computed once: inside a lambda Spark computes what isn't a variable again for each element."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def words(text: Column) -> Column:
    return F.filter(F.split(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "), " "), lambda w: w != "")


def shingles(text: Column, n: int = 5, unit: str = "word") -> Column:
    """Distinct n-grams of words or characters; fewer units than n are one shingle, none give an empty array.

    unit 'auto' takes characters where a third of them are Han, which are written without spaces.
    """
    if unit == "auto":
        han = F.regexp_count(text, F.lit(r"\p{IsHan}")) * 3 >= F.length(text)
        return F.when(han, shingles(text, n, "char")).otherwise(shingles(text, n, "word"))
    parts = words(text) if unit == "word" else F.filter(F.split(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", ""), ""), lambda c: c != "")
    glue = " " if unit == "word" else ""

    def grams(p: Column) -> Column:
        at = F.sequence(F.lit(1), F.greatest(F.size(p) - (n - 1), F.lit(1)))
        return F.when(F.size(p) == 0, F.array().cast("array<string>")).otherwise(F.array_distinct(F.transform(at, lambda i: F.array_join(F.slice(p, i, F.lit(n)), glue))))

    return let(parts, grams)


def multiply_family(n: int) -> list[tuple[int, int]]:
    """Odd multipliers and offsets mod 2^64, by the recurrence of a 64-bit linear congruence."""
    out, x = [], 0x9E3779B97F4A7C15
    for _ in range(n):
        a = x = (x * 6364136223846793005 + 1442695040888963407) % 2**64
        x = (x * 6364136223846793005 + 1442695040888963407) % 2**64
        out.append((a | 1, x))
    return out


def units_of(text: Column, unit: str = "word") -> tuple[Column, Column]:
    """What n-grams are made of, and what stands between: words, characters, or 'auto' as in shingles()."""
    chars = F.filter(F.split(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", ""), ""), lambda c: c != "")
    if unit == "char":
        return chars, F.lit("")
    if unit == "word":
        return words(text), F.lit(" ")
    han = F.regexp_count(text, F.lit(r"\p{IsHan}")) * 3 >= F.length(text)
    return F.when(han, chars).otherwise(words(text)), F.when(han, F.lit("")).otherwise(F.lit(" "))


def signature(docs: DataFrame, id_col: str = "doc_id", ngram: int = 5, hashes: int = 112, family: str = "xxhash64", unit: str = "word", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, keep..., sig array<long>): element-wise minima over the shingles, so signatures of unions are minima of signatures.

    affine31 hashes md5 prefixes by (a x + b) mod 2^31 - 1, the same in any engine; xxhash64 multiplies 64-bit hashes. One
    vectorised crossing to Python; the text is dropped at once. Texts without words have no row and never meet by MinHash.
    """
    if family == "affine31":
        members = affine_family(hashes)

        def one(units: list[str], glue: str) -> list[int] | None:
            return grams.affine_minima(grams.md5_prefixes(grams.spans(units, ngram, glue)), members, PRIME).tolist() if units else None
    elif family == "xxhash64":
        members = multiply_family(hashes)

        def one(units: list[str], glue: str) -> list[int] | None:
            return grams.multiply_minima(np.fromiter(map(grams.xx64, grams.spans(units, ngram, glue)), np.uint64), members).tolist() if units else None
    else:
        raise ValueError(family)
    return grams.map_units(docs, *units_of(F.col("text"), unit), [id_col, *keep], one, "sig")


def signature_expr(docs: DataFrame, id_col: str = "doc_id", ngram: int = 5, hashes: int = 112) -> DataFrame:
    """The affine31 signature by column functions alone: the reference form of the kernel, slow for many hashes."""
    first = lambda g: F.conv(F.substring(F.md5(g.cast("binary")), 1, 7), 16, 10).cast("long")
    pairs = F.array(*(F.struct(F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b")) for a, b in affine_family(hashes)))
    minima = lambda xs: F.transform(pairs, lambda p: F.array_min(F.transform(xs, lambda x: (p["a"] * x + p["b"]) % PRIME)))
    return docs.where(F.col("text").rlike(r"[\p{L}\p{N}]")).select(id_col, let(F.transform(shingles(F.col("text"), ngram), lambda g: first(g)), minima).alias("sig"))


def bands(sigs: DataFrame, n_bands: int, rows: int, id_col: str = "doc_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, keep..., band, key): one row for each band."""
    keys = F.transform(F.sequence(F.lit(0), F.lit(n_bands - 1)), lambda b: F.md5(F.concat_ws(":", b.cast("string"), F.array_join(F.transform(F.slice("sig", b * rows + 1, F.lit(rows)), lambda x: x.cast("string")), ",")).cast("binary")))
    return sigs.select(id_col, *keep, F.posexplode(keys).alias("band", "key"))


def star_edges(banded: DataFrame, prefer: Column, id_col: str = "doc_id", scope: tuple[str, ...] = ()) -> DataFrame:
    """(src, dst), distinct: each bucket's records to its preferred one (the least of prefer), not all pairs of a bucket.

    Buckets are aggregated to their centre before the join back, and AQE splits buckets that are hot.
    """
    keys = [*scope, "band", "key"]
    centre = banded.groupBy(*keys).agg(F.min_by(id_col, prefer).alias("src"), F.count("*").alias("__n")).where("__n > 1").drop("__n")
    return banded.join(centre, keys).select("src", F.col(id_col).alias("dst")).where("src <> dst").distinct()


def collision_probability(s: Column, n_bands: int, rows: int) -> Column:
    return 1 - F.pow(1 - F.pow(s, F.lit(rows)), F.lit(n_bands))


def verify(pairs: DataFrame, docs: DataFrame, mode: str = "jaccard", t: float = 0.75, ngram: int = 5, hashes: int = 112, family: str = "xxhash64", id_col: str = "doc_id") -> DataFrame:
    """(src, dst, similarity) of pairs at t or more: band (all pairs, similarity null), estimate (equal minima) or jaccard (exact)."""
    if mode == "band":
        return pairs.select("src", "dst", F.lit(None).cast("double").alias("similarity"))
    if mode == "estimate":
        side = signature(docs, id_col, ngram, hashes, family).select(F.col(id_col).alias("id"), F.col("sig").alias("v"))
        value = F.aggregate(F.zip_with("va", "vb", lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, x: s + x) / F.lit(float(hashes))
    else:
        side = docs.select(F.col(id_col).alias("id"), shingles(F.col("text"), ngram).alias("v"))
        value = F.size(F.array_intersect("va", "vb")) / F.size(F.array_union("va", "vb"))
    a, b = side.select(F.col("id").alias("src"), F.col("v").alias("va")), side.select(F.col("id").alias("dst"), F.col("v").alias("vb"))
    return pairs.join(a, "src").join(b, "dst").select("src", "dst", value.alias("similarity")).where(F.col("similarity") >= t)


#: Documents whose shingles are counted for the order of exact_pairs, shingles read of each, and shingles that the order knows.
SAMPLE, SAMPLE_SHINGLES, COMMON = 4_000, 2_000, 100_000
#: Bytes of a shingle's hash that name its list: a list of two shingles costs pairs that are verified, and loses none.
NAME = 5


def _line(docs: DataFrame, id_col: str) -> DataFrame:
    """(id, line): the words of texts that have some, parted by spaces, as bytes."""
    return docs.where(F.col(id_col).isNotNull() & F.col("text").rlike(r"[\p{L}\p{N}]")).select(F.col(id_col).cast("long").alias("id"), F.regexp_replace(F.lower("text"), r"[^\p{L}\p{N}]+", " ").cast("binary").alias("line"))


def _map_sets(lines: DataFrame, ngram: int, row: Callable[[np.ndarray], tuple], schema: pa.Schema, keep: str = "") -> DataFrame:
    """(id, keep..., what row makes of a line's shingles), map-only; schema is that of row's columns."""
    ensure_importable(lines.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):  # bounds what a batch of long texts becomes in Python
                part = batch.slice(at, 512)
                made = zip(*(row(grams.line_hashes(x.as_py(), ngram)) for x in part.column("line")), strict=True)
                kept = part.drop_columns(["line"])
                yield pa.RecordBatch.from_arrays([*kept.columns, *(pa.array(c, f.type) for c, f in zip(made, schema, strict=True))], names=[*kept.schema.names, *schema.names])

    types = {pa.int64(): "bigint", pa.binary(): "binary", pa.list_(pa.int64()): "array<bigint>"}
    return lines.mapInArrow(run, ", ".join(["id bigint", *([keep] if keep else []), *(f"{f.name} {types[f.type]}" for f in schema)]))


def _order(lines: DataFrame, ngram: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles of more than one document of a sample, sorted, and their counts; bounded by the constants above."""
    some = lines.where(F.pmod(F.xxhash64("id"), F.lit(max(1, lines.count() // SAMPLE))) == 0)
    some = _map_sets(some, ngram, lambda s: (s[:SAMPLE_SHINGLES],), pa.schema([("found", pa.list_(pa.int64()))]))
    top = some.select(F.explode("found").alias("x")).groupBy("x").count().where("count > 1").orderBy(F.desc("count"), "x").limit(COMMON).toPandas().sort_values("x")
    return top["x"].to_numpy(np.int64), top["count"].to_numpy(np.int64)


def _named(nodes: DataFrame) -> DataFrame:
    """(key, id, n, before): a row for each listed shingle of (id, n, names), with the name before it, -1 for the first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1_024):  # bounds memory
                part = batch.slice(at, 1_024)
                names = part.column("names").to_pylist()
                of = np.fromiter(map(len, names), np.int64, len(names)) // NAME
                whole = np.zeros((int(of.sum()), 8), np.uint8)
                whole[:, 8 - NAME :] = np.frombuffer(b"".join(names), np.uint8).reshape(-1, NAME)
                key = whole.view(">i8").ravel().astype(np.int64)
                before = np.concatenate(([-1], key[:-1]))
                before[(np.cumsum(of) - of)[of > 0]] = -1
                ids, n = (np.repeat(part.column(c).to_numpy(), of) for c in ("id", "n"))
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (key, ids, n, before)], names=["key", "id", "n", "before"])

    return nodes.select("id", "n", "names").mapInArrow(run, "key bigint, id bigint, n bigint, before bigint")


def exact_pairs(docs: DataFrame, t: float = 0.75, ngram: int = 5, id_col: str = "doc_id") -> DataFrame:
    """(src, dst, similarity): every pair of different shingle sets at t or more, and each copy of a set beside the set's least id.

    Copies become one node first, so that a group of them costs a row each. Sets are then listed by their first shingles
    only: in one order of all shingles, two sets at t or more share one of their first n - ceil(t n) + 1. The order puts
    shingles that are common in a sample last; any order gives the same result, this one keeps lists short. Sizes and parity
    sketches are compared before anything is verified; verification intersects whole sets. No pair is missed at any size.
    """
    lines = _line(docs, id_col)
    common, counts = _order(lines, ngram)

    def row(found: np.ndarray) -> tuple:
        n, rank = len(found), np.zeros(len(found), np.int64)
        if len(common):
            at = np.minimum(np.searchsorted(common, found), len(common) - 1)
            rank = np.where(common[at] == found, counts[at], 0)
        first = found[np.lexsort((found, rank))[: n - math.ceil(n * t) + 1]]
        return xxhash.xxh3_128_digest(found.tobytes()), n, first.astype(">i8").view(np.uint8).reshape(-1, 8)[:, :NAME].tobytes(), setjoin.sketch(found)

    sets = cut(_map_sets(lines, ngram, row, pa.schema([("same", pa.binary()), ("n", pa.int64()), ("names", pa.binary()), ("sketch", pa.binary())])))
    equal = sets.groupBy("same").agg(F.min("id").alias("src"), F.count("*").alias("of")).where("of > 1")
    copies = cut(sets.select("id", "same").join(equal, "same").where("id <> src").select("src", F.col("id").alias("dst")))
    lost = copies.select(F.col("dst").alias("id"))
    nodes = sets.join(F.broadcast(lost) if lost.count() <= setjoin.IDS else lost, "id", "left_anti")
    pairs = setjoin.met(nodes, _named, t)
    beside = lambda members: nodes.select("id", "n", F.col("sketch").alias("found")).join(members, "id")
    pairs = cut(setjoin.settle(pairs, beside, setjoin.by_sketch(t), "src long, dst long"))
    whole = lambda members: _map_sets(setjoin.of_members(lines, members), ngram, lambda s: (len(s), s.tobytes()), pa.schema([("n", pa.int64()), ("found", pa.binary())]), "cells array<bigint>")
    similarity = F.col("both") / (F.col("n1") + F.col("n2") - F.col("both"))
    near = setjoin.settle(pairs, whole, setjoin.shared(np.int64), setjoin.SHARED).select("src", "dst", similarity.alias("similarity")).where(F.col("similarity") >= t)
    return near.unionByName(copies.withColumn("similarity", F.lit(1.0)))


def library_pairs(docs: DataFrame, t: float = 0.75, tables: int = 8, buckets: int = 1 << 18, id_col: str = "doc_id") -> DataFrame:
    """(src, dst): pairs of different shingle sets, each by its least id, that the library's MinHash join finds over t.

    Its hashes and its distance, which is of hashed shingles, decide; its join deals whole vectors out once a table and
    looks for repeated pairs of them. Here ids meet on a hash with a sketch of their vector, which says what can't be over
    t, and whole vectors are made again for those that are left.
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH
    from pyspark.ml.functions import vector_to_array

    # The condition is on the text, since one on the shingles would make them twice.
    grams_of = lambda rows, *keep: rows.where(F.col("text").rlike(r"[\p{L}\p{N}]")).select(*keep, shingles(F.col("text")).alias("grams"))
    docs = docs.select(F.col(id_col).cast("long").alias("id"), "text").where("id is not null")
    hashing = HashingTF(binary=True, inputCol="grams", outputCol="features", numFeatures=buckets)
    rows = hashing.transform(grams_of(docs, "id"))
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=7).fit(rows)
    hashes = F.concat(*(vector_to_array(F.col("hashes")[k]) for k in range(tables)))
    found = F.unwrap_udt("features")["indices"].alias("found")
    made = model.transform(rows).select("id", F.xxhash64(F.sort_array("grams")).alias("same"), F.transform(hashes, lambda h: h.cast("long")).alias("hashes"), found)
    ensure_importable(docs.sparkSession)

    def vectors(narrow: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                own = [x.values.to_numpy() for x in batch.column("found")]
                last = pa.array([setjoin.sketch(x) if narrow else x.astype(np.int32).tobytes() for x in own], pa.binary())
                kept = batch.drop_columns(["found"])
                yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(map(len, own), pa.int64()), last], names=[*kept.schema.names, "n", "sketch" if narrow else "found"])

        return run

    sets = cut(made.mapInArrow(vectors(True), "id bigint, same bigint, hashes array<bigint>, n bigint, sketch binary"))
    nodes = sets.join(sets.groupBy("same").agg(F.min("id").alias("id")).select("id"), "id", "left_semi").drop("same")
    each = F.explode(F.transform("hashes", lambda h, k: F.shiftleft(k.cast("long"), 32) + h)).alias("key")  # hashes are below 2^31
    pairs = setjoin.met(cut(nodes), lambda some: some.select(each, "id", "n", "sketch"), t)
    whole = lambda members: hashing.transform(grams_of(setjoin.of_members(docs, members), "id", "cells")).select("id", "cells", found).mapInArrow(vectors(False), "id bigint, cells array<bigint>, n bigint, found binary")
    return setjoin.settle(pairs, whole, setjoin.shared(np.int32), setjoin.SHARED).where(1 - F.col("both") / (F.col("n1") + F.col("n2") - F.col("both")) < 1 - t).select("src", "dst")


PREFER = {
    "latest": lambda: F.struct(-F.datediff("snapshot_date", F.lit("1970-01-01").cast("date")), F.col("rec_id")),
    "earliest": lambda: F.struct(F.datediff("snapshot_date", F.lit("1970-01-01").cast("date")), F.col("rec_id")),
    "longest": lambda: F.struct(-F.col("n_text"), F.col("rec_id")),
}


def content(docs: DataFrame, scope: str = "snapshot", keep: str = "latest", ngram: int = 5, n_bands: int = 14, rows: int = 8, family: str = "xxhash64", pairing: str = "sliding", sigs: DataFrame | None = None) -> DataFrame:
    """(rec_id, component, kept) for rows (rec_id, text, snapshot_id, snapshot_date).

    scope: within each snapshot, between neighbouring snapshots (sliding or disjoint pairs; records of one snapshot meet
    too), or global. A component keeps its preferred record. sigs, where given, are reused: (rec_id, snapshot_id, snapshot_date, n_text, sig).
    """
    if sigs is None:
        sigs = sign_for_content(docs, ngram, n_bands * rows, family)
    extra = ("snapshot_id", "snapshot_date", "n_text")
    banded = bands(sigs, n_bands, rows, "rec_id", extra)
    cols: tuple[str, ...] = ()
    if scope == "snapshot":
        cols = ("snapshot_id",)
    elif scope == "neighbor":
        cols = ("pair_id",)
        pair = F.explode(F.array(F.col("snapshot_id") - 1, F.col("snapshot_id"))) if pairing == "sliding" else F.floor(F.col("snapshot_id") / 2).cast("int")
        banded = banded.withColumn("pair_id", pair)
    elif scope != "global":
        raise ValueError(scope)
    edges = star_edges(banded, PREFER[keep](), "rec_id", cols)
    found = components(edges)
    named = sigs.select("rec_id", *extra).join(found, F.col("rec_id") == F.col("node"), "left").withColumn("component", F.coalesce("component", "rec_id"))
    best = named.groupBy("component").agg(F.min_by("rec_id", PREFER[keep]()).alias("best"))
    out = named.join(best, "component").select("rec_id", "component", (F.col("rec_id") == F.col("best")).alias("kept"))
    # Texts without words have no signature and stay.
    return docs.select("rec_id").join(out, "rec_id", "left").select("rec_id", F.coalesce("component", "rec_id").alias("component"), F.coalesce("kept", F.lit(True)).alias("kept"))


def sign_for_content(docs: DataFrame, ngram: int, hashes: int, family: str) -> DataFrame:
    return cut(signature(docs.withColumn("n_text", F.length("text")), "rec_id", ngram, hashes, family, keep=("snapshot_id", "snapshot_date", "n_text")))


def content_two_step(docs: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """Kept record ids after both steps, and the ledger (stage, n_in, n_out). Signatures are computed once."""
    n_bands, rows = options.get("n_bands", 14), options.get("rows", 8)
    sigs = sign_for_content(docs, options.get("ngram", 5), n_bands * rows, options.get("family", "xxhash64"))
    first = cut(content(docs, "snapshot", sigs=sigs, **options))
    left = docs.join(first.where("kept").select("rec_id"), "rec_id", "left_semi")
    second = cut(content(left, "neighbor", sigs=sigs.join(first.where("kept").select("rec_id"), "rec_id", "left_semi"), **options))
    count = lambda df, n, stage: df.agg(F.lit(n).alias("step"), F.lit(stage).alias("stage"), F.count("*").alias("n_in"), F.sum(F.col("kept").cast("long")).alias("n_out"))
    return second.where("kept").select("rec_id"), count(first, 1, "within_snapshot").unionByName(count(second, 2, "neighbor_snapshots"))


def bucket_representative(banded: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Ids that some bucket holds beside a smaller one: what one pass removes, always fewer than components do."""
    low = banded.groupBy("band", "key").agg(F.min(id_col).alias("low"), F.count("*").alias("n")).where("n > 1")
    return banded.join(low, ["band", "key"]).where(F.col(id_col) > F.col("low")).select(id_col).distinct()


def exact(docs: DataFrame, key: Column, id_col: str = "doc_id") -> DataFrame:
    """(id, keep_id, kept) by equality of a normalised text's digest; the largest id stays."""
    hashed = docs.select(id_col, F.sha2(key, 256).alias("__h"))
    best = hashed.groupBy("__h").agg(F.max(id_col).alias("keep_id"))
    return hashed.join(best, "__h").select(id_col, "keep_id", (F.col(id_col) == F.col("keep_id")).alias("kept"))


def normalised(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def canonical_url(url: Column) -> Column:
    """Scheme, leading www. or m., query and fragment away: a coarser key than the exact one."""
    return F.regexp_replace(F.regexp_replace(url, r"[?#].*$", ""), r"^https?://(?:www\.|m\.)?", "")


def url(pages: DataFrame, scope: str = "year", keep: str = "latest", key: str = "exact", method: str = "max_by") -> DataFrame:
    """Kept rows' rec_id: of equal URLs in one scope the newest (or oldest) snapshot's, ties to the smallest rec_id.

    max_by aggregates narrow rows before the shuffle; window sorts and is the reference form. Null URLs are never equal.
    """
    k = F.col("url") if key == "exact" else canonical_url(F.col("url"))
    cols = {"year": ["year"], "snapshot": ["snapshot_id"], "global": []}[scope]
    rows = pages.select("rec_id", *cols, "snapshot_date", F.coalesce(k, F.concat(F.lit("\u0000"), F.col("rec_id").cast("string"))).alias("__k"))
    if method == "window":
        order = F.col("snapshot_date").desc() if keep == "latest" else F.col("snapshot_date").asc()
        return rows.withColumn("__n", F.row_number().over(W.partitionBy(*cols, "__k").orderBy(order, "rec_id"))).where("__n = 1").select("rec_id")
    day = F.datediff("snapshot_date", F.lit("1970-01-01").cast("date"))
    return rows.groupBy(*cols, "__k").agg(F.max_by("rec_id", F.struct(day if keep == "latest" else -day, -F.col("rec_id"))).alias("rec_id")).select("rec_id")


def signature_sql(source: str, id_col: str, hashes: int, ngram: int = 5, extra: str = "") -> str:
    """CTEs w, s, x, sig in DuckDB SQL: the affine signatures of a table, for checks."""
    family = ", ".join(f"({k}, {a}, {b})" for k, (a, b) in enumerate(affine_family(hashes)))
    return rf"""
        w AS (SELECT {id_col}{extra}, list_filter(string_split(regexp_replace(lower(text), '[^\p{{L}}\p{{N}}]+', ' ', 'g'), ' '), lambda v: v <> '') AS p FROM {source}),
        s AS (SELECT {id_col}{extra}, list_distinct(list_transform(range(1, greatest(len(p) - {ngram - 1}, 1) + 1), lambda i: array_to_string(p[i : i + {ngram - 1}], ' '))) AS g FROM w WHERE len(p) > 0),
        fam(k, a, b) AS (VALUES {family}),
        x AS (SELECT DISTINCT {id_col}{extra}, {H28.format('g')} AS x FROM (SELECT {id_col}{extra}, unnest(g) AS g FROM s)),
        sig AS (SELECT {id_col}{extra}, k, min((a * x + b) % {PRIME}) AS m FROM x, fam GROUP BY ALL)"""


def bands_sql(id_col: str, rows: int, extra: str = "") -> str:
    """CTE bands in DuckDB SQL, after signature_sql."""
    return f"""
        bands AS (SELECT {id_col}{extra}, k // {rows} AS band, md5((k // {rows}) || ':' || string_agg(m::VARCHAR, ',' ORDER BY k)) AS key FROM sig GROUP BY {id_col}{extra}, k // {rows})"""


def closure_sql(edges: str, mark: str = "") -> str:
    """CTE comp(node, component): the least node reachable, in DuckDB SQL, for small graphs. mark tells several apart."""
    return f"""
        both_ways{mark} AS (SELECT src AS a, dst AS b FROM {edges} UNION SELECT dst, src FROM {edges}),
        reach{mark} AS (SELECT a, b FROM both_ways{mark} UNION SELECT r.a, e.b FROM reach{mark} r JOIN both_ways{mark} e ON r.b = e.a),
        comp{mark} AS (SELECT a AS node, least(a, min(b)) AS component FROM reach{mark} GROUP BY a)"""


def merge_signatures(sigs: DataFrame, by: str, hashes: int) -> DataFrame:
    """(by, sig): signatures of the unions of the groups' shingle sets, element-wise minima; mergeable for incremental crawls."""
    mins = [F.min(F.get("sig", F.lit(k))).alias(f"m{k}") for k in range(hashes)]
    return sigs.groupBy(by).agg(*mins).select(by, F.array(*(f"m{k}" for k in range(hashes))).alias("sig"))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
