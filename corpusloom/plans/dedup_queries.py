"""Deduplication queries: MinHash in its scopes, URLs, exact copies."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusloom.operators import dedup
from corpusloom.operators.graph import components
from corpusloom.plans.registry import query
from corpusloom.runtime import cut, table, texts
from corpusloom.sources.views import CRAWL, DOC_CRAWL, crawl, doc_crawl

H, B, R = 112, 14, 8  # the operators' defaults
OPTIONS = {"n_bands": B, "rows": R, "family": "affine31"}
DOCS = dedup.signature_sql("documents", "doc_id", H) + "," + dedup.bands_sql("doc_id", R)
EDGES = "star AS (SELECT min(doc_id) AS src, band, key FROM bands GROUP BY band, key HAVING count(*) > 1), edges AS (SELECT DISTINCT s.src, b.doc_id AS dst FROM bands b JOIN star s USING (band, key) WHERE b.doc_id <> s.src)"
JACCARD = """pairs AS (SELECT src, dst, len(list_intersect(a.g, b.g)) / (len(a.g) + len(b.g) - len(list_intersect(a.g, b.g))) AS similarity
        FROM edges JOIN s a ON a.doc_id = src JOIN s b ON b.doc_id = dst)"""


def _sigs(spark, sf):
    return dedup.signature(texts(spark, sf, "documents"), hashes=H, family="affine31")


def _edges(spark, sf):
    return dedup.star_edges(dedup.bands(_sigs(spark, sf), B, R), F.col("doc_id"))


@query("m07_signature_affine", f"WITH {dedup.signature_sql('documents', 'doc_id', H)} SELECT doc_id, string_agg(m::VARCHAR, ',' ORDER BY k) AS sig FROM sig GROUP BY doc_id")
def m07(spark, sf):
    return _sigs(spark, sf).select("doc_id", F.array_join(F.transform("sig", lambda x: x.cast("string")), ",").alias("sig"))


@query("m07_signature_xxhash64")
def m07b(spark, sf):
    return dedup.signature(texts(spark, sf, "documents"), hashes=H).select("doc_id", F.array_join(F.transform("sig", lambda x: x.cast("string")), ",").alias("sig"))


@query("m07_union_by_lang", f"WITH {dedup.signature_sql('documents', 'doc_id', H)} SELECT lang, string_agg(m::VARCHAR, ',' ORDER BY k) AS sig FROM (SELECT lang, k, min(m) AS m FROM sig JOIN documents USING (doc_id) GROUP BY lang, k) GROUP BY lang")
def m07_union(spark, sf):
    sigs = dedup.signature(texts(spark, sf, "documents"), hashes=H, family="affine31", keep=("lang",))
    return dedup.merge_signatures(sigs, "lang", H).select("lang", F.array_join(F.transform("sig", lambda x: x.cast("string")), ",").alias("sig"))


@query(
    "m07b_char_shingles",
    r"SELECT doc_id, len(list_distinct(list_transform(range(1, greatest(length(t) - 4, 1) + 1), lambda i: t[i : i + 4]))) AS shingles FROM (SELECT doc_id, regexp_replace(lower(text), '[^\p{L}\p{N}]+', '', 'g') AS t FROM documents) WHERE t <> ''",
)
def m07b_chars(spark, sf):
    """Shingles of characters, for texts written without spaces."""
    n = F.size(dedup.shingles(F.col("text"), 5, "char"))
    return texts(spark, sf, "documents").select("doc_id", n.cast("long").alias("shingles")).where("shingles > 0")


@query("m07b_signature_auto")
def m07b_auto(spark, sf):
    """Signatures whose unit is chosen by each text's script."""
    return dedup.signature(texts(spark, sf, "documents"), unit="auto").select("doc_id", F.array_join(F.transform("sig", lambda x: x.cast("string")), ",").alias("sig"))


@query("m08_library_cross_check")
def m08_library(spark, sf):
    """Pairs that the library's MinHash join finds at 0.75 among different shingle sets, and how many of all pairs these are."""
    found = dedup.library_pairs(texts(spark, sf, "documents"))
    truth = dedup.exact_pairs(texts(spark, sf, "documents")).where("similarity < 1").select("src", "dst")
    both = found.withColumn("f", F.lit(1)).join(truth.withColumn("t", F.lit(1)), ["src", "dst"], "full")
    return both.agg(F.count("t").alias("pairs"), F.count("f").alias("found"), F.sum((F.col("t") == F.col("f")).cast("long")).alias("both"))


@query("m08_candidate_pairs", f"WITH {DOCS}, {EDGES} SELECT src, dst FROM edges")
def m08(spark, sf):
    return _edges(spark, sf)


@query("m08_collision_curve", "SELECT s, b, r, round(1 - pow(1 - pow(s, r), b), 6) AS p FROM (SELECT DISTINCT CAST(l_quantity AS DOUBLE) / 50 AS s FROM lineitem WHERE l_quantity BETWEEN 0 AND 50), (VALUES (14, 8), (16, 4), (8, 2)) v(b, r)")
def m08_curve(spark, sf):
    """The curve at the shares that a column of the given tables takes."""
    share = table(spark, sf, "lineitem").where("l_quantity BETWEEN 0 AND 50").select((F.col("l_quantity").cast("double") / 50).alias("s")).distinct()
    v = F.explode(F.array(*(F.struct(F.lit(b).alias("b"), F.lit(r).alias("r")) for b, r in ((14, 8), (16, 4), (8, 2)))))
    return share.select("s", v.alias("v")).select("s", "v.b", "v.r", F.round(1 - F.pow(1 - F.pow(F.col("s"), F.col("v.r")), F.col("v.b")), 6).alias("p"))


def _scope_sql(scope: str) -> str:
    if scope == "snapshot":
        scoped, key = "scoped AS (SELECT *, snapshot_id AS scope FROM bands)", "scope, band, key"
    elif scope == "neighbor":
        scoped, key = "scoped AS (SELECT *, unnest([snapshot_id - 1, snapshot_id]) AS scope FROM bands)", "scope, band, key"
    elif scope == "disjoint":
        scoped, key = "scoped AS (SELECT *, snapshot_id // 2 AS scope FROM bands)", "scope, band, key"
    else:
        scoped, key = "scoped AS (SELECT *, 0 AS scope FROM bands)", "scope, band, key"
    extra = ", snapshot_id, snapshot_date"
    return f"""WITH RECURSIVE {DOC_CRAWL}, {dedup.signature_sql('doc_crawl', 'rec_id', H, extra=extra)}, {dedup.bands_sql('rec_id', R, extra)}, {scoped},
        star AS (SELECT arg_min(rec_id, (-(snapshot_date - DATE '1970-01-01'), rec_id)) AS src, {key} FROM scoped GROUP BY {key} HAVING count(*) > 1),
        edges AS (SELECT DISTINCT s.src, b.rec_id AS dst FROM scoped b JOIN star s USING ({key}) WHERE b.rec_id <> s.src), {dedup.closure_sql('edges')},
        named AS (SELECT d.rec_id, d.snapshot_date, coalesce(c.component, d.rec_id) AS component FROM doc_crawl d LEFT JOIN comp c ON c.node = d.rec_id)
        SELECT rec_id, component, rec_id = first_value(rec_id) OVER (PARTITION BY component ORDER BY snapshot_date DESC, rec_id) AS kept FROM named"""


def _scoped(scope):
    def run(spark, sf):
        return dedup.content(doc_crawl(spark, sf), scope, **OPTIONS)

    return run


for _name, _scope in (("m09_minhash_within_snapshot", "snapshot"), ("m10_minhash_neighbor", "neighbor"), ("m11_minhash_global", "global")):
    query(_name, _scope_sql(_scope))(_scoped(_scope))


@query("m10_minhash_neighbor_disjoint", _scope_sql("disjoint"))
def m10_disjoint(spark, sf):
    return dedup.content(doc_crawl(spark, sf), "neighbor", pairing="disjoint", **OPTIONS)


def _step_sql(mark: str, source: str, scope: str) -> str:
    """CTEs of one step over the bands of a set of records: kept{mark}(rec_id, kept)."""
    return f"""scoped{mark} AS (SELECT *, {scope} AS scope FROM bands WHERE rec_id IN (SELECT rec_id FROM {source})),
        star{mark} AS (SELECT arg_min(rec_id, (-(snapshot_date - DATE '1970-01-01'), rec_id)) AS src, scope, band, key FROM scoped{mark} GROUP BY scope, band, key HAVING count(*) > 1),
        edges{mark} AS (SELECT DISTINCT s.src, b.rec_id AS dst FROM scoped{mark} b JOIN star{mark} s USING (scope, band, key) WHERE b.rec_id <> s.src), {dedup.closure_sql('edges' + mark, mark)},
        kept{mark} AS (SELECT rec_id, rec_id = first_value(rec_id) OVER (PARTITION BY coalesce(component, rec_id) ORDER BY snapshot_date DESC, rec_id) AS kept
            FROM {source} d LEFT JOIN comp{mark} ON node = rec_id)"""


_EXTRA = ", snapshot_id, snapshot_date"
_TWO = f"""WITH RECURSIVE {DOC_CRAWL}, {dedup.signature_sql('doc_crawl', 'rec_id', H, extra=_EXTRA)}, {dedup.bands_sql('rec_id', R, _EXTRA)}, {_step_sql('1', 'doc_crawl', 'snapshot_id')},
        left1 AS (SELECT * FROM doc_crawl WHERE rec_id IN (SELECT rec_id FROM kept1 WHERE kept)), {_step_sql('2', 'left1', 'unnest([snapshot_id - 1, snapshot_id])')}"""


@query(
    "m12_two_step_ledger",
    _TWO + " SELECT 1 AS step, 'within_snapshot' AS stage, count(*) AS n_in, count(*) FILTER (kept) AS n_out, round(1 - count(*) FILTER (kept) / count(*), 6) AS removed_frac FROM kept1 UNION ALL SELECT 2, 'neighbor_snapshots', count(*), count(*) FILTER (kept), round(1 - count(*) FILTER (kept) / count(*), 6) FROM kept2",
)
def m12(spark, sf):
    ledger = dedup.content_two_step(doc_crawl(spark, sf), **OPTIONS)[1]
    return ledger.withColumn("removed_frac", F.round(1 - F.col("n_out") / F.col("n_in"), 6))


@query(
    "w17_scope_comparison",
    _TWO + f", {_step_sql('3', 'doc_crawl', '0')} SELECT 'snapshot' AS scope, count(*) AS n_in, count(*) FILTER (NOT kept) AS removed FROM kept1 UNION ALL SELECT 'global', count(*), count(*) FILTER (NOT kept) FROM kept3 UNION ALL SELECT 'two_step', (SELECT count(*) FROM doc_crawl), (SELECT count(*) FROM doc_crawl) - count(*) FILTER (kept) FROM kept2",
)
def w17(spark, sf):
    docs = cut(doc_crawl(spark, sf).select("rec_id", "text", "snapshot_id", "snapshot_date"))
    count = lambda df, name: df.agg(F.lit(name).alias("scope"), F.count("*").alias("n_in"), F.sum((~F.col("kept")).cast("long")).alias("removed"))
    both = [count(dedup.content(docs, s, **OPTIONS), s) for s in ("snapshot", "global")]
    kept = dedup.content_two_step(docs, **OPTIONS)[0].select("rec_id", F.lit(True).alias("kept"))
    return dedup.union_all([*both, count(docs.select("rec_id").join(kept, "rec_id", "left").select(F.coalesce("kept", F.lit(False)).alias("kept")), "two_step")])


@query("m13_verified_pairs", f"WITH {DOCS}, {EDGES}, {JACCARD} SELECT src, dst, round(similarity, 6) AS similarity FROM pairs WHERE similarity >= 0.75")
def m13(spark, sf):
    return dedup.verify(_edges(spark, sf), texts(spark, sf, "documents")).withColumn("similarity", F.round("similarity", 6))


@query(
    "m13_estimated_pairs",
    f"WITH {DOCS}, {EDGES} SELECT src, dst, sum(CAST(a.m = b.m AS INTEGER)) / {H}.0::DOUBLE AS similarity FROM edges JOIN sig a ON a.doc_id = src JOIN sig b ON b.doc_id = dst AND a.k = b.k GROUP BY src, dst HAVING sum(CAST(a.m = b.m AS INTEGER)) >= {H * 3 // 4}",
)
def m13b(spark, sf):
    return dedup.verify(_edges(spark, sf), texts(spark, sf, "documents"), "estimate", hashes=H, family="affine31")


@query("m14_components", f"WITH RECURSIVE {DOCS}, {EDGES}, {JACCARD}, good AS (SELECT src, dst FROM pairs WHERE similarity >= 0.75), {dedup.closure_sql('good')} SELECT node, component FROM comp")
def m14(spark, sf):
    return components(dedup.verify(_edges(spark, sf), texts(spark, sf, "documents")))


@query("m14b_bucket_representative", f"WITH {DOCS} SELECT DISTINCT doc_id FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY band, key) AS low FROM bands) WHERE doc_id > low")
def m14b(spark, sf):
    return dedup.bucket_representative(dedup.bands(_sigs(spark, sf), B, R))


_BEST = {"latest": "snapshot_date DESC, rec_id", "earliest": "snapshot_date, rec_id", "longest": "length(text) DESC, rec_id"}


@query(
    "m15_survivor_rules",
    _TWO + f", {_step_sql('3', 'doc_crawl', '0')}, named AS (SELECT d.*, coalesce(component, rec_id) AS component FROM doc_crawl d LEFT JOIN comp3 ON node = rec_id) "
    + " UNION ALL ".join(f"SELECT '{rule}' AS rule, count(*) AS kept, CAST(sum(rec_id) AS BIGINT) AS sum_rec_id FROM (SELECT rec_id FROM named QUALIFY row_number() OVER (PARTITION BY component ORDER BY {order}) = 1)" for rule, order in _BEST.items()),
)
def m15(spark, sf):
    docs = cut(doc_crawl(spark, sf).select("rec_id", "text", "snapshot_id", "snapshot_date"))
    return dedup.union_all([dedup.content(docs, "global", keep=k, **OPTIONS).where("kept").agg(F.lit(k).alias("rule"), F.count("*").alias("kept"), F.sum("rec_id").alias("sum_rec_id")) for k in dedup.PREFER])


@query(
    "m16_exact_dedup",
    r"SELECT doc_id, max(doc_id) OVER w AS keep_id, doc_id = max(doc_id) OVER w AS kept FROM documents WINDOW w AS (PARTITION BY trim(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g')))",
)
def m16(spark, sf):
    return dedup.exact(texts(spark, sf, "documents"), dedup.normalised(F.col("text")))


def _url_sql(part: str, key: str = "url") -> str:
    part = f"{part}, " if part else ""
    return f"WITH {CRAWL} SELECT rec_id FROM (SELECT rec_id, row_number() OVER (PARTITION BY {part}{key} ORDER BY snapshot_date DESC, rec_id) AS n FROM crawl) WHERE n = 1"


CANON = r"regexp_replace(regexp_replace(url, '[?#].*$', ''), '^https?://(?:www\.|m\.)?', '')"


@query("m17_url_dedup_year_latest", _url_sql("year"))
def m17(spark, sf):
    return dedup.url(crawl(spark, sf))


@query("m17a_url_dedup_window", _url_sql("year"))
def m17a(spark, sf):
    return dedup.url(crawl(spark, sf), method="window")


@query("m17b_url_dedup_canonical", _url_sql("year", CANON))
def m17b(spark, sf):
    return dedup.url(crawl(spark, sf), key="canonical")


@query(
    "m17c_scope_counts",
    f"WITH {CRAWL} SELECT 'snapshot' AS scope, count(*) AS kept FROM (SELECT DISTINCT snapshot_id, url FROM crawl) UNION ALL SELECT 'year', count(*) FROM (SELECT DISTINCT year, url FROM crawl) UNION ALL SELECT 'global', count(DISTINCT url) FROM crawl",
)
def m17c(spark, sf):
    return dedup.union_all([dedup.url(crawl(spark, sf), scope=s).agg(F.lit(s).alias("scope"), F.count("*").alias("kept")) for s in ("snapshot", "year", "global")])


_TRUTH = """k AS (SELECT doc_id, list_sort(g) AS g, min(doc_id) OVER (PARTITION BY list_sort(g)) AS rep FROM s),
        e AS (SELECT doc_id, unnest(g) AS x FROM k WHERE doc_id = rep), met AS (SELECT a.doc_id AS src, c.doc_id AS dst, count(*) AS n FROM e a JOIN e c ON a.x = c.x AND a.doc_id < c.doc_id GROUP BY 1, 2),
        truth AS (SELECT src, dst, round(n / (len(x.g) + len(y.g) - n), 6) AS similarity FROM met JOIN s x ON x.doc_id = src JOIN s y ON y.doc_id = dst WHERE n / (len(x.g) + len(y.g) - n) >= 0.75
        UNION ALL SELECT rep, doc_id, 1.0 FROM k WHERE doc_id <> rep)"""


@query(
    "b12_exact_pairs",
    f"""WITH {dedup.signature_sql('documents', 'doc_id', 1)}, {_TRUTH} SELECT src, dst, similarity FROM truth""",
)
def b12(spark, sf):
    """Pairs of different shingle sets at 0.75 or more, and each copy beside its set's least document."""
    return dedup.exact_pairs(texts(spark, sf, "documents")).withColumn("similarity", F.round("similarity", 6))


@query(
    "e13_dedup_quality",
    f"""WITH RECURSIVE {DOCS}, {EDGES}, {JACCARD}, {_TRUTH}, good AS (SELECT src, dst FROM pairs WHERE similarity >= 0.75), {dedup.closure_sql('truth', '1')}, {dedup.closure_sql('good', '2')}
        SELECT count(t.node) AS docs_linked_by_truth, count(g.node) AS docs_linked_by_bands, CAST(sum(CAST(t.component = g.component AS BIGINT)) AS BIGINT) AS docs_in_same_component, (SELECT count(*) FROM truth) AS true_pairs, (SELECT count(*) FROM edges) AS candidate_pairs
        FROM comp1 t FULL JOIN comp2 g ON t.node = g.node""",
)
def e13(spark, sf):
    """Pairs of the bands against all pairs, by components: what bands miss and what they add."""
    docs = texts(spark, sf, "documents")
    truth = cut(dedup.exact_pairs(docs).select("src", "dst"))
    found = cut(_edges(spark, sf).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))
    good = dedup.verify(found, docs).select("src", "dst")
    t, g = components(truth), components(good)
    joined = t.select("node", F.col("component").alias("t")).join(g.select("node", F.col("component").alias("g")), "node", "full")
    return joined.agg(
        F.count("t").alias("docs_linked_by_truth"), F.count("g").alias("docs_linked_by_bands"), F.sum((F.col("t") == F.col("g")).cast("long")).alias("docs_in_same_component"),
    ).crossJoin(truth.agg(F.count("*").alias("true_pairs"))).crossJoin(found.agg(F.count("*").alias("candidate_pairs")))
