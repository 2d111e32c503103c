"""Queries of interleaved documents, image selection, and training-side operators."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusloom.operators import extract, images, interleave, sampling, training
from corpusloom.operators.dedup import union_all
from corpusloom.plans.registry import query
from corpusloom.runtime import cut, table, texts
from corpusloom.sources.views import H28, REFS_STAR, REFS_WEB, image_refs_star, image_refs_web

#: Caps that bite on the given tables; the operators' defaults are 10 and 100.
CAP, CROWD = 30, 10
_PATTERN = '<a href="[^"]*"|<p>[^<]+'
TERMS = (*images.TERMS, "casino", "pills")


def _segments(spark, sf):
    """Paragraphs and links of pages in order, links standing in for images."""
    hits = F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit(_PATTERN), F.lit(0))
    kind = lambda h, k: F.struct(
        k.cast("int").alias("pos"), F.when(h.startswith("<a"), "image").otherwise("text").alias("kind"),
        F.when(~h.startswith("<a"), F.regexp_replace(h, "^<p>", "")).alias("text"), F.when(h.startswith("<a"), F.regexp_extract(h, '"([^"]*)"', 1)).alias("image_url"),
    )
    return texts(spark, sf, "pages").select(F.col("page_id").alias("doc_id"), F.transform(hits, kind).alias("segments"))


def _md5(places):
    """The digest of a list's places; a page without any has one empty place, as SQL's outer join gives it."""
    return F.md5(F.array_join(F.when(F.size(places) > 0, F.col(places)).otherwise(F.array(F.lit("~"))), "|", "~").cast("binary"))


_SEG = f"""seg AS (SELECT doc_id, pos, CASE WHEN h LIKE '<a%' THEN NULL ELSE regexp_replace(h, '^<p>', '') END AS text, CASE WHEN h LIKE '<a%' THEN regexp_extract(h, '"([^"]*)"', 1) END AS image_url
    FROM (SELECT page_id AS doc_id, unnest(l) AS h, generate_subscripts(l, 1) AS pos FROM (SELECT page_id, regexp_extract_all(html, '{_PATTERN}') AS l FROM pages)))"""


@query("m28_parallel_lists", f"WITH {_SEG} SELECT page_id AS doc_id, count(pos) AS n, count(image_url) AS n_images, md5(coalesce(string_agg(coalesce(text, '~'), '|' ORDER BY pos), '')) AS texts_md5, md5(coalesce(string_agg(coalesce(image_url, '~'), '|' ORDER BY pos), '')) AS images_md5 FROM pages LEFT JOIN seg ON doc_id = page_id GROUP BY page_id")
def m28(spark, sf):
    d = interleave.to_parallel_lists(_segments(spark, sf))
    return d.select("doc_id", F.size("texts").cast("long").alias("n"), interleave.n_images(F.col("images")).cast("long").alias("n_images"), _md5("texts").alias("texts_md5"), _md5("images").alias("images_md5"))


@query("m28_roundtrip", "SELECT count(*) AS docs, count(*) AS same FROM pages")
def m28_roundtrip(spark, sf):
    s = _segments(spark, sf)
    back = interleave.from_parallel_lists(interleave.to_parallel_lists(s)).select("doc_id", F.col("segments").alias("again"))
    return s.join(back, "doc_id").agg(F.count("*").alias("docs"), F.sum((F.col("segments") == F.col("again")).cast("long")).alias("same"))


@query("m28_extracted_lists")
def m28_extracted(spark, sf):
    """The parser's segments as parallel lists."""
    d = interleave.to_parallel_lists(extract.interleaved(texts(spark, sf, "pages")))
    return d.select("page_id", F.size("texts").alias("n"), interleave.n_images(F.col("images")).alias("n_images"), F.md5(F.array_join("texts", "|", "~").cast("binary")).alias("texts_md5"))


@query("t08_text_only", f"WITH {_SEG} SELECT page_id AS doc_id, md5(coalesce(string_agg(text, chr(10) ORDER BY pos), '')) AS text_md5 FROM pages LEFT JOIN seg ON doc_id = page_id GROUP BY page_id")
def t08(spark, sf):
    return interleave.text_only(interleave.to_parallel_lists(_segments(spark, sf))).select("doc_id", F.md5(F.col("text").cast("binary")).alias("text_md5"))


def _both(name, run, sql):
    """A query over each of the two reference tables."""
    for source, refs, cte in (("web", image_refs_web, REFS_WEB), ("star", image_refs_star, REFS_STAR)):
        query(f"{name}_{source}", sql.format(refs=cte))(lambda spark, sf, refs=refs: run(refs(spark, sf)))


_both("m29_unique_images", images.unique, "WITH {refs} SELECT DISTINCT image_url FROM refs")
_both("m30_image_frequency_cap", lambda r: images.frequency_cap(r, CAP), f"WITH {{refs}} SELECT image_url FROM refs GROUP BY image_url HAVING count(DISTINCT doc_id) <= {CAP}")
_both("m30_image_occurrence_cap", lambda r: images.frequency_cap(r, CAP, "occurrences"), f"WITH {{refs}} SELECT image_url FROM refs GROUP BY image_url HAVING count(*) <= {CAP}")
for _mode, _agg in (("any", "max"), ("all", "min")):
    _both(f"m31_crowded_doc_cap_{_mode}", lambda r, m=_mode: images.crowded_doc_cap(r, CROWD, m), f"WITH {{refs}} SELECT image_url FROM (SELECT image_url, count(*) OVER (PARTITION BY doc_id) AS n FROM refs) GROUP BY image_url HAVING {_agg}(n) <= {CROWD}")
_both("m32_string_rules", lambda r: images.string_rules(images.unique(r), terms=TERMS), f"WITH {{refs}} SELECT DISTINCT image_url FROM refs WHERE image_url LIKE 'https%' AND NOT regexp_matches(lower(image_url), '{'|'.join(TERMS)}')")
_both("m33_fetch_manifest", lambda r: images.manifest(images.unique(r)), f"WITH {{refs}} SELECT image_url, {H28.format('image_url')} % 100 < 64 AS ok FROM (SELECT DISTINCT image_url FROM refs)")
_FLAGS = f"""n AS (SELECT *, count(*) OVER (PARTITION BY doc_id) AS n FROM refs), f AS (SELECT image_url, count(DISTINCT doc_id) <= {CAP} AND max(n) <= {CROWD} AS in_caps FROM n GROUP BY image_url),
    g AS (SELECT *, in_caps AND image_url LIKE 'https%' AND NOT regexp_matches(lower(image_url), '{'|'.join(TERMS)}') AS in_rules FROM f), ok AS (SELECT image_url FROM g WHERE in_rules AND {H28.format('image_url')} % 100 < 64)"""
_both("m35_image_funnel", lambda r: images.ledger(r, CAP, CROWD, TERMS), f"WITH {{refs}}, {_FLAGS} SELECT (SELECT count(*) FROM refs) AS occurrences, (SELECT count(*) FROM g) AS unique_urls, (SELECT count(*) FROM g WHERE in_caps) AS after_caps, (SELECT count(*) FROM g WHERE in_rules) AS after_rules, (SELECT count(*) FROM ok) AS fetched, (SELECT count(*) FROM refs WHERE image_url IN (SELECT image_url FROM ok)) AS placements")


@query("e11_download_rate", f"WITH {REFS_STAR}, u AS (SELECT DISTINCT image_url FROM refs) SELECT count(*) AS attempted, count(*) FILTER ({H28.format('image_url')} % 100 < 64) AS fetched, round(count(*) FILTER ({H28.format('image_url')} % 100 < 64) / count(*), 6) AS rate FROM u")
def e11(spark, sf):
    m = images.manifest(images.unique(image_refs_star(spark, sf)))
    n = F.sum(F.col("ok").cast("long"))
    return m.agg(F.count("*").alias("attempted"), n.alias("fetched"), F.round(n / F.count("*"), 6).alias("rate"))


@query("m33_fetch_interface", f"WITH {REFS_WEB}, u AS (SELECT image_url, list_sum(list_transform(string_split(image_url, ''), lambda c: ord(c))) AS n FROM (SELECT DISTINCT image_url FROM refs)) SELECT image_url, CASE WHEN n % 5 = 0 THEN 'TimeoutError' WHEN n % 3 = 0 THEN 'failed' ELSE 'ok' END AS status, CASE WHEN n % 5 <> 0 AND n % 3 <> 0 THEN sha256(image_url) END AS sha256 FROM u")
def m33_fetch(spark, sf):
    """The fetcher's interface with one that makes bytes of the URL, fails for every third and raises for every fifth."""

    def fetcher(url):
        n = sum(map(ord, url))
        if n % 5 == 0:
            raise TimeoutError
        return url.encode() if n % 3 else None

    return images.fetch(images.unique(image_refs_web(spark, sf)), fetcher, tasks=8).select("image_url", "status", "sha256")


_SMD5 = "md5(coalesce(string_agg(coalesce(image_url, '~'), '|' ORDER BY pos), ''))"


@query("m34_reattach", f"WITH {_SEG}, kept AS (SELECT * FROM seg WHERE image_url IS NULL OR {H28.format('image_url')} % 100 < 64) SELECT page_id AS doc_id, count(pos) AS n, count(image_url) AS n_images, {_SMD5} AS images_md5 FROM pages LEFT JOIN kept ON doc_id = page_id GROUP BY page_id")
def m34(spark, sf):
    d = interleave.to_parallel_lists(_segments(spark, sf))
    urls = d.select(F.explode(F.array_compact("images")).alias("image_url")).distinct()
    out = interleave.reattach(d, images.manifest(urls).where("ok"))
    return out.select("doc_id", F.size("texts").cast("long").alias("n"), interleave.n_images(F.col("images")).cast("long").alias("n_images"), _md5("images").alias("images_md5"))


@query("m34_reattach_null", f"WITH {_SEG}, kept AS (SELECT doc_id, pos, text, CASE WHEN {H28.format('image_url')} % 100 < 64 THEN image_url END AS image_url FROM seg) SELECT page_id AS doc_id, count(pos) AS n, count(image_url) AS n_images, {_SMD5} AS images_md5 FROM pages LEFT JOIN kept ON doc_id = page_id GROUP BY page_id")
def m34_null(spark, sf):
    d = interleave.to_parallel_lists(_segments(spark, sf))
    urls = d.select(F.explode(F.array_compact("images")).alias("image_url")).distinct()
    out = interleave.reattach(d, images.manifest(urls).where("ok"), missing="null")
    return out.select("doc_id", F.size("texts").cast("long").alias("n"), interleave.n_images(F.col("images")).cast("long").alias("n_images"), _md5("images").alias("images_md5"))


@query("t01_stage_plan", "SELECT stage, name, max_lr, min_lr, warmup, CAST(CASE stage WHEN 1 THEN (SELECT sum(len(regexp_extract_all(html, '<a href='))) FROM pages) WHEN 2 THEN (SELECT sum((n_chars + 4095) // 4096) FROM documents) ELSE (SELECT count(DISTINCT conv_id) FROM conversations) END AS BIGINT) AS examples FROM (VALUES (1, 'alignment', 0.0001::DOUBLE, 0::DOUBLE, 0), (2, 'continued_pretraining', 0.00005::DOUBLE, 0::DOUBLE, 0), (3, 'instruction_tuning', 0.000005::DOUBLE, 0.0000005::DOUBLE, 2000)) t(stage, name, max_lr, min_lr, warmup)")
def t01(spark, sf):
    """The stages with the examples that the given tables hold for each: links with their pages, contexts of documents (a token a character), conversations."""
    counts = union_all([
        texts(spark, sf, "pages").agg(F.lit(1).alias("stage"), F.sum(F.regexp_count("html", F.lit("<a href="))).cast("long").alias("examples")),
        table(spark, sf, "documents").agg(F.lit(2).alias("stage"), F.sum(F.floor((F.col("n_chars") + (training.CONTEXT - 1)) / training.CONTEXT)).cast("long").alias("examples")),
        table(spark, sf, "conversations").agg(F.lit(3).alias("stage"), F.countDistinct("conv_id").alias("examples")),
    ])
    return training.stage_plan(spark).join(counts, "stage").select("stage", "name", "max_lr", "min_lr", "warmup", "examples")


@query("t02_lr_schedule", "SELECT stage, step, round(CASE WHEN step < w THEN top * step / greatest(w, 1) ELSE low + (top - low) / 2 * (1 + cos(pi() * (step - w) / greatest(20000 - w, 1))) END * 1e6, 6) AS lr_millionths FROM (SELECT i * 1000 AS step FROM range(21) t(i)), (VALUES (1, 1e-4::DOUBLE, 0::DOUBLE, 0), (2, 5e-5::DOUBLE, 0::DOUBLE, 0), (3, 5e-6::DOUBLE, 5e-7::DOUBLE, 2000)) v(stage, top, low, w)")
def t02(spark, sf):
    s = spark.range(21).select((F.col("id") * 1000).alias("step"))
    return union_all([s.select(F.lit(k).alias("stage"), "step", F.round(training.learning_rate(F.col("step"), F.lit(20000), x[3], x[4], x[5]) * 1e6, 6).alias("lr_millionths")) for k, x in enumerate(training.STAGES, 1)])


@query("t03_exact_k", "SELECT vec_id FROM embeddings ORDER BY md5(vec_id::VARCHAR), vec_id LIMIT 200")
def t03(spark, sf):
    return sampling.exact_k(table(spark, sf, "embeddings").select("vec_id"), 200, "vec_id")


def _sizes(spark, sf):
    docs = texts(spark, sf, "documents").select("doc_id", F.size(F.filter(F.split("text", "[ \t\r\n]+"), lambda w: w != "")).cast("long").alias("n_tokens"))
    refs = image_refs_web(spark, sf).groupBy("doc_id").agg(F.count("*").alias("n_images"))
    return docs.join(refs, "doc_id", "left").select("doc_id", "n_tokens", F.coalesce("n_images", F.lit(0)).alias("n_images"))


_SIZES = REFS_WEB + ", i AS (SELECT doc_id, count(*) AS n FROM refs GROUP BY doc_id), w AS (SELECT d.doc_id, len(list_filter(regexp_split_to_array(text, '[ \\t\\r\\n]+'), lambda x: x <> '')) + 64 * coalesce(i.n, 0) AS w FROM documents d LEFT JOIN i ON i.doc_id = d.doc_id)"


@query("t04_packing", f"""WITH {_SIZES}, c AS (SELECT *, CAST(sum(w) OVER (PARTITION BY grp ORDER BY doc_id) AS BIGINT) AS e FROM (SELECT *, {H28.format('doc_id::VARCHAR')} % (SELECT (count(*) + 65535) // 65536 FROM documents) AS grp FROM w) WHERE w > 0)
    SELECT doc_id, CAST(grp AS INTEGER) AS grp, example, greatest(e - w, example * 4096) - (e - w) AS from_token, least(e, (example + 1) * 4096) - greatest(e - w, example * 4096) AS n FROM (SELECT *, unnest(range((e - w) // 4096, (e - 1) // 4096 + 1)) AS example FROM c)""")
def t04(spark, sf):
    return training.pack_parallel(_sizes(spark, sf))


@query("t04_packing_greedy")
def t04_greedy(spark, sf):
    return training.pack_greedy(_sizes(spark, sf))


@query("t05_visual_budget", f"WITH {_SIZES} SELECT count(*) AS docs, CAST(sum(64 * coalesce(i.n, 0)) AS BIGINT) AS visual_tokens, CAST(sum(w.w - 64 * coalesce(i.n, 0)) AS BIGINT) AS text_tokens FROM w LEFT JOIN i USING (doc_id)")
def t05(spark, sf):
    return _sizes(spark, sf).agg(F.count("*").alias("docs"), F.sum(training.visual_tokens(F.col("n_images"))).alias("visual_tokens"), F.sum("n_tokens").alias("text_tokens"))


@query("t06_mixture", f"SELECT name AS mixture_source, count(DISTINCT conv_id) AS convs, count(*) AS turns FROM conversations JOIN (VALUES (0, 'family_0', 1000), (1, 'family_1', 500), (2, 'other_0', 250)) v(k, name, cut) ON conv_id % 5 = k WHERE {H28.format('conv_id::VARCHAR')} % 1000 < cut GROUP BY name")
def t06(spark, sf):
    c = table(spark, sf, "conversations").select("conv_id", "turn")
    own = lambda k: c.where(F.col("conv_id") % 5 == k)
    mixed = training.compose({"family_0": (own(0), 1.0), "family_1": (own(1), 0.5), "other_0": (own(2), 0.25)}, "conv_id")
    return mixed.groupBy("mixture_source").agg(F.countDistinct("conv_id").alias("convs"), F.count("*").alias("turns"))


@query("t06_mixture_sets", "SELECT * FROM (VALUES ('narrow', 5), ('extended', 14), ('training', 16)) t(mixture, sources)")
def t06_sets(spark, sf):
    return spark.createDataFrame([("narrow", len(training.NARROW)), ("extended", len(training.EXTENDED)), ("training", len(training.TRAINING + training.TRAINING_TEXT))], "mixture string, sources int")


@query("t07_chat", "SELECT conv_id, count(*) AS n_turns, md5(string_agg('<|' || role || '|>' || chr(10) || text, chr(10) ORDER BY turn)) AS chat_md5 FROM conversations GROUP BY conv_id")
def t07(spark, sf):
    return training.render_chat(table(spark, sf, "conversations")).select("conv_id", "n_turns", F.md5(F.col("chat").cast("binary")).alias("chat_md5"))


@query("w11_alignment_sample", "SELECT label, count(*) AS n FROM (SELECT label FROM embeddings ORDER BY md5(vec_id::VARCHAR), vec_id LIMIT 200) GROUP BY label")
def w11(spark, sf):
    return cut(sampling.exact_k(table(spark, sf, "embeddings").select("vec_id", "label"), 200, "vec_id")).groupBy("label").agg(F.count("*").alias("n"))


@query("w10_image_path")
def w10(spark, sf):
    """Selection, stand-in fetching and re-attachment in one, then the corpus's size."""
    from corpusloom.plans.pipeline import corpus_stats

    return corpus_stats(images.pipeline(interleave.to_parallel_lists(_segments(spark, sf)), CAP, CROWD, TERMS))
