"""Queries of measures, published tables, the whole funnel and corpus statistics."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusloom.operators import dedup, evaluate, extract, rules, textclf
from corpusloom.operators.dedup import union_all
from corpusloom.plans import baselines as B
from corpusloom.plans.curation import _PROMPT_SIZE, _RULES_SQL, _nb, _split
from corpusloom.plans.dedup_queries import _step_sql
from corpusloom.plans.registry import ORACLES, QUERIES, query
from corpusloom.runtime import cut, table, texts
from corpusloom.sources.views import CRAWL, H28, crawl, hash28


@query("e04_positive_accuracy", f"WITH {textclf.NB_SQL} SELECT count(*) AS items, round(avg(CAST(prob >= 0.5 AS DOUBLE)), 6) AS accuracy FROM nb JOIN lab USING (doc_id) WHERE y = 1")
def e04(spark, sf):
    scored, lab = _nb(spark, sf)
    return evaluate.positive_accuracy(scored.join(lab.where("y = 1"), "doc_id")).withColumn("accuracy", F.round("accuracy", 6))


@query("e04a_confusion", f"WITH {textclf.NB_SQL}, c AS (SELECT count(*) FILTER (prob >= 0.5 AND y = 1) AS tp, count(*) FILTER (prob >= 0.5 AND y = 0) AS fp, count(*) FILTER (prob < 0.5 AND y = 1) AS fn, count(*) FILTER (prob < 0.5 AND y = 0) AS tn FROM nb JOIN lab USING (doc_id) WHERE split = 'test') SELECT tp, fp, fn, tn, round((tp + tn) / (tp + fp + fn + tn), 6) AS accuracy, round(tp / nullif(tp + fp, 0), 6) AS precision, round(tp / nullif(tp + fn, 0), 6) AS recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) AS f1 FROM c")
def e04a(spark, sf):
    scored, lab = _nb(spark, sf)
    out = evaluate.confusion(scored.join(lab.where("split = 'test'"), "doc_id"))
    return out.withColumns({c: F.round(c, 6) for c in ("accuracy", "precision", "recall", "f1")})


@query("e04a_auc", f"WITH {textclf.NB_SQL}, b AS (SELECT floor(prob * 1000) AS bin, count(*) FILTER (y = 1) AS p, count(*) FILTER (y = 0) AS n FROM nb JOIN lab USING (doc_id) WHERE split = 'test' GROUP BY 1) SELECT round((SELECT sum(x.p * z.n * CASE WHEN z.bin = x.bin THEN 0.5 ELSE 1 END) FROM b x, b z WHERE z.bin <= x.bin) / ((SELECT sum(p) FROM b) * (SELECT sum(n) FROM b)), 6)::DOUBLE AS auc")
def e04a_auc(spark, sf):
    scored, lab = _nb(spark, sf)
    return evaluate.auc(scored.join(lab.where("split = 'test'"), "doc_id")).select(F.round("auc", 6).alias("auc"))


@query("e05_score_table", "WITH t AS (SELECT source AS corpus, 100 * avg(quality) AS a, 100 * (1 - avg(toxic)) AS b FROM documents JOIN labels USING (doc_id) GROUP BY source) SELECT corpus, round(a, 6) AS a, round(b, 6) AS b, round(a - max(CASE WHEN corpus = 'src0' THEN a END) OVER (), 4) AS gain_a, round(b - max(CASE WHEN corpus = 'src0' THEN b END) OVER (), 4) AS gain_b FROM t")
def e05(spark, sf):
    """Two scores of each source's labelled documents, and their gains over the base source."""
    d = table(spark, sf, "documents").select("doc_id", F.col("source").alias("corpus")).join(table(spark, sf, "labels"), "doc_id")
    t = d.groupBy("corpus").agg((100 * F.avg("quality")).alias("a"), (100 * (1 - F.avg("toxic"))).alias("b"))
    base = t.agg(F.max(F.when(F.col("corpus") == "src0", F.col("a"))).alias("a0"), F.max(F.when(F.col("corpus") == "src0", F.col("b"))).alias("b0"))
    return t.crossJoin(F.broadcast(base)).select("corpus", F.round("a", 6).alias("a"), F.round("b", 6).alias("b"), F.round(F.col("a") - F.col("a0"), 4).alias("gain_a"), F.round(F.col("b") - F.col("b0"), 4).alias("gain_b"))  # base is one row


_OUTCOMES = f"o AS (SELECT CASE WHEN conv_id % 2 = 0 THEN 'm0' ELSE 'm1' END AS model, conv_id % 5 AS category, {H28.format('conv_id::VARCHAR || chr(58) || turn')} % 100 < 40 AS correct FROM conversations WHERE role = 'assistant')"


@query("e06_split_accuracy", f"WITH {_OUTCOMES}, c AS (SELECT model, category, avg(CAST(correct AS DOUBLE)) AS a FROM o GROUP BY ALL) SELECT model, " + ", ".join(f"round(max(CASE WHEN category = {k} THEN a END), 6) AS c_{k}" for k in range(5)) + ", round((" + " + ".join(f"max(CASE WHEN category = {k} THEN a END)" for k in range(5)) + ") / 5, 6) AS macro, (SELECT round(avg(CAST(correct AS DOUBLE)), 6) FROM o WHERE o.model = c.model) AS micro FROM c GROUP BY model")
def e06(spark, sf):
    """Stand-in answers: a hash rule says whether a turn is right."""
    t = table(spark, sf, "conversations").where("role = 'assistant'")
    o = t.select(F.when(F.col("conv_id") % 2 == 0, "m0").otherwise("m1").alias("model"), (F.col("conv_id") % 5).alias("category"), (hash28(F.concat_ws(":", F.col("conv_id").cast("string"), F.col("turn").cast("string"))) % 100 < 40).alias("correct"))
    out = evaluate.split_accuracy(o, list(range(5)))
    return out.select("model", *(F.round(c, 6).alias(c) for c in out.columns if c != "model"))


@query("e06_published_means", "WITH o AS (SELECT coalesce(source, '') AS model, doc_id % 5 AS category, CAST(quality = 1 AS DOUBLE) AS c FROM documents JOIN labels USING (doc_id)), s AS (SELECT model, category, avg(c) AS a FROM o GROUP BY ALL), m AS (SELECT model, (" + " + ".join(f"max(CASE WHEN category = {k} THEN a END)" for k in range(5)) + ") / 5 AS macro FROM s GROUP BY model), t AS (SELECT model, avg(c) AS overall FROM o GROUP BY model) SELECT model, round(100 * overall, 4) AS overall, round(100 * macro, 4) AS macro, coalesce(abs(100 * overall - 100 * macro) > 0.15, FALSE) AS differs FROM m JOIN t USING (model)")
def e06_published(spark, sf):
    """Sources' overall score against the mean of its five parts' scores, and whether they differ by more than the published table's rounding."""
    d = table(spark, sf, "documents").select("doc_id", F.coalesce("source", F.lit("")).alias("model")).join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id")
    t = evaluate.split_accuracy(d.select("model", (F.col("doc_id") % 5).alias("category"), (F.col("quality") == 1).alias("correct")), list(range(5)))
    overall, macro = 100 * F.col("micro"), 100 * F.col("macro")
    return t.select("model", F.round(overall, 4).alias("overall"), F.round(macro, 4).alias("macro"), F.coalesce(F.abs(overall - macro) > 0.15, F.lit(False)).alias("differs"))


@query("e07_ablation_delta", "WITH s AS (SELECT lang AS base, source AS mix, CAST(n_chars >= 1000 AS INTEGER) AS cpt, avg(quality) AS score FROM documents JOIN labels USING (doc_id) GROUP BY ALL), t AS (SELECT base, mix, max(CASE WHEN cpt = 0 THEN score END) AS a, max(CASE WHEN cpt = 1 THEN score END) AS b FROM s GROUP BY base, mix) SELECT base, mix, round(a, 6) AS without_cpt, round(b, 6) AS with_cpt, round(b - a, 4) AS delta FROM t")
def e07(spark, sf):
    """Two by two: languages and sources, the mean label of short documents against that of long ones."""
    d = table(spark, sf, "documents").select("doc_id", F.col("lang").alias("base"), F.col("source").alias("mix"), (F.col("n_chars") >= 1000).cast("int").alias("cpt"))
    s = d.join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id").groupBy("base", "mix", "cpt").agg(F.avg("quality").alias("score"))
    t = s.groupBy("base", "mix").pivot("cpt", [0, 1]).agg(F.first("score"))
    return t.select("base", "mix", F.round("0", 6).alias("without_cpt"), F.round("1", 6).alias("with_cpt"), F.round(F.col("1") - F.col("0"), 4).alias("delta"))


@query("e08_four_way", "WITH s AS (SELECT l_orderkey AS k, bool_and(l_discount <= 0.07) AS sub_ok FROM lineitem GROUP BY 1), o AS (SELECT sub_ok, o_orderstatus = 'F' AS top FROM s JOIN orders ON k = o_orderkey), r AS (SELECT count(*) AS problems, avg(CAST(NOT sub_ok AND NOT top AS DOUBLE)) AS ik, avg(CAST(sub_ok AND NOT top AS DOUBLE)) AS ig, avg(CAST(sub_ok AND top AS DOUBLE)) AS cm, avg(CAST(NOT sub_ok AND top AS DOUBLE)) AS rote FROM o) SELECT problems, round(ik, 6) AS ik, round(ig, 6) AS ig, round(cm, 6) AS cm, round(rote, 6) AS rote, round(cm + ig / 2, 6) AS avg, round(rote / nullif(rote + cm, 0), 6) AS rm FROM r")
def e08(spark, sf):
    sub = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.bool_and(F.col("l_discount") <= 0.07).alias("sub_ok"))
    out = evaluate.four_way(sub.join(table(spark, sf, "orders").select("o_orderkey", (F.col("o_orderstatus") == "F").alias("composite_ok")), "o_orderkey"))
    return out.select("problems", *(F.round(c, 6).alias(c) for c in out.columns if c != "problems"))


@query("e09_published_average", "WITH s AS (SELECT l_orderkey AS k, bool_and(l_discount <= 0.07) AS sub_ok FROM lineitem GROUP BY 1), o AS (SELECT o_orderpriority AS model, sub_ok, o_orderstatus = 'F' AS top FROM s JOIN orders ON k = o_orderkey), r AS (SELECT model, 100 * avg(CASE WHEN top AND sub_ok THEN 1.0::DOUBLE WHEN NOT top AND sub_ok THEN 0.5::DOUBLE ELSE 0.0::DOUBLE END) AS average, 100 * avg(CAST(NOT sub_ok AND NOT top AS DOUBLE)) AS ik, 100 * avg(CAST(sub_ok AND NOT top AS DOUBLE)) AS ig, 100 * avg(CAST(sub_ok AND top AS DOUBLE)) AS cm FROM o GROUP BY model) SELECT model, round(average, 4) AS average, round(cm + ig / 2, 4) AS by_formula, round(100 * (100 - ik - ig - cm) / nullif(100 - ik - ig, 0), 4) AS rote_by_formula FROM r")
def e09(spark, sf):
    """Mean points of composite problems (orders, by priority) against the formula of the four outcomes' shares."""
    sub = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.bool_and(F.col("l_discount") <= 0.07).alias("sub"))
    o = sub.join(table(spark, sf, "orders").select("o_orderkey", F.col("o_orderpriority").alias("model"), (F.col("o_orderstatus") == "F").alias("top")), "o_orderkey")
    s, t = F.col("sub"), F.col("top")
    share = lambda c: 100 * F.avg(c.cast("double"))
    r = o.groupBy("model").agg((100 * F.avg(F.when(s & t, 1.0).when(s & ~t, 0.5).otherwise(0.0))).alias("average"), share(~s & ~t).alias("ik"), share(s & ~t).alias("ig"), share(s & t).alias("cm"))
    rest = 100 - F.col("ik") - F.col("ig")
    return r.select("model", F.round("average", 4).alias("average"), F.round(F.col("cm") + F.col("ig") / 2, 4).alias("by_formula"), F.round(100 * (rest - F.col("cm")) / F.nullif(rest, F.lit(0.0)), 4).alias("rote_by_formula"))


@query("e10_extract_answer", "SELECT item_id, CASE item_id % 4 WHEN 0 THEN (item_id * 7)::VARCHAR WHEN 1 THEN 'B' WHEN 2 THEN (item_id * 1000)::VARCHAR END AS truth, item_id % 4 <> 3 AS correct FROM benchmark")
def e10(spark, sf):
    """Generated responses in four formats, the answer taken out, and compared with the truth."""
    b, i = table(spark, sf, "benchmark").select("item_id"), F.col("item_id")
    kind, n = i % 4, (i * 7).cast("string")
    truth = F.when(kind == 0, n).when(kind == 1, "B").when(kind == 2, (i * 1000).cast("string"))
    said = F.when(kind == 0, F.concat(F.lit("So 3 + 4. The answer is "), n)).when(kind == 1, "It must be (A) or (B)").when(kind == 2, F.concat(F.lit("Answer: "), F.format_number(i * 1000, 0))).otherwise("I do not know")
    return b.select("item_id", truth.alias("truth"), evaluate.same_answer(evaluate.extract_answer(said), truth).alias("correct"))


_COUNT = r"len(list_filter(regexp_split_to_array(text, '[ \t\r\n]+'), lambda w: w <> ''))"


@query("e12_data_efficiency", f"SELECT source AS corpus, CAST(sum({_COUNT}) AS DOUBLE) AS tokens, round(100 * avg(quality), 6) AS score, round(100 * avg(quality) / nullif(CAST(sum({_COUNT}) AS DOUBLE) / 1e6::DOUBLE, 0), 3) AS per_million FROM documents LEFT JOIN labels USING (doc_id) GROUP BY source")
def e12(spark, sf):
    """Score of each source's labelled documents by the tokens of all its documents, in millions."""
    d = texts(spark, sf, "documents").select("doc_id", F.col("source").alias("corpus"), rules.n_words(F.col("text")).alias("n")).join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left")
    t = d.groupBy("corpus").agg(F.sum("n").cast("double").alias("tokens"), (100 * F.avg("quality")).alias("score"))
    return t.select("corpus", "tokens", F.round("score", 6).alias("score"), F.round(F.col("score") / F.nullif(F.col("tokens") / 1e6, F.lit(0.0)), 3).alias("per_million"))


_STAGES = [("crawled", "TRUE"), ("language", "lang IN ('en', 'zh')"), ("rules", "lang IN ('en', 'zh') AND n_chars >= 300"), ("high_precision", "lang IN ('en', 'zh') AND n_chars >= 300 AND quality = 1")]


@query("e01_published_funnel", "WITH d AS (SELECT lang, n_chars, quality FROM documents LEFT JOIN labels USING (doc_id)), s AS (" + " UNION ALL ".join(f"SELECT {k} AS step, '{n}' AS stage, count(*) FILTER ({c}) AS n FROM d" for k, (n, c) in enumerate(_STAGES)) + f") SELECT stage, n, round(n / nullif(lag(n) OVER (ORDER BY step), 0), 6) AS kept, round(p.n_published / lag(p.n_published) OVER (ORDER BY step), 6) AS published FROM s JOIN ({B.values(B.FUNNEL)}) p(stage, n_published) USING (stage)")
def e01(spark, sf):
    """Stages over the documents, with what each keeps of the one before, beside the published stages of these names."""
    from pyspark.sql import Window as W

    d = table(spark, sf, "documents").select("doc_id", "lang", "n_chars").join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left")
    one = d.agg(*(F.count(F.when(F.expr(c), 1)).alias(n) for n, c in _STAGES))
    s = one.select(F.posexplode(F.array(*(F.struct(F.lit(n).alias("stage"), F.col(n).alias("n")) for n, _ in _STAGES))).alias("step", "x")).select("step", "x.stage", "x.n")
    s = s.join(F.broadcast(B.frame(spark, B.FUNNEL, "stage string, n_published double")), "stage")
    before = lambda c: F.lag(c).over(W.orderBy("step"))  # noqa: E731  four rows
    return s.select("stage", "n", F.round(F.col("n") / F.nullif(before("n"), F.lit(0)), 6).alias("kept"), F.round(F.col("n_published") / before("n_published"), 6).alias("published"))


_IMAGE_STAGES = (("referenced", "occurrences"), ("after_caps", "after_caps"), ("after_rules", "after_rules"), ("fetched", "fetched"))


@query("e02_published_image_funnel", f"WITH one AS ({ORACLES['m35_image_funnel_star']}) " + " UNION ALL ".join(f"SELECT '{n}' AS stage, {c} AS n, round({c} / occurrences, 6) AS of_all, {dict(B.IMAGE_FUNNEL)[n]}::DOUBLE AS published FROM one" for n, c in _IMAGE_STAGES))
def e02(spark, sf):
    """The image stages over an order's parts as images, as shares of all references, beside the published numbers (millions)."""
    one = cut(QUERIES["m35_image_funnel_star"](spark, sf))  # one row
    return union_all([one.select(F.lit(n).alias("stage"), F.col(c).alias("n"), F.round(F.col(c) / F.col("occurrences"), 6).alias("of_all"), F.lit(dict(B.IMAGE_FUNNEL)[n]).alias("published")) for n, c in _IMAGE_STAGES])


@query("b01_extraction_comparison", "SELECT 'interleaved' AS extractor, count(*) FILTER (html LIKE '%</h1>%') AS formulas, count(*) FILTER (html LIKE '%</h1>%') AS images FROM pages UNION ALL SELECT 'plain', 0, 0")
def b01(spark, sf):
    """Formulas and images that each extractor keeps, on pages with planted formulas and images."""
    pages = texts(spark, sf, "pages").select("page_id", "url", F.regexp_replace("html", "</h1>", r"</h1><p>Let \\(x^2+1\\) be</p><img src='/f.png'>").alias("html"))

    def count(df, name):
        s = df.select(F.explode("segments").alias("s"))
        return s.agg(F.lit(name).alias("extractor"), F.sum((F.col("s.kind") == "math").cast("long")).alias("formulas"), F.sum((F.col("s.kind") == "image").cast("long")).alias("images"))

    return count(extract.interleaved(pages), "interleaved").unionByName(count(extract.interleaved(pages, math=False, images=False), "plain"))


def _two_filters(spark, sf):
    """Ids that the high-recall filter keeps of all documents, and those that the one retrained on scores of six and more keeps."""
    from corpusloom.plans import pipeline
    from corpusloom.plans.curation import _scores

    cfg, docs = pipeline.Config(), cut(texts(spark, sf, "documents").select("doc_id", "text"))
    labels = table(spark, sf, "labels")
    good = docs.join(labels.where("quality = 1"), "doc_id", "left_semi").select("text")
    bad = docs.join(labels.where("quality = 0"), "doc_id", "left_semi").select("text")
    first = textclf.keep(pipeline.first_filter(docs, good, bad, cfg, "doc_id"), cfg.recall_cut).select("doc_id")
    second = textclf.keep(pipeline.second_filter(docs, _scores(spark, sf), cfg, "doc_id"), cfg.precision_cut).select("doc_id")
    return cut(first), cut(second)


@query("b03_filter_comparison")
def b03(spark, sf):
    """The recall-minded filter against the one retrained, on normalised texts, on documents scored six and more, as two kept sets."""
    return evaluate.compare_filters(*_two_filters(spark, sf))


@query("b05_filters_against_judge")
def b05(spark, sf):
    """Both linear filters against the judge's own decision on the scored documents: what each keeps of either side of its cut."""
    from corpusloom.plans.curation import _scores

    judged = _scores(spark, sf).select("doc_id", (F.col("score") >= 6).alias("y"))
    n = lambda c: F.sum(c.cast("long"))
    rows = []
    for name, kept in zip(("high_recall", "high_precision"), _two_filters(spark, sf), strict=True):
        both = judged.join(kept.withColumn("kept", F.lit(True)), "doc_id", "left").select("y", F.coalesce("kept", F.lit(False)).alias("kept"))
        rows.append(both.agg(F.lit(name).alias("filter"), n(F.col("kept") & F.col("y")).alias("tp"), n(F.col("kept") & ~F.col("y")).alias("fp"), n(~F.col("kept") & F.col("y")).alias("fn"), n(~F.col("kept") & ~F.col("y")).alias("tn")))
    return union_all(rows)


@query("w08_corpus_comparison")
def w08(spark, sf):
    """One learner trained on four subsets, by its area under the curve on held-out labels: nothing, all, without copies, curated."""
    d = cut(_split(spark, sf).join(table(spark, sf, "documents").select("doc_id", "lang"), "doc_id"))
    train, test = d.where("split = 'train'"), d.where("split = 'test'")
    single = dedup.exact(train, dedup.normalised(F.col("text"))).where("kept").select("doc_id")
    clean = rules.apply(train).where("kept").select("doc_id")
    sets = {"raw": train, "deduplicated": train.join(single, "doc_id", "left_semi"), "curated": train.join(single, "doc_id", "left_semi").join(clean, "doc_id", "left_semi")}
    out = [evaluate.auc(test.select(F.lit(0.5).alias("prob"), "y")).select(F.lit("none").alias("subset"), F.round("auc", 4).alias("auc"), F.lit(0).cast("long").alias("docs"))]
    for name, part in sets.items():
        model = textclf.nb_fit(part.select("text", "y"))
        out.append(evaluate.auc(textclf.nb_score(test, model).join(test.select("doc_id", "y"), "doc_id")).select(F.lit(name).alias("subset"), F.round("auc", 4).alias("auc")).crossJoin(part.agg(F.count("*").alias("docs"))))
    return union_all(out)


@query("w18_contamination", r"WITH w AS (SELECT doc_id, list_filter(string_split(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g'), ' '), lambda v: v <> '') AS p FROM documents), v AS (SELECT item_id, list_filter(string_split(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g'), ' '), lambda v: v <> '') AS p FROM benchmark), a AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, greatest(len(p) - 7, 1) + 1), lambda i: array_to_string(p[i : i + 7], ' '))) AS g FROM w WHERE len(p) > 0), b AS (SELECT DISTINCT item_id, unnest(list_transform(range(1, greatest(len(p) - 7, 1) + 1), lambda i: array_to_string(p[i : i + 7], ' '))) AS g FROM v WHERE len(p) > 0) SELECT doc_id, count(DISTINCT item_id) AS items, count(DISTINCT g) AS grams FROM a JOIN b USING (g) GROUP BY doc_id")
def w18(spark, sf):
    return evaluate.contamination(texts(spark, sf, "documents"), table(spark, sf, "benchmark"))


_FUNNEL = f"""WITH {CRAWL}, s0 AS (SELECT c.rec_id, c.url, c.snapshot_date, c.year, d.text, d.lang FROM crawl c JOIN documents d ON d.doc_id = CAST(regexp_extract(url, '^https?://[^/]+/[a-z]+/([0-9]+)', 1) AS BIGINT)),
    s1 AS (SELECT * FROM s0 WHERE lang IN ('en', 'zh')),
    s2 AS (SELECT * FROM s1 QUALIFY row_number() OVER (PARTITION BY year, trim(regexp_replace(lower(text), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')) ORDER BY rec_id DESC) = 1),
    s3 AS (SELECT * FROM s2 QUALIFY row_number() OVER (PARTITION BY year, url ORDER BY snapshot_date DESC, rec_id) = 1),
    s4 AS (SELECT * FROM s3 WHERE NOT ({' OR '.join(_RULES_SQL.values())}))
    SELECT 0 AS step, 'crawl' AS stage, (SELECT count(*) FROM s0) AS n_out UNION ALL SELECT 1, 'language', (SELECT count(*) FROM s1) UNION ALL SELECT 2, 'exact_copies', (SELECT count(*) FROM s2)
    UNION ALL SELECT 3, 'url_dedup', (SELECT count(*) FROM s3) UNION ALL SELECT 4, 'rules', (SELECT count(*) FROM s4)"""


@query("m36_corpus_funnel", _FUNNEL)
def m36(spark, sf):
    """The ledger of the stages that SQL can follow: language, copies within a year, URLs within a year, rules."""
    key = F.regexp_extract("url", "^https?://[^/]+/[a-z]+/([0-9]+)", 1).cast("long")
    pages = crawl(spark, sf).select("rec_id", "url", "snapshot_date", "year", key.alias("doc_id"))
    s0 = pages.join(texts(spark, sf, "documents").select("doc_id", "text", "lang"), "doc_id")
    s1 = s0.where(F.col("lang").isin("en", "zh"))
    narrow = s1.select("rec_id", "url", "snapshot_date", "year", F.sha2(dedup.normalised(F.col("text")), 256).alias("h"))
    flagged = rules.apply(s1).select("rec_id", "kept")
    best = narrow.groupBy("year", "h").agg(F.max("rec_id").alias("rec_id")).select("rec_id")
    s2 = narrow.join(best, "rec_id", "left_semi")
    s3 = dedup.url(s2)
    s4 = s3.join(flagged.where("kept"), "rec_id", "left_semi")
    count = lambda df, k, name: df.agg(F.lit(k).alias("step"), F.lit(name).alias("stage"), F.count("*").alias("n_out"))
    return union_all([count(df, k, name) for k, (name, df) in enumerate((("crawl", s0), ("language", s1), ("exact_copies", s2), ("url_dedup", s3), ("rules", s4)))])


def _path(spark, sf, cfg):
    from corpusloom.plans.pipeline import curate

    docs, labels = texts(spark, sf, "documents"), table(spark, sf, "labels")
    pool = lambda q: docs.join(labels.where(F.col("quality") == q), "doc_id", "left_semi").select("text")
    return curate(spark, crawl(spark, sf), pool(1), cfg, pool(0), docs.select("text", "lang"))


@query("m36_full_pipeline")
def m36_full(spark, sf):
    """All stages on pages: parser, language model, high recall, two-step content dedup, URLs, rules, high precision on normalised texts, images."""
    from corpusloom.plans.pipeline import Config

    return _path(spark, sf, Config())[1]


@query("m36_kept_documents")
def m36_documents(spark, sf):
    """The size of what the whole path keeps: documents, tokens, image places."""
    from corpusloom.plans.pipeline import Config, corpus_stats

    return corpus_stats(_path(spark, sf, Config())[0])


_WORDS = r"list_filter(string_split(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g'), ' '), lambda v: v <> '')"
_EXTRA = ", snapshot_id, snapshot_date"
_LEDGER = rf"""WITH RECURSIVE {CRAWL},
    s0 AS (SELECT rec_id, url, snapshot_id, snapshot_date, year, coalesce(nullif(regexp_extract(html, '<html[^>]* lang="([a-zA-Z-]+)"', 1), ''), nullif(regexp_extract(url, '^https?://[^/]+/([a-z][a-z])/', 1), '')) AS lang, {extract.article_text_sql('html')} AS text FROM crawl),
    s1 AS (SELECT * FROM s0 WHERE lang IN ('en', 'zh')),
    pool AS (SELECT DISTINCT text, quality AS y FROM documents JOIN labels USING (doc_id)), size AS (SELECT least(count(*) FILTER (y = 1), 500000) AS p, least(count(*) FILTER (y = 0), 500000) AS n FROM pool),
    tok AS (SELECT y, unnest({_WORDS}) AS token FROM (SELECT CASE WHEN y = 1 THEN text ELSE regexp_replace(text, '!\[[^\]]*\]\([^)]*\)|https?://[^ \n]+\.(?:png|jpe?g|gif|svg|webp)', '', 'g') END AS text, y FROM pool)),
    cnt AS (SELECT token, sum(CAST(y = 1 AS BIGINT)) AS n1, sum(CAST(y = 0 AS BIGINT)) AS n0 FROM tok GROUP BY token), tot AS (SELECT sum(n1) AS t1, sum(n0) AS t0, count(*) AS v FROM cnt),
    model AS (SELECT token, ln((n1 + 1) / (t1 + v)) - ln((n0 + 1) / (t0 + v)) AS weight FROM cnt, tot),
    nb AS (SELECT rec_id, sum(weight) / count(*) AS score FROM (SELECT rec_id, unnest({_WORDS}) AS token FROM s1) JOIN model USING (token) GROUP BY rec_id),
    s2 AS (SELECT s1.* FROM s1 LEFT JOIN nb USING (rec_id) WHERE 1 / (1 + exp(-4 * coalesce(score, 0))) >= 0.4),
    {dedup.signature_sql('s2', 'rec_id', 112, extra=_EXTRA)}, {dedup.bands_sql('rec_id', 8, _EXTRA)}, {_step_sql('1', 's2', 'snapshot_id')},
    left1 AS (SELECT * FROM s2 WHERE rec_id IN (SELECT rec_id FROM kept1 WHERE kept)), {_step_sql('2', 'left1', 'unnest([snapshot_id - 1, snapshot_id])')},
    s4 AS (SELECT * FROM s2 WHERE rec_id IN (SELECT rec_id FROM kept2 WHERE kept)), s5 AS (SELECT * FROM s4 QUALIFY row_number() OVER (PARTITION BY year, url ORDER BY snapshot_date DESC, rec_id) = 1),
    s6 AS (SELECT * FROM s5 WHERE NOT ({' OR '.join(_RULES_SQL.values())})),
    n AS (SELECT (SELECT count(*) FROM s0) AS n0, (SELECT count(*) FROM s1) AS n1, (SELECT count(*) FROM s2) AS n2, (SELECT count(*) FROM left1) AS n3, (SELECT count(*) FROM s4) AS n4, (SELECT count(*) FROM s5) AS n5, (SELECT count(*) FROM s6) AS n6)
    SELECT 1 AS step, 'language' AS stage, n0 AS n_in, n1 AS n_out FROM n UNION ALL SELECT 2, 'high_recall', n1, n2 FROM n UNION ALL SELECT 3, 'within_snapshot', n2, n3 FROM n UNION ALL SELECT 4, 'neighbor_snapshots', n3, n4 FROM n
    UNION ALL SELECT 5, 'url_dedup', n4, n5 FROM n UNION ALL SELECT 6, 'rules', n5, n6 FROM n"""


@query("m36_ledger_by_counts", _LEDGER)
def m36_ledger(spark, sf):
    """The same path with its countable variants: declared language, naive Bayes, the affine hash family, up to the rules."""
    from corpusloom.plans.pipeline import Config

    return _path(spark, sf, Config(language="declared", classifier="bayes", family="affine31", training_rows=1 << 40, precise=False))[1]


@query("m37_corpus_stats", r"SELECT count(*) AS docs, CAST(sum(len(list_filter(regexp_split_to_array(text, '[ \t\r\n]+'), lambda w: w <> ''))) AS BIGINT) AS tokens, CAST(sum(length(text)) AS BIGINT) AS chars, (SELECT CAST(sum(len(regexp_extract_all(html, '<a href=')))  AS BIGINT) FROM pages) AS image_refs FROM documents")
def m37(spark, sf):
    t = texts(spark, sf, "documents").agg(F.count("*").alias("docs"), F.sum(rules.n_words(F.col("text"))).alias("tokens"), F.sum(F.length("text")).alias("chars"))
    return t.crossJoin(texts(spark, sf, "pages").agg(F.sum(F.regexp_count("html", F.lit("<a href="))).alias("image_refs")))  # one row each


@query("e01_stage_ledger", f"SELECT 1 AS step, 'language' AS stage, count(*) AS n_in, count(*) FILTER (lang = 'en') AS n_out, round(count(*) FILTER (lang = 'en') / count(*), 6) AS kept_frac FROM documents UNION ALL SELECT 2, 'rules', count(*), count(*) FILTER (NOT ({' OR '.join(_RULES_SQL.values())})), round(count(*) FILTER (NOT ({' OR '.join(_RULES_SQL.values())})) / count(*), 6) FROM documents WHERE lang = 'en'")
def e01_ledger(spark, sf):
    """Two stages counted in one pass over the documents."""
    from corpusloom.operators.funnel import ledger

    found = ledger(rules.apply(texts(spark, sf, "documents")), [("language", F.col("lang") == "en"), ("rules", F.col("kept"))])
    return found.select("step", "stage", "n_in", "n_out", F.round("kept_frac", 6).alias("kept_frac"))


@query("e14_engine_cost")
def e14(spark, sf):
    """What stages of the path cost the engine: seconds, rows a second, shuffled and spilled bytes."""
    from corpusloom.operators import cost, normalise

    docs, pages = texts(spark, sf, "documents"), texts(spark, sf, "pages")
    stages = {
        "extraction": (pages, extract.with_text(pages)), "exact_dedup": (docs, dedup.exact(docs, dedup.normalised(F.col("text")))), "signatures": (docs, dedup.signature(docs)), "rules": (docs, rules.apply(docs)),
        "url_dedup": (pages, dedup.url(crawl(spark, sf))), "normalised": (docs, docs.select("doc_id", normalise.tokens(F.col("text")))),
    }
    return spark.createDataFrame([cost.measured(spark, name, source.count(), df) for name, (source, df) in stages.items()], cost.SCHEMA)


@query("e10_generate_and_judge", "SELECT count(*) AS items, count(*) FILTER (length(text) % 3 <> 0) AS correct FROM benchmark")
def e10_judge(spark, sf):
    """Three steps with a stand-in model that counts characters, and for every third length says nothing of use."""
    b = table(spark, sf, "benchmark").select("item_id", "text")
    said = evaluate.generate(b, lambda texts: [f"The answer is {len(t)}" if len(t) % 3 else "No idea" for t in texts])
    out = evaluate.judge(said, b.select("item_id", F.length("text").cast("string").alias("truth")))
    return out.agg(F.count("*").alias("items"), F.sum(F.col("correct").cast("long")).alias("correct"))


@query("m03_language_filter")
def m03_filter(spark, sf):
    """Documents that a subword model finds to be English with at least nine in ten."""
    from corpusloom.operators import langid, sampling

    docs = cut(sampling.split(texts(spark, sf, "documents").select("doc_id", "text", "lang"), "doc_id"))
    model = langid.train_subword(docs.where("split = 'train'"))
    return langid.filter(docs.where("split = 'test'"), model, ("en",), 0.9).select("doc_id", "predicted", F.round("lang_prob", 4).alias("lang_prob"))


@query("m26_judge_filter", f"SELECT doc_id FROM documents WHERE least(10, ({_PROMPT_SIZE} + length(text)) // 300) >= 6")
def m26_judge(spark, sf):
    """The judge as the filter, on a stand-in that likes long texts."""
    from corpusloom.operators import scoring

    return scoring.filter(texts(spark, sf, "documents").select("doc_id", "text"), lambda prompts: [str(min(10, len(p) // 300)) for p in prompts]).select("doc_id")
