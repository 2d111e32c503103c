"""Queries of the text path: extraction, language, sampling, classifiers, rules, scoring, normalising."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusloom.operators import extract, langid, normalise, rules, sampling, scoring, textclf
from corpusloom.operators.dedup import union_all
from corpusloom.plans.registry import query
from corpusloom.runtime import cut, table, texts
from corpusloom.sources.views import H28, LINKS

PART = {"docs": lambda s, d: table(s, d, "documents"), "labels": lambda s, d: table(s, d, "labels")}


def _labelled(spark, sf):
    return texts(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id")


@query("m01_plain_text_sql", f"SELECT page_id, length(t) AS n_chars, md5(t) AS text_md5 FROM (SELECT page_id, {extract.article_text_sql('html')} AS t FROM pages)")
def m01(spark, sf):
    return extract.plain_text_sql(texts(spark, sf, "pages")).select("page_id", F.length("text").cast("long").alias("n_chars"), F.md5(F.col("text").cast("binary")).alias("text_md5"))


_BARE = r"regexp_replace({}, '[^\p{{L}}\p{{N}}_]+', '', 'g')"


@query(
    "m01_plain_text_match",
    f"""SELECT count(*) AS pages, count(*) FILTER ({_BARE.format(extract.article_text_sql('html', True))} = {_BARE.format('text')}) AS matches
    FROM pages JOIN documents ON doc_id = CAST(regexp_extract(url, '^https?://[^/]+/[a-z]+/([0-9]+)', 1) AS BIGINT)""",
)
def m01_match(spark, sf):
    """The parser's text of each page against the document that the page was made from."""
    bare = lambda c: F.regexp_replace(c, r"[^\p{L}\p{N}_]+", "")
    found = extract.plain_text(texts(spark, sf, "pages"), headings=False).select(F.regexp_extract("url", "^https?://[^/]+/[a-z]+/([0-9]+)", 1).cast("long").alias("doc_id"), bare("text").alias("a"))
    truth = texts(spark, sf, "documents").select("doc_id", bare("text").alias("b"))
    return found.join(truth, "doc_id").agg(F.count("*").alias("pages"), F.sum((F.col("a") == F.col("b")).cast("long")).alias("matches"))


@query("m02_interleaved_segments")
def m02(spark, sf):
    s = extract.interleaved(texts(spark, sf, "pages")).select("page_id", F.explode("segments").alias("s"))
    return s.groupBy("page_id").agg(F.count("*").alias("segments"), F.sum((F.col("s.kind") == "math").cast("long")).alias("math"), F.sum((F.col("s.kind") == "image").cast("long")).alias("images"))


@query("m02_link_positions", f"WITH {LINKS} SELECT page_id, pos, link FROM links")
def m02_links(spark, sf):
    return extract.link_positions(texts(spark, sf, "pages"))


@query("m03_language_keep", "SELECT doc_id, lang FROM documents WHERE lang IN ('en', 'zh')")
def m03(spark, sf):
    return langid.keep(texts(spark, sf, "documents")).select("doc_id", "lang")


@query("m03b_declared_language", """SELECT page_id, nullif(coalesce(nullif(regexp_extract(html, '<html[^>]* lang="([a-zA-Z-]+)"', 1), ''), regexp_extract(url, '^https?://[^/]+/([a-z][a-z])/', 1)), '') AS lang FROM pages""")
def m03b(spark, sf):
    return langid.declared(texts(spark, sf, "pages"))


@query("m03c_script_ratio", r"SELECT doc_id, round(length(regexp_replace(text, '[^\p{Latin}]', '', 'g')) / nullif(length(regexp_replace(text, '[^\p{L}]', '', 'g')), 0), 6) AS latin, round(length(regexp_replace(text, '[^\p{Han}]', '', 'g')) / nullif(length(regexp_replace(text, '[^\p{L}]', '', 'g')), 0), 6) AS han FROM documents")
def m03c(spark, sf):
    return texts(spark, sf, "documents").select("doc_id", F.round(langid.script_ratio(F.col("text"), "Latin"), 6).alias("latin"), F.round(langid.script_ratio(F.col("text")), 6).alias("han"))


@query("m03_langid_confusion")
def m03_confusion(spark, sf):
    docs = cut(sampling.split(texts(spark, sf, "documents").select("doc_id", "text", "lang"), "doc_id"))
    model = langid.train_subword(docs.where("split = 'train'"))
    return langid.predict(docs.where("split = 'test'"), model, ["lang"]).groupBy("lang", "predicted").agg(F.count("*").alias("n"))


@query("m04_balanced_sample", "WITH l AS (SELECT doc_id, quality, md5(doc_id::VARCHAR) AS h FROM labels JOIN documents USING (doc_id)) SELECT doc_id, 1 AS y FROM (SELECT * FROM l WHERE quality = 1 ORDER BY h, doc_id LIMIT 50) UNION ALL SELECT doc_id, 0 FROM (SELECT * FROM l WHERE quality = 0 ORDER BY h, doc_id LIMIT 50)")
def m04(spark, sf):
    d = _labelled(spark, sf).select("doc_id", "quality")
    return sampling.balanced(d.where("quality = 1"), d.where("quality = 0"), 50).select("doc_id", "y")


@query("m04a_bernoulli_sample", f"SELECT doc_id FROM documents WHERE {H28.format('doc_id::VARCHAR')} % 1000 < 100")
def m04a(spark, sf):
    return sampling.bernoulli(table(spark, sf, "documents").select("doc_id"), 0.1, "doc_id")


@query("m04b_strip_image_links", r"SELECT doc_id, md5(regexp_replace(text, '!\[[^\]]*\]\([^)]*\)|https?://[^ \n]+\.(?:png|jpe?g|gif|svg|webp)', '', 'g')) AS text_md5 FROM documents")
def m04b(spark, sf):
    return texts(spark, sf, "documents").select("doc_id", F.md5(extract.strip_image_links(F.col("text")).cast("binary")).alias("text_md5"))


def _nb(spark, sf):
    docs = texts(spark, sf, "documents").select("doc_id", "text")
    lab = sampling.split(table(spark, sf, "labels").select("doc_id", F.col("quality").alias("y")), "doc_id")
    return textclf.nb_score(docs, textclf.nb_fit(docs.join(lab.where("split = 'train'"), "doc_id"))), lab


@query("m05_nb_scores", f"WITH {textclf.NB_SQL} SELECT doc_id, round(score, 6) AS score FROM nb")
def m05(spark, sf):
    return _nb(spark, sf)[0].select("doc_id", F.round("score", 6).alias("score"))


@query("m05_linear_scores", rf"""WITH tok AS (SELECT doc_id, unnest(list_filter(string_split(regexp_replace(lower(text), '[^\p{{L}}\p{{N}}]+', ' ', 'g'), ' '), lambda v: v <> '')) AS t FROM documents),
    s AS (SELECT doc_id, avg((({H28.format('t')} % 512) * 7919 % 2001 - 1000) / 1000.0::DOUBLE) AS m FROM tok GROUP BY doc_id)
    SELECT doc_id, round(1 / (1 + exp(-(coalesce(m, 0) + 0.1))), 6) AS prob FROM documents LEFT JOIN s USING (doc_id)""")
def m05_linear(spark, sf):
    """Scoring by given hashed weights."""
    weights = [(b * 7919 % 2001 - 1000) / 1000 for b in range(512)]
    return textclf.score(texts(spark, sf, "documents"), weights, 0.1).select("doc_id", F.round("prob", 6).alias("prob"))


def _metrics(scored, name):
    p, y = F.col("prob") >= 0.5, F.col("y") == 1
    n = lambda c: F.sum(c.cast("long"))
    return scored.agg(F.lit(name).alias("model"), n(p & y).alias("tp"), n(p & ~y).alias("fp"), n(~p & y).alias("fn"), n(~p & ~y).alias("tn"))


def _split(spark, sf, col="quality"):
    return sampling.split(_labelled(spark, sf).select("doc_id", "text", F.col(col).alias("y")), "doc_id")


@query("m05_logistic_metrics")
def m05_logistic(spark, sf):
    d = cut(_split(spark, sf))
    model = textclf.train(d.where("split = 'train'").select("text", "y"))
    return _metrics(textclf.predict(d.where("split = 'test'").select("doc_id", "text", "y"), model, ["doc_id", "y"]), "logistic")


@query("m05a_low_rank_metrics")
def m05a(spark, sf):
    d = cut(_split(spark, sf))
    model = textclf.train_low_rank(d.where("split = 'train'"))
    test = d.where("split = 'test'")
    return _metrics(textclf.score_low_rank(test, model).join(test.select("doc_id", "y"), "doc_id"), "low_rank")


CUTS = [0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]


@query("m06_threshold_sweep", f"WITH {textclf.NB_SQL} SELECT cut, count(*) FILTER (prob >= cut) AS kept, count(*) FILTER (prob >= cut AND y = 1) AS tp, count(*) FILTER (prob < cut AND y = 1) AS fn FROM nb JOIN lab USING (doc_id), (SELECT unnest({CUTS}::DOUBLE[]) AS cut) GROUP BY cut")
def m06(spark, sf):
    scored, lab = _nb(spark, sf)
    n = lambda c: F.sum(c.cast("long"))
    each = scored.join(lab, "doc_id").select("prob", "y", F.explode(F.array(*map(F.lit, CUTS))).alias("cut"))
    return each.groupBy("cut").agg(n(F.col("prob") >= F.col("cut")).alias("kept"), n((F.col("prob") >= F.col("cut")) & (F.col("y") == 1)).alias("tp"), n((F.col("prob") < F.col("cut")) & (F.col("y") == 1)).alias("fn"))


@query("m06_high_recall_keep", f"WITH {textclf.NB_SQL} SELECT doc_id FROM nb WHERE prob >= 0.4")
def m06_keep(spark, sf):
    return textclf.keep(_nb(spark, sf)[0]).select("doc_id")


_RULES_SQL = {
    "lorem": "(lower(text) LIKE '%lorem ipsum%' AND len(list_filter(regexp_split_to_array(text, '[ \\t\\r\\n]+'), lambda w: w <> '')) <= 100)",
    "punctuation": r"(lang = 'en' AND length(regexp_replace(text, '[^\p{P}\p{S}]', '', 'g')) > length(text) * 0.3)",
    "blocklist": r"list_has_any(regexp_split_to_array(lower(text), '[^\p{L}\p{N}_]+'), [" + ", ".join(f"'{w}'" for w in rules.INSULTS) + "])",
    "unicode": r"regexp_matches(text, '[\x{FFFD}\x{80}-\x{9F}\x{FDD0}-\x{FDEF}\x{FFFE}\x{FFFF}]')",
}


def _one_rule(name):
    def run(spark, sf):
        return texts(spark, sf, "documents").groupBy(F.coalesce(rules.retained()[name], F.lit(False)).alias("hit")).agg(F.count("*").alias("n"))

    return run


for _q, _name in (("m18_lorem", "lorem"), ("m19_punct_ratio_en", "punctuation"), ("m20_blocklist", "blocklist"), ("m21_unicode", "unicode")):
    query(_q, f"SELECT {_RULES_SQL[_name]} AS hit, count(*) AS n FROM documents GROUP BY 1")(_one_rule(_name))


@query("m22_rule_reasons", "SELECT doc_id, array_to_string(list_filter([" + ", ".join(f"CASE WHEN {c} THEN '{n}' END" for n, c in _RULES_SQL.items()) + "], lambda x: x IS NOT NULL), ',') AS reasons FROM documents")
def m22(spark, sf):
    return rules.apply(texts(spark, sf, "documents")).select("doc_id", F.array_join("reasons", ",").alias("reasons"))


@query("m22_rule_ledger", "WITH h AS (SELECT " + ", ".join(f"CAST({c} AS BIGINT) AS {n}" for n, c in _RULES_SQL.items()) + " FROM documents) " + " UNION ALL ".join(f"SELECT '{n}' AS rule, count(*) FILTER ({n} = 1) AS hits, count(*) FILTER ({n} = 1 AND {' + '.join(_RULES_SQL)} = 1) AS only_hits FROM h" for n in _RULES_SQL) + f" UNION ALL SELECT 'any', count(*) FILTER ({' + '.join(_RULES_SQL)} > 0), count(*) FILTER ({' + '.join(_RULES_SQL)} > 0) FROM h")
def m22_ledger(spark, sf):
    return rules.ledger(rules.apply(texts(spark, sf, "documents")), list(rules.retained()))


_LINES = "list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '')"
_CANDIDATES_SQL = {
    "curly_brace": "text LIKE '%{%'", "javascript": "lower(text) LIKE '%javascript%'", "few_words": "len(list_filter(regexp_split_to_array(text, '[ \\t\\r\\n]+'), lambda w: w <> '')) < 50",
    "few_sentences": "length(regexp_replace(text, '[^.!?]', '', 'g')) < 3", "no_terminal_punctuation": f"len(list_filter({_LINES}, lambda x: regexp_matches(x, '[.!?\"'']$'))) * 2 < len({_LINES})",
    "repeated_lines": f"len(list_distinct({_LINES})) * 10 < len({_LINES}) * 7", "digits": "length(regexp_replace(text, '[^0-9]', '', 'g')) * 10 > length(text)",
}


@query("m22a_damage_report", " UNION ALL ".join(f"SELECT '{n}' AS rule, count(*) FILTER (({c}) AND quality = 1) AS positives_hit, count(*) FILTER (({c}) AND quality = 0) AS negatives_hit FROM documents JOIN labels USING (doc_id)" for n, c in _CANDIDATES_SQL.items()))
def m22a(spark, sf):
    return rules.damage_report(_labelled(spark, sf), rules.candidates())


_SCORE_SQL = "SELECT doc_id, least(10, greatest(0, 6 * quality + 2 * (1 - toxic) + CASE WHEN length(text) >= 1000 THEN 2 WHEN length(text) >= 300 THEN 1 ELSE 0 END)) AS score FROM documents JOIN labels USING (doc_id)"


def _scores(spark, sf):
    return _labelled(spark, sf).select("doc_id", scoring.heuristic(F.col("quality"), F.col("toxic"), F.col("text")).alias("score"))


@query("m23_standin_scores", _SCORE_SQL)
def m23(spark, sf):
    return _scores(spark, sf)


_PROMPT_SIZE = len(scoring.PROMPT.format(text=""))


@query("m23_judge_interface", f"SELECT doc_id, CASE WHEN s <= 10 THEN s ELSE -1 END AS score FROM (SELECT doc_id, ({_PROMPT_SIZE} + length(text)) % 12 AS s FROM documents)")
def m23_judge(spark, sf):
    """The judge's interface with a judge that counts digits of the text's length."""
    return scoring.score(texts(spark, sf, "documents").select("doc_id", "text"), lambda prompts: [f"Score: {len(p) % 12}" for p in prompts]).select("doc_id", F.coalesce("score", F.lit(-1)).cast("long").alias("score"))


@query("m24_positive_set", f"SELECT doc_id, score FROM ({_SCORE_SQL}) WHERE score >= 6")
def m24(spark, sf):
    return sampling.from_scores(_scores(spark, sf))


@query("m24_training_set", f"WITH p AS (SELECT doc_id FROM ({_SCORE_SQL}) WHERE score >= 6 ORDER BY md5(doc_id::VARCHAR), doc_id LIMIT 100), n AS (SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM p) ORDER BY md5(doc_id::VARCHAR), doc_id LIMIT 100) SELECT doc_id, 1 AS y FROM p UNION ALL SELECT doc_id, 0 FROM n")
def m24_set(spark, sf):
    """Positives by score; negatives from the general pool without the positives."""
    p = cut(sampling.exact_k(sampling.from_scores(_scores(spark, sf), 6).select("doc_id"), 100, "doc_id"))
    n = sampling.exact_k(table(spark, sf, "documents").select("doc_id").join(p, "doc_id", "left_anti"), 100, "doc_id")
    return p.withColumn("y", F.lit(1)).unionByName(n.withColumn("y", F.lit(0)))


@query("m25_cut_for_volume", f"WITH {textclf.NB_SQL}, c AS (SELECT min(prob) AS cut FROM (SELECT prob FROM nb ORDER BY prob DESC LIMIT 100)) SELECT round(cut, 6) AS cut, count(*) AS kept FROM nb, c WHERE prob >= cut GROUP BY cut")
def m25(spark, sf):
    scored = cut(_nb(spark, sf)[0])
    c = textclf.cut_for_volume(scored, 100)
    return textclf.keep(scored, c).agg(F.round(F.lit(c), 6).alias("cut"), F.count("*").alias("kept"))


@query("m26_filter_agreement", f"WITH {textclf.NB_SQL}, j AS (SELECT doc_id FROM ({_SCORE_SQL}) WHERE score >= 6), l AS (SELECT nb.doc_id FROM nb JOIN labels USING (doc_id) WHERE prob >= 0.5) SELECT coalesce(CAST(j.doc_id IS NOT NULL AS INTEGER), 0) AS judge, coalesce(CAST(l.doc_id IS NOT NULL AS INTEGER), 0) AS linear, count(*) AS n FROM j FULL JOIN l ON j.doc_id = l.doc_id GROUP BY ALL")
def m26(spark, sf):
    """The judge's kept set against the linear filter's, by a full outer join of ids."""
    a = sampling.from_scores(_scores(spark, sf)).select("doc_id", F.lit(1).alias("judge"))
    b = textclf.keep(_nb(spark, sf)[0], 0.5).join(table(spark, sf, "labels"), "doc_id", "left_semi").select("doc_id", F.lit(1).alias("linear"))
    return a.join(b, "doc_id", "full").groupBy(F.coalesce("judge", F.lit(0)).alias("judge"), F.coalesce("linear", F.lit(0)).alias("linear")).agg(F.count("*").alias("n"))


_PLAIN = tuple(s for s in normalise.STEPS if s != "lemmas")


@query("m27_normalised_tokens", f"SELECT doc_id, len(t) AS n_tokens, md5(array_to_string(t, ' ')) AS tokens_md5 FROM (SELECT doc_id, {normalise.tokens_sql('text', _PLAIN)} AS t FROM documents)")
def m27(spark, sf):
    t = texts(spark, sf, "documents").select("doc_id", normalise.tokens(F.col("text"), _PLAIN).alias("t"))
    return t.select("doc_id", F.size("t").cast("long").alias("n_tokens"), F.md5(F.array_join("t", " ").cast("binary")).alias("tokens_md5"))


@query("m27_lemmatised_tokens")
def m27_lemmas(spark, sf):
    return table(spark, sf, "benchmark").select("item_id", F.array_join(normalise.tokens(F.col("text")), " ").alias("tokens"))


_VARIANTS = {"all": _PLAIN, "none": (), **{f"without_{s}": tuple(x for x in _PLAIN if x != s) for s in _PLAIN}}


@query("m27_step_ablation", " UNION ALL ".join(f"SELECT '{n}' AS variant, count(*) AS tokens, count(DISTINCT w) AS distinct_tokens FROM (SELECT unnest({normalise.tokens_sql('text', s)}) AS w FROM benchmark)" for n, s in _VARIANTS.items()))
def m27_steps(spark, sf):
    b = table(spark, sf, "benchmark")
    return union_all([b.select(F.explode(normalise.tokens(F.col("text"), s)).alias("w")).agg(F.lit(n).alias("variant"), F.count("*").alias("tokens"), F.countDistinct("w").alias("distinct_tokens")) for n, s in _VARIANTS.items()])


@query("w07_normaliser_ablation")
def w07(spark, sf):
    """Recall on an all-positive benchmark of a classifier trained on labelled documents, with and without the normaliser.

    The items are printed as exercises are: in capitals, each word numbered. Only the normaliser sees the same words in them.
    """
    d = cut(_split(spark, sf).select("doc_id", "text", "y", "split"))
    shown = F.array_join(F.transform(F.split("text", " "), lambda w, k: F.concat_ws(" ", F.concat((k + 1).cast("string"), F.lit(".")), F.upper(w))), " ")
    b = table(spark, sf, "benchmark").select("item_id", shown.alias("text"))
    out = []
    for name, steps in (("raw", ()), ("normalised", normalise.STEPS)):
        t = normalise.tokens(F.col("text"), steps)
        model = textclf.train(d.where("split = 'train'").select("text", "y"), ngrams=1, tokens=t)
        scored = textclf.predict(b, model, ["item_id"], t)
        out.append(scored.agg(F.lit(name).alias("variant"), F.count("*").alias("items"), F.round(F.avg((F.col("prob") >= 0.5).cast("double")), 4).alias("accuracy")))
    return union_all(out)
