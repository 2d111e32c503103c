"""Sessions in which queries follow each other, floors of models, and operators that replace size limits, against brute force."""

import datetime as dt
import itertools
import random

import numpy as np
import pytest
from pyspark.sql import Observation
from pyspark.sql import functions as F

from corpusloom.operators import dedup, evaluate, funnel, grams, langid, sampling, textclf, training, vectors
from corpusloom.plans import pipeline
from corpusloom.plans.registry import QUERIES
from tests.conftest import SMALL

MIDDLE = "/root/testdata/sf0.01"


def words(text):
    import regex

    return [w for w in regex.sub(r"[^\p{L}\p{N}]+", " ", (text or "").lower()).split(" ") if w]


def shingle_set(text, n=5):
    w = words(text)
    return {" ".join(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def test_models_after_an_observed_frame(spark):
    """What watches a frame stays in the session; models must not carry the session with them."""
    seen = Observation("rows")
    spark.range(5).observe(seen, F.count(F.lit(1)).alias("n")).collect()
    assert seen.get["n"] == 5
    for name in ("e01_stage_ledger", "m05_logistic_metrics", "m03_langid_confusion", "b03_filter_comparison"):
        assert QUERIES[name](spark, SMALL).count() > 0


def test_floors_of_models(spark):
    r = QUERIES["m05_logistic_metrics"](spark, MIDDLE).first()
    assert (r["tp"] + r["tn"]) / (r["tp"] + r["tn"] + r["fp"] + r["fn"]) >= 0.75
    c = QUERIES["m03_langid_confusion"](spark, MIDDLE).toPandas()
    assert c.loc[c["lang"] == c["predicted"], "n"].sum() >= 0.95 * c["n"].sum()


def test_normalised_texts_are_recognised_better(spark):
    got = {r["variant"]: r["accuracy"] for r in QUERIES["w07_normaliser_ablation"](spark, MIDDLE).collect()}
    assert got["normalised"] > got["raw"] and got["normalised"] >= 0.9


def test_ledger(spark):
    df = spark.createDataFrame([(k, None if k == 9 else k % 2 == 0, k < 5) for k in range(10)], "id int, a boolean, b boolean")
    got = [tuple(r) for r in funnel.ledger(df, [("a", F.col("a")), ("b", F.col("b"))]).select("stage", "n_in", "n_out").collect()]
    assert got == [("a", 10, 5), ("b", 5, 3)]
    none = funnel.ledger(df.where("id < 0"), [("a", F.col("a"))]).first()
    assert (none["n_in"], none["n_out"], none["kept_frac"]) == (0, 0, None)


def test_signature_kernel_equals_expressions(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(40).unionByName(spark.createDataFrame([(9001, "", "en", "s", 0), (9002, None, "en", "s", 0), (9003, "One two", "en", "s", 7), (9004, "İx ẞy Σας", "en", "s", 9)], "doc_id long, text string, lang string, source string, n_chars long"))
    a = {r["doc_id"]: r["sig"] for r in dedup.signature(docs, hashes=9, family="affine31").collect()}
    b = {r["doc_id"]: r["sig"] for r in dedup.signature_expr(docs, hashes=9).collect()}
    assert a == b and 9001 not in a and 9002 not in a
    assert list(grams.spans(["a", "b", "c"], 2)) == [b"a b", b"b c"] and list(grams.spans(["a"], 2)) == [b"a"] and list(grams.spans([], 2)) == []


def test_minhash_at_its_defaults_finds_what_brute_force_does(spark):
    """112 hashes in 14 bands of 8: of pairs at 0.9 and more nearly all, and none at 0.4 or less is joined directly."""
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "text")
    sets = {r["doc_id"]: shingle_set(r["text"]) for r in docs.collect()}
    sets = {d: s for d, s in sets.items() if s}
    share = lambda a, b: len(sets[a] & sets[b]) / len(sets[a] | sets[b])
    owners = {}
    for d, s in sets.items():
        for g in s:
            owners.setdefault(g, []).append(d)
    pairs = {p for own in owners.values() if len(own) < 200 for p in itertools.combinations(sorted(own), 2)}
    near = [(a, b) for a, b in pairs if share(a, b) >= 0.9]
    banded = dedup.bands(dedup.signature(docs), 14, 8)
    edges = {tuple(sorted(r)) for r in dedup.star_edges(banded, F.col("doc_id")).collect()}
    of = {}
    for a, b in sorted(edges):
        of[b] = of.get(a, a)
    joined = sum(of.get(a, a) == of.get(b, b) for a, b in near)
    assert joined >= 0.97 * len(near) and all(share(a, b) > 0.4 for a, b in edges)


def test_exact_pairs_equal_all_pairs(spark):
    rng = random.Random(4)
    base = [" ".join(f"w{rng.randrange(60)}" for _ in range(rng.randrange(3, 40))) for _ in range(25)]
    rows = [(k, t) for k, t in enumerate(base + base[:6] * 3 + [" ".join(t.split()[:-1]) + " zz" for t in base] + [t + " yy" for t in base] + ["", None, "common words at the start " + base[0], "a b"])]
    sets = {d: shingle_set(t) for d, t in rows if words(t)}
    rep = {}
    for d in sorted(sets):
        rep.setdefault(frozenset(sets[d]), d)
    reps = sorted(rep.values())
    want = {(a, b) for a, b in itertools.combinations(reps, 2) if len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.75} | {(rep[frozenset(s)], d) for d, s in sets.items() if rep[frozenset(s)] != d}
    got = dedup.exact_pairs(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {(r["src"], r["dst"]) for r in got} == want and len(got) == len(want)
    assert dedup.exact_pairs(spark.createDataFrame([], "doc_id long, text string")).count() == 0


@pytest.mark.parametrize("k", [0, 1, 37, 300, 5000])
def test_exact_k_equals_a_sort(spark, k):
    df = spark.range(300).select(F.when(F.col("id") != 7, F.col("id")).alias("id"))
    want = [r["id"] for r in df.orderBy(F.md5(F.col("id").cast("string").cast("binary")).asc_nulls_last(), "id").limit(k).collect()]
    for bins in (1 << 16,):
        assert sorted(map(str, want)) == sorted(str(r["id"]) for r in sampling.exact_k(df, k, "id", bins).collect())


@pytest.mark.parametrize("target", [1, 2, 50, 51, 149, 150, 151, 199])
def test_cut_for_volume_equals_a_sort(spark, target):
    values = [0.5] * 100 + [k / 977 for k in range(50)] + [0.5 + 1e-12, 1 - 1e-16] * 25
    df = spark.createDataFrame([(k, float(v)) for k, v in enumerate(values)], "id int, prob double")
    assert textclf.cut_for_volume(df, target, bins=4) == sorted(values, reverse=True)[target - 1]


def test_nearest_in_blocks(spark):
    rng = np.random.default_rng(1)
    v = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(rng.normal(size=(60, 4)))], "vec_id long, embedding array<double>")
    whole, parts = (sorted(map(tuple, vectors.nearest(v.where("vec_id < 9"), v, 3, block=b).collect())) for b in (100, 2))
    assert whole == parts and len(whole) == 27


def test_contamination_in_slices(spark):
    docs, bench = (spark.read.parquet(f"{SMALL}/{t}.parquet") for t in ("documents", "benchmark"))
    whole, parts = (sorted(map(tuple, evaluate.contamination(docs, bench, most=m).collect())) for m in (1 << 24, 500))
    assert whole == parts and whole


def test_naive_bayes_by_table_and_by_join(spark):
    train = spark.createDataFrame([("good maths proof", 1), ("spam buy now", 0), ("proof of maths", 1)], "text string, y int")
    docs = spark.createDataFrame([(1, "a proof of maths maths"), (2, "buy spam"), (3, ""), (4, None), (5, "unknown")], "doc_id int, text string")
    model = textclf.nb_fit(train)
    a, b = ({r["doc_id"]: (round(r["score"], 9), round(r["prob"], 9)) for r in textclf.nb_score(docs, model, local=n).collect()} for n in (100, 0))
    assert a == b and a[1][1] > 0.5 > a[2][1] and a[3] == a[4] == a[5] == (0.0, 0.5)


def test_packing_groups_follow_the_data(spark, monkeypatch):
    monkeypatch.setattr(training, "GROUP_DOCS", 10)
    docs = spark.createDataFrame([(k, 100 + k, 0) for k in range(95)], "doc_id long, n_tokens long, n_images long")
    p = training.pack_parallel(docs)
    assert p.select("grp").distinct().count() > 5 and p.agg(F.sum("n")).first()[0] == sum(100 + k for k in range(95))


def test_the_path_keeps_what_it_should(spark):
    """A small crawl: the wrong language, a repeated URL of a year, a copy in the next snapshot, an insult, and an image to keep."""
    d = dt.date
    body = lambda t, extra="": f"<html lang='en'><body><nav><a href=/>menu</a></nav><article><p>{t}</p>{extra}</article></body></html>"
    long_ = lambda k: " ".join(f"proof{(k * 31 + j * 7) % 97} number{(k + j) % 89}" for j in range(80))
    pages = [(1, "http://a/1", body(long_(1), "<img src='https://i/1.png'><img src='http://i/2.png'>"), 0, d(2019, 1, 1), 2019), (2, "http://a/1", body(long_(2)), 1, d(2019, 7, 1), 2019), (3, "http://a/3", body(long_(3)), 0, d(2019, 1, 1), 2019),
             (4, "http://a/4", body(long_(3)), 1, d(2019, 7, 1), 2019), (5, "http://a/5", body(long_(5) + " you idiot"), 2, d(2020, 1, 1), 2020), (6, "http://a/6", body("der die das und nicht " * 20).replace("lang='en'", 'lang="de"'), 2, d(2020, 1, 1), 2020)]
    pages = [(a, u, h.replace("lang='en'", 'lang="en"'), s, t, y) for a, u, h, s, t, y in pages]
    crawl = spark.createDataFrame(pages, "rec_id long, url string, html string, snapshot_id int, snapshot_date date, year int")
    good, bad = (spark.createDataFrame([(t,) for t in x], "text string") for x in ([long_(k) for k in range(9)], ["cheap pills now " * 9, "casino bonus " * 12]))
    cfg = pipeline.Config(language="declared", classifier="bayes", precise=False)
    docs, ledger = pipeline.curate(spark, crawl, good, cfg, bad, fetched=spark.createDataFrame([("https://i/1.png",), ("http://i/2.png",)], "image_url string"))
    assert [(r["stage"], r["n_in"], r["n_out"]) for r in ledger.orderBy("step").collect()] == [("language", 6, 5), ("high_recall", 5, 5), ("within_snapshot", 5, 5), ("neighbor_snapshots", 5, 4), ("url_dedup", 4, 3), ("rules", 3, 2)]
    got = {r["rec_id"]: r["images"] for r in docs.collect()}
    assert sorted(got) == [2, 4]


def test_language_models_hold_no_session(spark):
    df = spark.createDataFrame([("the cat and the dog", "en"), ("der hund und die katze", "de")] * 5, "text string, lang string")
    model = langid.train_subword(df, iterations=5)
    assert not model.stages[-1].hasSummary
    assert {r["lang"] for r in langid.predict(df, model, ["lang"]).where("lang = predicted").collect()} == {"en", "de"}
