"""Nulls in any column, empty and very long texts, ties, repeated rows, empty tables, clashing names; the whole pipeline."""

import hashlib
import importlib
import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusloom.llm import bpe, exact_dedup, flac, html_text, licences, near_copies, packing, pii, simhash, token_files, toxicity, vocab
from tests.conftest import SMALL
from tests.llm.test_ops import plain_base, plain_components, plain_fingerprint

corpus_pipeline = importlib.import_module("corpus_pipeline")
WORD, BYTE = vocab.at("word_bpe_49k.json"), vocab.at("byte_bpe_multi_50k.tiktoken")
CLASH = "h fp key rep slice owner bin part offset score label toxic word count n kept salt keep_id group_size text_sha256 component_id __h __sha __word __maybe __text __base __spans piece start length file block ids media url html".split()
OPERATORS = {
    "html": lambda d: html_text.extract(d, "doc_id", "lang", "text"),
    "simhash": simhash.near_duplicates,
    "pii": lambda d: pii.digests(d, pii.fit(d)),
    "licences": licences.scan,
    "token_files": lambda d: token_files.document_counts(d, WORD, 49407),
    "toxicity": lambda d: toxicity.score(d, toxicity.fit(d, d.select("doc_id", F.lit(1).alias("toxic")))),
    "flac": flac.digests,
    "packing": lambda d: packing.pack(packing.document_pieces(d, WORD))[0],
    "bpe": lambda d: bpe.digests(d, BYTE),
    "exact_dedup": exact_dedup.exact_duplicates,
}
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def odd(spark):
    long_ = "long text of words " * 40_000
    rows = [(1, "same text here", "en", "s", 14), (2, "same text here", None, "s", 14), (3, None, None, None, None), (4, "", "de", "s", 0), (5, " \n ", "de", "s", 3), (6, long_, "en", "s", len(long_)), (7, "x" * 300_000, "en", "s", 300_000), (None, "no id", "en", "s", 5), (8, "tie", "en", None, 3), (8, "tie", "en", None, 3)]
    df = spark.createDataFrame(rows, DOCS)
    return df.withColumns({c: F.lit("clash") for c in CLASH})


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_odd_rows(spark, name):
    out = OPERATORS[name](odd(spark)).toPandas()
    per_row = out if name != "packing" else out[out["piece"] == 0]
    assert len(per_row) == 10


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_empty_tables(spark, name):
    out = OPERATORS[name](spark.createDataFrame([], DOCS))
    assert out.count() == 0 and out.columns


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_equal_texts_give_equal_values(spark, name):
    out = OPERATORS[name](odd(spark).where("doc_id in (1, 2)")).toPandas()
    out = out.set_index(out.columns[0])
    own = [c for c in out.columns if c not in ("url", "kept", "held_out", "ordinal", "start_token", "file", "sequence_id", "offset")]
    assert out.loc[1, own].tolist() == out.loc[2, own].tolist()


@pytest.mark.parametrize("stage", [s for s, _ in corpus_pipeline.STAGES])
@pytest.mark.parametrize("empty", [False, True])
def test_stages_on_odd_rows(spark, stage, empty):
    docs = spark.createDataFrame([], DOCS) if empty else odd(spark)
    out = dict(corpus_pipeline.STAGES)[stage](spark, docs, SMALL)
    if stage != "best_fit_packing":
        assert out.columns == docs.columns
    assert (out.count() == 0) == empty


def test_stages_in_order():
    assert [s for s, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "simhash_near_dedup", "pii", "best_fit_packing"]


def test_pipeline_equals_brute_force(spark, tmp_path):
    """Each stage's decisions, over all that its predecessor kept."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        stage(spark, docs, SMALL).write.parquet(str(tmp_path / name))
        before = {r["doc_id"]: r for r in docs.collect()}
        docs = spark.read.parquet(str(tmp_path / name))
        kept[name] = (before, {r["doc_id"]: r for r in docs.collect()})
    before, after = kept["toxicity"]
    model = toxicity.fit(spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet"))
    bad = {d for d, r in before.items() if model.probability(np.clip(toxicity.margins_of_texts(model, [r["text"]]), -2, 2))[0] >= 0.3}
    assert set(after) == set(before) - bad
    before, after = kept["exact_dedup"]
    best = {}
    for d, r in before.items():
        best[r["text"]] = max(d, best.get(r["text"], -1))
    assert set(after) == set(best.values())
    before, after = kept["simhash_near_dedup"]
    comp = plain_components({d: plain_fingerprint(r["text"]) for d, r in before.items()})
    assert set(after) == set(comp.values())
    before, after = kept["pii"]
    assert set(after) == set(before)
    tags = ("[EMAIL]", "[IP]", "[CARD]", "[PHONE]")
    for d, r in before.items():
        spans, out, at = plain_base(r["text"]), [], 0
        for a, k, e in spans:
            if a >= at:
                out += [r["text"][at:a], tags[k]]
            at = max(at, e)
        if spans:
            assert all(t in after[d]["text"] for t in {tags[k] for _, k, _ in spans})
        assert after[d]["n_chars"] == len(after[d]["text"]) if spans else True
        want = "".join([*out, r["text"][at:]])
        assert after[d]["text"] == want or len(after[d]["text"]) < len(want)  # the trees may add spans
    packed = stages["best_fit_packing"](spark, docs, SMALL).toPandas()
    assert set(packed["doc_id"]) == set(after) and packed.groupby("sequence_id")["length"].sum().max() <= 4096
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, SMALL).collect()} == set(after)


def test_later_stages_at_five_words_and_similarity(spark, tmp_path):
    """Near-dedup by the similarity that stages take, and what follows it, over all that the stage before kept."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    stages, kept = dict(corpus_pipeline.STAGES), {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        stage(spark, docs, SMALL).write.parquet(str(tmp_path / name))
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        docs = spark.read.parquet(str(tmp_path / name))
        kept[name] = (before, {r["doc_id"]: r["text"] for r in docs.collect()})
    before, after = kept["simhash_near_dedup"]
    sets = {d: set(near_copies.shingles(t).tolist()) for d, t in before.items()}
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        if sets[a] and sets[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            x, y = sorted((root(a), root(b)))
            parent[y] = x
    blank = [d for d, s in sets.items() if not s]
    assert {d for d in after if sets[d]} == {root(d) for d, s in sets.items() if s} and len([d for d in after if not sets[d]]) <= len(blank)
    before, after = kept["pii"]
    assert set(after) == set(before)
    for d, text in before.items():
        for a, k, e in plain_base(text):
            assert ("[EMAIL]", "[IP]", "[CARD]", "[PHONE]")[k] in after[d]
    packed = stages["best_fit_packing"](spark, docs, SMALL).toPandas()
    assert set(packed["doc_id"]) == set(after) and packed.groupby("sequence_id")["length"].sum().max() <= 4096
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, SMALL).collect()} == set(after)


def test_digest_of_no_spans(spark):
    r = pii.digests(spark.createDataFrame([(1, "none")], "doc_id long, text string"), pii.Boosted()).first()
    assert r["base_sha256"] == hashlib.sha256(b"").hexdigest() and r["spans"] == ""
