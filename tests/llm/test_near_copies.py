"""The near-dedup stage of the pipeline against brute-force Jaccard similarity of five-word shingles."""

import importlib
import itertools
import random

import pytest

from corpusloom.llm import near_copies, simhash
from tests.conftest import SMALL

corpus_pipeline = importlib.import_module("corpus_pipeline")
SCHEMA = "doc_id long, text string"


def _similar(a: set, b: set) -> bool:
    return a == b or len(a & b) * 5 >= len(a | b) * 4 > 0


def _kept(rows: list[tuple[int, str | None]]) -> set[int]:
    """Brute force: the smallest id of each component of pairs at 0.8 or more."""
    sets = [set(near_copies.shingles(t).tolist()) for _, t in rows]
    low = [k for k, _ in rows]
    links = [(i, j) for i, j in itertools.combinations(range(len(rows)), 2) if _similar(sets[i], sets[j])]
    moved = True
    while moved:
        moved = False
        for i, j in links:
            if low[i] != low[j]:
                low[i] = low[j] = min(low[i], low[j])
                moved = True
    return {k for (k, _), least in zip(rows, low, strict=True) if k == least}


@pytest.fixture(scope="module")
def rows():
    """Texts of twelve themes, with words exchanged at random, so that similarities lie on both sides of 0.8; odd ones."""
    draw = random.Random(5)
    made = []
    for theme in range(12):
        base = [f"w{theme}x{draw.randrange(10**6)}" for _ in range(120)]
        for changes in (0, 1, 2, 3, 4, 4, 5, 5, 6, 8):
            words = base.copy()
            for at in draw.sample(range(120), changes):
                words[at] = f"n{draw.randrange(10**9)}"
            made.append(" ".join(words))
    # Long ones on both sides of a change of the sketch's width.
    base = [f"l{draw.randrange(10**9)}" for _ in range(2_200)]
    for n in (1_900, 2_000, 2_048, 2_060, 2_100, 2_200):
        words = base[:n]
        for at in draw.sample(range(n), n // 60):
            words[at] = f"n{draw.randrange(10**9)}"
        made.append(" ".join(words))
    # A passage that most documents share does not make them near copies.
    shared = " ".join(f"c{i}" for i in range(60))
    made += [f"{shared} " + " ".join(f"u{draw.randrange(10**9)}" for _ in range(40)) for _ in range(60)]
    made += ["", " ", None, "One two", "one  TWO", "one two three four five", "one two three four five six"]
    draw.shuffle(made)
    return list(enumerate(made))


@pytest.mark.parametrize(("block", "short"), [(near_copies.BLOCK, near_copies.SHORT), (7, 2)])
def test_components_equal_brute_force(spark, rows, block, short):
    found = near_copies.near_copies(spark.createDataFrame(rows, SCHEMA), block=block, short=short).where("component < node").collect()
    assert {k for k, _ in rows} - {r["node"] for r in found} == _kept(rows)


def test_stage_keeps_what_brute_force_keeps(spark, rows):
    docs = spark.createDataFrame([*rows, (None, rows[0][1])], SCHEMA)
    got = [r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, SMALL).collect()]
    assert sorted(k for k in got if k is not None) == sorted(_kept(rows)) and got.count(None) == 1


def test_no_similar_pair_survives_on_given_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in docs.collect()]
    kept = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, SMALL).collect()}
    assert kept == _kept(rows)


def test_similar_texts_beyond_four_bits(spark, rows):
    """What the stage missed: pairs at 0.8 or more whose SimHash fingerprints differ in more than four bits."""
    texts = [t for _, t in rows if t]
    sets = [set(near_copies.shingles(t).tolist()) for t in texts]
    far = [(i, j) for i, j in itertools.combinations(range(len(texts)), 2) if _similar(sets[i], sets[j]) and (simhash.fingerprint(texts[i]) ^ simhash.fingerprint(texts[j])).bit_count() > 4]
    assert len(far) > 20
    for i, j in far[:2]:
        assert near_copies.drop_near_copies(spark.createDataFrame([(0, texts[i]), (1, texts[j])], SCHEMA)).count() == 1


def test_listed_shingles_meet():
    """Sets at exactly 0.8 share a listed shingle, whatever the order."""
    draw = random.Random(3)
    import numpy as np

    for _ in range(300):
        both, rest = draw.sample(range(10**6), 100), draw.sample(range(10**6, 2 * 10**6), 25)
        cut = draw.randrange(26)
        one, other = (np.array(sorted(both + x), np.int64) for x in (rest[:cut], rest[cut:]))
        common = np.array(sorted(draw.sample(both, 40)), np.int64)
        counts = np.array([draw.randrange(2, 9) for _ in common], np.int64)
        assert set(near_copies.listed(one, common, counts).tolist()) & set(near_copies.listed(other, common, counts).tolist())


def test_whole_pipeline_keeps_one_of_each_component(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:2]:
        stage(spark, docs, SMALL).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
    want = _kept([(r["doc_id"], r["text"]) for r in docs.collect()])
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, SMALL).collect()} == want


def _group(n: int = 80) -> list[str]:
    """Near copies of one text, each with one other word exchanged: nearly all pairs are at 0.8 or more."""
    base = [f"g{i}" for i in range(150)]
    return [" ".join([*base[:k], f"other{k}", *base[k + 1 :]]) for k in range(n)]


def test_a_list_of_near_copies_costs_a_pair_a_member():
    import numpy as np

    sets = [near_copies.shingles(t) for t in _group()]
    sizes, sketches = np.array([len(s) for s in sets]), [np.array(near_copies.parities(s), np.int64).view(np.uint64) for s in sets]
    forest, whole = (sum(len(j) for _, j in near_copies.search(sizes, sketches, np.arange(len(sets)), f)) for f in (True, False))
    assert forest == len(sets) - 1 and whole > 20 * len(sets)


def test_search_meets_sketches_of_two_widths():
    import numpy as np

    long_, other = np.random.default_rng(3).integers(0, 1 << 60, (2, 1_100))
    sketches = [np.array(near_copies.parities(s), np.int64).view(np.uint64) for s in (long_, long_[:1_000], other[:1_000])]
    assert len(sketches[0]) == 2 * len(sketches[1])
    assert [(i.tolist(), j.tolist()) for i, j in near_copies.search(np.array([1_100, 1_000, 1_000]), sketches, np.arange(3))] == [([0], [1])]


def test_stage_takes_candidates_from_the_fingerprints(spark, rows, monkeypatch):
    """The byte-position index of SimHash fingerprints runs in the stage, on the fingerprints of five-word shingles."""
    seen = []

    def links(nodes, *args, **kwargs):
        seen.append({r["fp"] for r in nodes.collect()})
        return simhash.links(nodes, *args, **kwargs)

    monkeypatch.setattr(near_copies, "links", links)
    near_copies.near_copies(spark.createDataFrame(rows, SCHEMA)).count()
    assert seen == [{near_copies.fingerprint(near_copies.shingles(t)) for _, t in rows}]


def test_fingerprint_is_that_of_the_text():
    """Of distinct shingles both ways give the same bits."""
    text = _group(1)[0]
    assert near_copies.fingerprint(near_copies.shingles(text)) % 2**64 == simhash.fingerprint(text, 5)
