"""What a reviewer found in queries on odd inputs and on larger tables."""

import duckdb
import pytest
from pyspark.errors import AnalysisException

from corpusloom.operators import vectors
from corpusloom.plans.registry import ORACLES, QUERIES
from tests.conftest import SMALL
from tests.test_oracles import rows


@pytest.mark.parametrize("name", ["m28_parallel_lists", "m34_reattach", "m34_reattach_null"])
def test_pages_without_places(spark, tmp_path, name):
    """Pages without html or segments, and one whose only image is not fetched."""
    lost = next(u for u in (f"http://h/{k}" for k in range(99)) if int(__import__("hashlib").md5(u.encode()).hexdigest()[:7], 16) % 100 >= 64)
    pages = [(1, "http://a/", "<b>none</b>"), (2, "http://b/", f'<a href="{lost}">'), (3, "http://c/", f'<p>text<a href="{lost}">'), (4, "http://d/", None)]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(str(tmp_path / "pages.parquet"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet/*.parquet'")
    assert rows(QUERIES[name](spark, str(tmp_path)).toPandas()) == rows(con.execute(ORACLES[name]).df())


@pytest.mark.parametrize(("distance", "bucket"), [(1.2, 0.4), (6.0, 4.0)])
def test_near_pairs_are_those_of_the_librarys_join(spark, distance, bucket):
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector
    from pyspark.sql import functions as F

    v = spark.read.parquet(f"{SMALL}/embeddings.parquet").limit(150)
    f = v.select("vec_id", array_to_vector(F.col("embedding").cast("array<double>")).alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=4, seed=7).fit(f)
    joined = model.approxSimilarityJoin(f, f, distance, distCol="d").select(F.col("datasetA.vec_id").alias("a"), F.col("datasetB.vec_id").alias("b"), "d").collect()
    want = {(r["a"], r["b"]): round(r["d"], 9) for r in joined if r["a"] != r["b"]}
    got = {(r["a"], r["b"]): round(r["distance"], 9) for r in vectors.near_pairs_lsh(v, distance, bucket, block=40).collect()}
    assert got == {k: d for k, d in want.items() if k[0] < k[1]}
    asked = {(r["a"], r["b"]): round(r["distance"], 9) for r in vectors.near_pairs_lsh(v, distance, bucket, queries=v.where("vec_id % 10 = 0")).collect()}
    assert asked == {k: d for k, d in want.items() if k[0] % 10 == 0} and asked


def test_vector_query_asks_for_every_hundredth(spark):
    n = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    asked, most = n.where("vec_id % 100 = 0").count(), n.count()
    assert 0 < QUERIES["ops_vector_lsh"](spark, SMALL).first()["pairs"] <= asked * (most - 1)


def test_library_pairs_are_those_of_the_librarys_join(spark):
    from pyspark.ml.feature import HashingTF, MinHashLSH
    from pyspark.sql import functions as F

    from corpusloom.operators import dedup
    from corpusloom.runtime import cut

    base = [f"w{k}" for k in range(60)]
    texts = [" ".join([*base[: 60 - k], *(f"x{k}y{j}" for j in range(k))]) for k in (0, 1, 3, 5, 7, 9, 12, 14, 20)] + [" ".join(base), "one two", "", None]
    texts += [" ".join([*(f"z{g}v{j}" for j in range(30)), *(f"q{g}r{k}" for _ in range(k))]) for g in range(6) for k in range(5)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows_ = docs.select("doc_id", dedup.shingles(F.col("text")).alias("grams")).where(F.size("grams") > 0)
    same = rows_.groupBy(F.array_sort("grams").alias("g")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    f = HashingTF(binary=True, inputCol="grams", outputCol="features", numFeatures=1 << 18).transform(cut(rows_.join(same, "doc_id")))
    joined = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=8, seed=7).fit(f).approxSimilarityJoin(f, f, 0.25)
    want = {tuple(r) for r in joined.select("datasetA.doc_id", "datasetB.doc_id").collect() if r[0] < r[1]}
    assert {tuple(r) for r in dedup.library_pairs(docs).collect()} == want and len(want) > 20


@pytest.mark.parametrize("name", ["e01_published_funnel", "e02_published_image_funnel", "e05_score_table", "e06_published_means", "e07_ablation_delta", "e09_published_average", "e12_data_efficiency", "m08_collision_curve", "t01_stage_plan"])
def test_query_reads_given_tables(spark, tmp_path, name):
    """Without tables there is nothing to say; these made their rows up before."""
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_buckets_of_grams_are_sparks(spark):
    """The kernel against column functions, which cost the square of a text's words, and a long text within seconds."""
    import time

    import numpy as np
    from pyspark.sql import functions as F

    from corpusloom.operators import grams, textclf
    from corpusloom.operators.dedup import words

    docs = spark.createDataFrame([(0, "One two  three two"), (1, "one"), (2, ""), (3, None), (4, "ä 数学 b " * 9)], "doc_id long, text string")
    weights, tokens = np.random.default_rng(5).normal(size=1 << 10), words(F.col("text"))
    want = {r["doc_id"]: r["total"] for r in grams.weigh(docs, textclf._buckets(tokens, 2, len(weights)), ["doc_id"], lambda b: weights[b], mean=False).collect()}
    got = {r["doc_id"]: r["total"] for r in grams.weigh_grams(docs, tokens, ["doc_id"], weights, 2).collect()}
    assert got == pytest.approx(want)
    long_ = spark.createDataFrame([(0, " ".join(f"w{k}" for k in range(60_000)))], "doc_id long, text string")
    begun = time.perf_counter()
    assert textclf.predict(long_, textclf.Linear(weights, 0.0, 2), ["doc_id"]).count() == 1 and textclf.predict(long_, textclf.Linear(weights, 0.0, 2), ["doc_id"]).first()["prob"] >= 0
    assert time.perf_counter() - begun < 10


def _near_texts(seed: int) -> list[str | None]:
    """Near copies at many similarities and sizes, exact copies, a passage of many texts, short texts and empty ones."""
    import random

    rng = random.Random(seed)
    fresh = lambda k: [f"w{rng.randrange(10**9)}" for _ in range(k)]
    passage, out = fresh(30), ["", None, "one", "One!", "one two", "?"]
    for size in (1, 3, 8, 55, 62, 70, 120, 250, 300):
        base = fresh(size)
        out += [" ".join(base), " ".join(base).upper(), " ".join([*base, *passage])]
        out += [" ".join([*base, *fresh(max(1, int(size * share)))]) for share in (0.02, 0.1, 0.2, 0.3, 0.35, 0.5)]
        out += [" ".join(base[k:]) for k in range(1, min(size, 25), 3)]
    return out


@pytest.mark.parametrize("small", [False, True])
def test_pairs_of_lists_are_all_pairs(spark, monkeypatch, small):
    """Against brute force, also where lists are cut into blocks, cells dealt, ids broadcast in parts and names of lists shared."""
    import itertools

    from corpusloom.operators import dedup, grams, setjoin

    if small:
        for where, name, value in ((setjoin, "BLOCK", 2), (setjoin, "SHARE", 1), (setjoin, "CELL", 3), (setjoin, "HEAVY", 5), (setjoin, "IDS", 7), (dedup, "NAME", 1), (dedup, "SAMPLE", 20)):
            monkeypatch.setattr(where, name, value)
    texts = _near_texts(3)
    docs = spark.createDataFrame([*enumerate(texts), (None, texts[-1])], "doc_id int, text string").repartition(3)
    sets = {k: frozenset(grams.line_hashes((t or "").lower().replace("!", " ").replace("?", " ").encode(), 5).tolist()) for k, t in enumerate(texts)}
    least = {}
    for k, found in sets.items():
        least.setdefault(found, k)
    reps = sorted(k for found, k in least.items() if found)
    alike = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a, b in itertools.combinations(reps, 2)}
    want = {p: x for p, x in alike.items() if x >= 0.75} | {(least[f], k): 1.0 for k, f in sets.items() if f and least[f] != k}
    got = dedup.exact_pairs(docs).collect()
    assert {(r["src"], r["dst"]): r["similarity"] for r in got} == want and len(got) == len(want) > 100
    # So many tables and buckets that the library misses no pair and joins no other.
    found = dedup.library_pairs(docs, tables=24).collect()
    assert {tuple(r) for r in found} == {p for p, x in alike.items() if x > 0.75} and len(found) == len({tuple(r) for r in found})


def test_cross_check_stores_no_sets(spark):
    """Sets of all documents were stored three times before: 3.3 times the texts, in checkpoints."""
    import random

    from corpusloom.operators import dedup

    rng = random.Random(8)
    texts = [" ".join(f"w{rng.randrange(10**5)}" for _ in range(2_000)) for _ in range(150)]
    docs = spark.createDataFrame(list(enumerate([*texts, *(t + " more words" for t in texts[:15])])), "doc_id long, text string")
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(spark.sparkContext.getCheckpointDir())
    stored = lambda: hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(hadoop).getLength()
    before = stored()
    assert {tuple(r)[:2] for r in dedup.exact_pairs(docs).collect()} == {(k, 150 + k) for k in range(15)} == {tuple(r) for r in dedup.library_pairs(docs).collect()}
    assert stored() - before < sum(map(len, texts)) / 2
