"""What Spark owns of training: stage plans, learning rates, context packing, instruction mixtures, chat rendering, exports."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpusloom.operators.dedup import union_all
from corpusloom.runtime import ensure_importable
from corpusloom.sources.views import hash28

IMAGE_TOKENS, CONTEXT, MAX_IMAGES = 64, 4096, 32
#: Fixed values of the three stages: name, data, trained parts, highest and last rate, warm-up steps, context, images.
STAGES = (
    ("alignment", "8 million sampled pairs", "connector", 1e-4, 0.0, 0, None, None),
    ("continued_pretraining", "the corpus", "connector, language model", 5e-5, 0.0, 0, 4096, 32),
    ("instruction_tuning", "instruction mixture", "connector, language model", 5e-6, 5e-7, 2000, 4096, None),
)


def stage_plan(spark: SparkSession) -> DataFrame:
    rows = [(k, *s, 1, 0.9, 0.95, 0.1) for k, s in enumerate(STAGES, 1)]
    return spark.createDataFrame(rows, "stage int, name string, data string, trained string, max_lr double, min_lr double, warmup int, context int, max_images int, epochs int, beta1 double, beta2 double, weight_decay double")


def learning_rate(step: Column, total: Column, top: float, low: float = 0.0, warmup: int = 0) -> Column:
    """Linear warm-up, then a half cosine from top to low."""
    part = (step - warmup) / F.greatest(total - warmup, F.lit(1))
    return F.when(step < warmup, F.lit(top) * step / F.lit(max(1, warmup))).otherwise(F.lit(low) + F.lit((top - low) / 2) * (1 + F.cos(F.pi() * part)))


def visual_tokens(images: Column, each: int = IMAGE_TOKENS) -> Column:
    return images * each


#: Documents of a packing group: what one task holds as narrow rows.
GROUP_DOCS = 1 << 16


def _grouped(docs: DataFrame, groups: int | None) -> DataFrame:
    """docs with grp, by a hash of the id; as many groups as the number of documents asks for unless told."""
    n = groups or max(1, -(-docs.count() // GROUP_DOCS))
    return docs.withColumn("grp", F.pmod(hash28(F.col("doc_id").cast("string")), F.lit(n)).cast("int"))


def pack_parallel(docs: DataFrame, context: int = CONTEXT, groups: int | None = None, each: int = IMAGE_TOKENS) -> DataFrame:
    """(doc_id, grp, example, from_token, n): a running sum of weights in each group, cut at multiples of the context.

    Weight is tokens plus `each` for an image. A document across a border is split; totals are conserved. Documents are
    spread over groups by a hash, in groups of about GROUP_DOCS, so that no window grows with the data.
    """
    weight = F.col("n_tokens") + visual_tokens(F.col("n_images"), each)
    df = _grouped(docs.select("doc_id", weight.cast("long").alias("w")), groups)
    end = F.sum("w").over(W.partitionBy("grp").orderBy("doc_id").rowsBetween(W.unboundedPreceding, 0))
    df = df.withColumn("end", end).withColumn("begin", F.col("end") - F.col("w")).where("w > 0")
    df = df.withColumn("example", F.explode(F.sequence(F.floor(F.col("begin") / context), F.floor((F.col("end") - 1) / context))))
    lo, hi = F.greatest("begin", F.col("example") * context), F.least("end", (F.col("example") + 1) * context)
    return df.select("doc_id", "grp", F.col("example").cast("long").alias("example"), (lo - F.col("begin")).alias("from_token"), (hi - lo).alias("n"))


def pack_greedy(docs: DataFrame, context: int = CONTEXT, max_images: int = MAX_IMAGES, groups: int | None = None, each: int = IMAGE_TOKENS) -> DataFrame:
    """(doc_id, grp, example, tokens, images): in id order, a new example where either limit would be passed.

    Larger documents are split first, images after text. One task holds and packs the narrow rows of a group of about GROUP_DOCS.
    """
    ensure_importable(docs.sparkSession)

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        rows, example, t, i = [], 0, 0, 0
        for d, n, m in frame.sort_values("doc_id")[["doc_id", "n_tokens", "n_images"]].itertuples(index=False):
            while n or m:
                room, spots = context - t - each * i, max_images - i
                whole = n + each * m <= room and m <= spots
                if not whole and (t or i) and (n + each * m <= context and m <= max_images or room < min(n or each, each)):
                    example, t, i = example + 1, 0, 0
                    continue
                a = min(n, room)
                b = min(m, spots, (room - a) // each)
                if not a and not b:
                    example, t, i = example + 1, 0, 0
                    continue
                rows.append((d, key[0], example, a, b))
                n, m, t, i = n - a, m - b, t + a, i + b
        return pd.DataFrame(rows, columns=["doc_id", "grp", "example", "tokens", "images"])

    df = _grouped(docs.select("doc_id", F.col("n_tokens").cast("long").alias("n_tokens"), F.col("n_images").cast("long").alias("n_images")), groups)
    return df.groupBy("grp").applyInPandas(run, "doc_id long, grp int, example long, tokens long, images long")


#: The instruction sets of the narrow mixture, of the extended one, and of the training stage (another list).
NARROW = ("MAVIS-Caption-to-QA", "MAVIS-Existing-Dataset-Augment", "MAVIS-Caption", "MAVIS-DataEngine-Geometry", "MAVIS-Meta-Question")
EXTENDED = (*NARROW, "Vflan", "VisualWebInstruct", "AI2D", "ChartQA", "DocVQA", "DVQA", "GeoQA", "DART-Math", "NuminaMath")
TRAINING = ("PGPS9K", "Geo170k", "TABMWP", "ScienceQA", "Vflan", "VisualWebInstruct", "AI2D", "ChartQA", "DocVQA", "DVQA", "GeoQA", "MAVIS")
TRAINING_TEXT = ("Math", "MetaMathQA", "DART-Math", "NuminaMath")


def compose(sources: dict[str, tuple[DataFrame, float]], key: str) -> DataFrame:
    """Rows of each source with its share kept by a hash of the key, and their source's name."""
    return union_all([df.where(hash28(F.col(key).cast("string")) % 1000 < round(1000 * w)).withColumn("mixture_source", F.lit(name)) for name, (df, w) in sources.items()])


def render_chat(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, chat): turns in order, each as a role line and its text."""
    ordered = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    return turns.groupBy("conv_id").agg(ordered.alias("m")).select("conv_id", F.size("m").cast("long").alias("n_turns"), F.array_join(F.transform("m", lambda x: F.concat(F.lit("<|"), x["role"], F.lit("|>\n"), x["text"])), "\n").alias("chat"))


def export_parquet(df: DataFrame, path: str, files: int | None = None) -> None:
    """The contract with training: Parquet, compressed, evenly dealt."""
    (df.repartition(files) if files else df).write.mode("overwrite").option("compression", "zstd").parquet(path)

