"""Token counts of documents in flat, unindexed token files, by a scan for separators.

A token file is a run of ids of fixed width, each document followed by an end-of-document id, in blocks that take no
notice of documents. Every block is searched by itself, vectorised; what crosses blocks is stitched by a prefix scan over
the blocks' sizes and last separators. No index is read or needed.
"""

from __future__ import annotations

from collections.abc import Iterator
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from corpusloom.llm import vocab
from corpusloom.runtime import cut, ensure_importable, remove, shared_dir

BLOCK_BYTES, BLOCK_CHARS = 1 << 18, 3_000_000


def write_flat(docs: DataFrame, folder: str, path: str, end_id: int, width: int = 2, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK_BYTES) -> None:
    """Tokenises docs into token files under folder: rows (file, block, data), and rows (file, first, ids) of each file's documents in order.

    Null texts are empty documents: a separator only. Strings of special tokens in a text are ordinary text, so that none
    becomes a separator.
    """
    ensure_importable(docs.sparkSession)
    kind, key_type = docs.schema[id_col].dataType.simpleString(), to_arrow_type(docs.schema[id_col].dataType)
    end = np.array([end_id], f"<u{width}").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, file, at, held, first = vocab.pieces(path, special=False).encode, TaskContext.get().partitionId(), 0, bytearray(), 0
        for keys, texts in vocab.blocks(batches, BLOCK_CHARS):
            for ids in encode(texts):
                held += np.frombuffer(ids, "<u4").astype(f"<u{width}").tobytes() + end
            n = len(held) // block
            rows = [(file, at + k, bytes(held[k * block : (k + 1) * block]), None, None) for k in range(n)]
            del held[: n * block]
            at += n
            rows.append((file, None, None, first, keys.to_pylist()))
            first += len(texts)
            yield _batch(rows)
        if held:
            yield _batch([(file, at, bytes(held), None, None)])

    def _batch(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int32(), pa.int64(), pa.binary(), pa.int64(), pa.list_(key_type))
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["file", "block", "data", "first", "ids"])

    both = docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"file int, block bigint, data binary, first bigint, ids array<{kind}>")
    both.write.mode("overwrite").option("compression", "zstd").option("parquet.block.size", 16 << 20).parquet(folder)


def read_raw(spark, path: str, block: int = BLOCK_BYTES) -> DataFrame:
    """(file, block, data) of raw binary token files, for files that others wrote; each file is cut into blocks as it is read."""
    ensure_importable(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                raw = data.as_buffer()
                cuts = range(0, max(1, raw.size), block)
                for a in cuts:
                    yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([a // block], pa.int64()), pa.array([raw[a : a + block].to_pybytes()], pa.binary())], names=["file", "block", "data"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "file string, block bigint, data binary")


def count_tokens(blocks: DataFrame, end_id: int, width: int = 2) -> DataFrame:
    """(file, ordinal, start_token, n_tokens): each document's place in its file and its ids without the separator.

    blocks: (file, block, data), blocks of a file numbered in order. Ids behind the last separator are a document too.
    """
    ensure_importable(blocks.sparkSession)
    kind = blocks.schema["file"].dataType.simpleString()

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, ends = [], []
            for data in batch.column(2):
                ids = np.frombuffer(data.as_buffer(), f"<u{width}")
                sizes.append(len(ids))
                ends.append(np.flatnonzero(ids == end_id))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int64()), pa.array(ends, pa.list_(pa.int64()))], names=["file", "block", "size", "ends"])

    found = blocks.select("file", "block", "data").mapInArrow(search, f"file {kind}, block bigint, size bigint, ends array<bigint>")
    before = W.partitionBy("file").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    placed = found.withColumn("base", F.coalesce(F.sum("size").over(before), F.lit(0))).withColumn("seen", F.coalesce(F.sum(F.size("ends")).over(before), F.lit(0)))
    placed = placed.withColumn("ends", F.transform("ends", lambda x: x + F.col("base")))
    placed = placed.withColumn("begin", F.coalesce(F.max(F.get("ends", F.size("ends") - 1)).over(before) + 1, F.lit(0)))
    closed = placed.select("file", "seen", F.col("begin"), F.posexplode("ends").alias("k", "end"), "ends").select(
        "file", (F.col("seen") + F.col("k")).alias("ordinal"), F.when(F.col("k") == 0, F.col("begin")).otherwise(F.get("ends", F.col("k") - 1) + 1).alias("start_token"), "end"
    )
    tails = placed.groupBy("file").agg(F.sum(F.size("ends")).alias("ordinal"), F.coalesce(F.max(F.get("ends", F.size("ends") - 1)) + 1, F.lit(0)).alias("start_token"), F.sum("size").alias("end")).where("end > start_token")
    return closed.unionByName(tails).select("file", F.col("ordinal").cast("long").alias("ordinal"), "start_token", (F.col("end") - F.col("start_token")).alias("n_tokens"))


def document_counts(docs: DataFrame, path: str, end_id: int, width: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, file, ordinal, start_token), one row for each row of docs, through token files in the shared folder.

    Null texts have no tokens; null and repeated ids keep a row each; other columns are not read. The token files are
    deleted when the counts are stored.
    """
    spark = docs.sparkSession
    folder = f"{shared_dir(spark)}/tokens-{uuid4().hex}"
    write_flat(docs, folder, path, end_id, width, id_col, text_col)
    both = spark.read.parquet(folder)
    counts = count_tokens(both.where("block is not null").select("file", "block", "data"), end_id, width)
    names = both.where("first is not null").select("file", "first", F.posexplode("ids").alias("k", "doc_id")).select("file", (F.col("first") + F.col("k")).alias("ordinal"), "doc_id")
    out = cut(counts.join(names, ["file", "ordinal"]).select("doc_id", "n_tokens", "file", "ordinal", "start_token"))
    remove(spark, folder)
    return out
