"""Byte-level BPE by replaying the merges over a whole block of distinct words (see merges.py), and decoding."""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from public_tokenizers import PATTERN
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm import vocab
from corpusloom.llm.merges import MergeReplay
from corpusloom.llm.worker import held
from corpusloom.runtime import ensure_importable

BLOCK_CHARS = 6_000_000
CACHE = 250_000
_EDGE = regex.compile(r"\s | \s|^ | $")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Codec:
    """Texts to little-endian 32-bit ids and back, with a bounded cache of words and of what stands between spaces."""

    def __init__(self, path: str):
        ranks = load_ranks(path)
        size = max(ranks.values()) + 1
        self.token = [b""] * size
        for b, r in ranks.items():
            self.token[r] = b
        self.byte = np.array([ranks[bytes([b])] for b in range(256)], np.int32)
        pairs = {(ranks[t[:k]], ranks[t[k:]]): r for t, r in ranks.items() for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks}
        self.replay = MergeReplay(pairs, None, size)
        self.split = regex.compile(PATTERN).findall
        self.words: dict[str, bytes] = {}
        self.spaced: dict[str, bytes] = {}
        self.names = [str(i) for i in range(size)]

    def _ids(self, words: list[str]) -> Iterator[bytes]:
        raw = [w.encode() for w in words]
        ids, counts = self.replay.encode(self.byte[np.frombuffer(b"".join(raw), np.uint8)], np.fromiter(map(len, raw), np.int64, len(raw)))
        flat, stops = ids.astype("<u4").tobytes(), (4 * np.cumsum(counts)).tolist()
        return map(flat.__getitem__, map(slice, [0, *stops], stops))

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        """A space between two other characters that aren't white space opens a new word, so such texts are cut there."""
        cut, whole = {}, {}
        for k, t in enumerate(texts):
            if _EDGE.search(t):
                whole[k] = self.split(t)
            else:
                cut[k] = t.split(" ")
        rest: set[str] = set()
        for p in cut.values():
            rest.update(p)
        new = rest.difference(self.spaced)
        if len(self.spaced) + len(new) > CACHE:  # what these texts need stays
            self.spaced = {p: ids for p, ids in self.spaced.items() if p in rest}
        letters = [x for x in new if x.isalpha()]  # one word with the space before it
        inside = {x: self.split(" " + x) for x in new if not x.isalpha()}
        first = {k: self.split(p[0]) for k, p in cut.items()}  # without a space before it
        words = set().union(*inside.values(), *first.values(), *whole.values())
        fresh = list(words.difference(self.words))
        if len(self.words) + len(fresh) > CACHE:
            self.words = {p: ids for p, ids in self.words.items() if p in words}
        self.words.update(zip(fresh, self._ids(fresh), strict=False))
        spaced, word = self.spaced, self.words.__getitem__
        spaced.update(zip(letters, self._ids([" " + x for x in letters]), strict=False))
        for x, parts in inside.items():
            spaced[x] = b"".join(map(word, parts))
        for k in range(len(texts)):
            if k in whole:
                yield b"".join(map(word, whole[k]))
            else:
                yield b"".join(map(word, first[k])) + b"".join(map(spaced.__getitem__, cut[k][1:]))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def codec(path: str) -> Codec:
    """One for each worker process."""
    return held(f"codec {path}", lambda: Codec(path))


def _encoder(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for ids, texts in vocab.blocks(batches, BLOCK_CHARS):
            yield pa.RecordBatch.from_arrays([ids, pa.array(list(c.encode(texts)), pa.binary())], names=["doc_id", "ids"])

    return run


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids): ids as little-endian unsigned 32-bit integers. Null and empty texts have none."""
    ensure_importable(docs.sparkSession)
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_encoder(path), f"doc_id {docs.schema[id_col].dataType.simpleString()}, ids binary")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, bytes) of (doc_id, ids)."""
    ensure_importable(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([c.decode(x.as_py() or b"") for x in b.column(1)], pa.binary())], names=["doc_id", "bytes"])

    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id {encoded.schema['doc_id'].dataType.simpleString()}, bytes binary")


def digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256), one row for each row of docs; null counts as the empty text."""
    ensure_importable(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for keys, texts in vocab.blocks(batches, BLOCK_CHARS):
            n, coded, plain = [], [], []
            for ids in c.encode(texts):
                some = np.frombuffer(ids, "<u4").tolist()
                n.append(len(some))
                coded.append(hashlib.sha256(",".join(map(c.names.__getitem__, some)).encode()).hexdigest())
                plain.append(hashlib.sha256(b"".join(map(c.token.__getitem__, some))).hexdigest())
            yield pa.RecordBatch.from_arrays([keys, pa.array(n, pa.int64()), pa.array(coded), pa.array(plain)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
