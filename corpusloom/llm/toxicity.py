"""Toxicity by a subsequence string kernel with Nyström landmarks and a linear support vector machine.

Two words are as alike as the ordered, gapped triples of letters (and word ends) they share, each triple worth less the
more letters it spans. Signs between letters have decay one and occur in no landmark, so they may as well be left out:
letters that are spaced out or parted by signs make the same word. Landmarks are words, and beginnings of words, that are
far more frequent in toxic documents of a bounded labelled sample. Kernel values against the landmarks, whitened, are the
features of the machine.

It is trained on sentences. Those of clean documents are clean; those of toxic documents begin as toxic where they are
like a landmark, and are labelled anew by each round's machine. A sentence stands for its word of the highest margin.
Forms of the landmarks with a letter put in, doubled or left out are further toxic sentences. A document's evidence is the
sum of its words' margins above zero; the sum, and the sum for each hundred words, turn into a probability by a logistic
fit to the sampled documents, at the class shares of all labelled ones.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.llm.vocab import blocks
from corpusloom.llm.worker import held, trim
from corpusloom.runtime import cut, ensure_importable

#: Labelled documents of each class that a model is fitted on, at most; landmarks; rounds of labelling sentences.
SAMPLE, LANDMARKS, ROUNDS = 2500, 32, 3
DECAY, WIDTH, THRESHOLD = 0.4, 18, 0.3
BLOCK_CHARS = 300_000
_SIGNS = re.compile(r"[\W_]+")
_SENTENCE = re.compile(r"\n+|(?<=[.!?])\s+")


def units(text: str) -> list[str]:
    """Letters of the words of a lower-case text; three or more single letters in a row are one word."""
    out: list[str] = []
    run: list[str] = []
    for word in [*text.split(), "  "]:
        letters = _SIGNS.sub("", word)
        if len(letters) == 1:
            run.append(letters)
            continue
        out += ["".join(run)] if len(run) > 2 else run
        run = []
        if letters:
            out.append(letters)
    return out


def sentences(text: str) -> list[list[str]]:
    """Words of each sentence that has any; lines end sentences too."""
    return [s for s in map(units, _SENTENCE.split(text.lower())) if s]


def marked(word: str) -> str:
    return f"^{word}$"


def windows(word: str) -> list[str]:
    """A marked word, or what of a longer one is read at once: overlapping parts, of which the worst counts."""
    return [word] if len(word) <= WIDTH else [word[a : a + WIDTH] for a in range(0, len(word) - WIDTH // 2, WIDTH // 2)]


def _codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points in rows of WIDTH, zero beyond a word's end, and whose window each row is."""
    parts = [windows(w) for w in words]
    return np.array([p for own in parts for p in own], f"<U{WIDTH}").view(np.uint32).reshape(-1, WIDTH), np.repeat(np.arange(len(words)), list(map(len, parts)))


def subsequence_kernel(a: np.ndarray, b: np.ndarray, decay: float = DECAY, order: int = 3) -> np.ndarray:
    """Values for the pairs of rows of a and b (code points, zero beyond a word's end), by the usual recursion over prefixes."""
    n, la, lb = len(a), a.shape[1], b.shape[1]
    met = (a[:, :, None] == b[:, None, :]) & (a > 0)[:, :, None]
    spread = np.triu(decay ** np.maximum(np.subtract.outer(np.arange(lb), np.arange(lb)).T, 0)).astype(np.float32)
    prior = np.ones((n, la + 1, lb + 1), np.float32)
    for _ in range(order - 1):
        now = np.zeros_like(prior)
        for i in range(1, la + 1):
            now[:, i, 1:] = decay * now[:, i - 1, 1:] + (met[:, i - 1] * prior[:, i - 1, :-1] * np.float32(decay**2)) @ spread
        prior = now
    return (met * prior[:, :-1, :-1]).sum((1, 2)) * decay**2


class Letters:
    """Weights of triples of letters: a word's kernel values, or any linear function of them, is a sum over its triples."""

    def __init__(self, landmarks: list[str]):
        self.place = {c: k + 1 for k, c in enumerate(sorted(set("".join(landmarks))))}  # 0 is any other letter
        self.size = len(self.place) + 1
        self.points = np.array([ord(c) for c in self.place], np.uint32)

    def triples(self, word: str) -> np.ndarray:
        """The word's own triples with their decay, flat."""
        out = np.zeros((self.size,) * 3)
        at = [self.place.get(c, 0) for c in word]
        for i, j, k in combinations(range(len(at)), 3):
            if at[i] and at[j] and at[k]:
                out[at[i], at[j], at[k]] += DECAY ** (k - i + 1)
        return out.ravel()

    def sums(self, words: list[str], table: np.ndarray) -> np.ndarray:
        """For each word (of at most WIDTH letters) the decayed sum of table's rows over all its triples: the whole kernel."""
        out = np.zeros((len(words), table.shape[1]))
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        for n in np.unique(sizes[sizes > 2]).tolist():
            own = np.flatnonzero(sizes == n)
            codes = np.array([words[i] for i in own], f"<U{n}").view(np.uint32).reshape(-1, n)
            near = np.minimum(np.searchsorted(self.points, codes), len(self.points) - 1)
            at = np.where(self.points[near] == codes, near + 1, 0)
            total = np.zeros((len(own), table.shape[1]))
            for i in range(n - 2):
                for j in range(i + 1, n - 1):
                    pair = (at[:, i] * self.size + at[:, j]) * self.size
                    for k in range(j + 1, n):
                        total += DECAY ** (k - i + 1) * table[pair + at[:, k]]
            out[own] = total
        return out


@dataclass
class Model:
    landmarks: list[str]
    whiten: np.ndarray
    weights: np.ndarray
    bias: float
    #: Of the evidence, of the evidence for each hundred words, and the offset.
    logistic: tuple[float, float, float]
    key: str = field(init=False)

    def __post_init__(self) -> None:
        self.key = hashlib.md5(repr((self.landmarks, self.whiten.tolist(), self.weights.tolist(), self.bias, self.logistic)).encode()).hexdigest()

    def values(self) -> tuple[Letters, np.ndarray]:
        """Letters, and the table that makes a word's sums its kernel values against the landmarks, each over the landmark's own."""
        letters = Letters(self.landmarks)
        own = np.stack([letters.triples(w) for w in self.landmarks])
        return letters, (own / (own**2).sum(1, keepdims=True)).T

    def features(self, words: list[str]) -> np.ndarray:
        """Whitened kernel values of marked words."""
        letters, table = self.values()
        return letters.sums(words, table) @ self.whiten

    def margins(self, words: list[str]) -> np.ndarray:
        """Of words without marks; the worst window of longer ones."""
        out = np.full(len(words), self.bias if not self.landmarks else -np.inf)
        if not self.landmarks or not words:
            return out

        def make() -> tuple[Letters, np.ndarray]:
            letters, table = self.values()
            return letters, table @ (self.whiten @ self.weights)[:, None]

        letters, table = held(f"toxicity {self.key}", make)
        parts = [windows(marked(w)) for w in words]
        found = letters.sums([p for own in parts for p in own], table)[:, 0] + self.bias
        np.maximum.at(out, np.repeat(np.arange(len(words)), list(map(len, parts))), found)
        return out

    def logits(self, evidence: np.ndarray, n_words: np.ndarray) -> np.ndarray:
        a, b, c = self.logistic
        return a * np.log1p(evidence) + b * np.log1p(100 * evidence / np.maximum(n_words, 1)) + c

    def probability(self, logits: np.ndarray) -> np.ndarray:
        return np.exp(-np.logaddexp(0, -logits))


def evidence_of_texts(model: Model, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Each text's sum of margins above zero over all its words, and its number of words."""
    parts = [units(t.lower()) for t in texts]
    place: dict[str, int] = {}
    at = np.fromiter((place.setdefault(w, len(place)) for p in parts for w in p), np.int64)
    worth = np.maximum(0, model.margins(list(place)))
    sizes = np.fromiter(map(len, parts), np.int64, len(parts))
    return np.bincount(np.repeat(np.arange(len(parts)), sizes), worth[at], len(parts)), sizes


def margins_of_texts(model: Model, texts: list[str]) -> np.ndarray:
    """Each text's log-odds."""
    return model.logits(*evidence_of_texts(model, texts))


def scores_of_texts(model: Model, texts: list[str]) -> np.ndarray:
    return model.probability(margins_of_texts(model, texts))


def in_training(id_col: str = "doc_id") -> F.Column:
    """Rows whose crc32 of the id's text leaves another rest than 2 by 4."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4)) != 2


def _logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Coefficients and offset by Newton steps, slightly regularised so that separable classes stay finite."""
    x = np.concatenate((x, np.ones((len(x), 1))), 1)
    p = np.zeros(x.shape[1])
    for _ in range(100):
        q = 1 / (1 + np.exp(-np.clip(x @ p, -30, 30)))
        grad = x.T @ (weight * (q - y)) + 1e-3 * p
        hess = (x * (weight * q * (1 - q))[:, None]).T @ x + 1e-3 * np.eye(len(p))
        step = np.linalg.solve(hess, grad)
        p = p - step / max(1, np.abs(step).max() / 2)
        if np.abs(step).max() < 1e-8:
            break
    return p


def _svm(x: np.ndarray, y: np.ndarray, weight: np.ndarray, reg: float = 1e-5, steps: int = 3000) -> tuple[np.ndarray, float]:
    """Squared hinge loss by accelerated gradient steps; the bias is not regularised."""
    z = np.concatenate((x, np.ones((len(x), 1))), 1)
    rate = 1 / (2 * float(np.linalg.eigvalsh((z * weight[:, None]).T @ z)[-1]) + reg)
    w, v, t = np.zeros(z.shape[1]), np.zeros(z.shape[1]), 1.0
    for _ in range(steps):
        slack = np.maximum(0, 1 - y * (z @ v))
        grad = -2 * z.T @ (weight * y * slack) + reg * np.append(v[:-1], 0)
        new, t2 = v - rate * grad, (1 + (1 + 4 * t * t) ** 0.5) / 2
        v, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return w[:-1], float(w[-1])


def _variants(word: str) -> list[str]:
    """Forms of a marked toxic word: an inner letter doubled, left out, or followed by one that it lacks."""
    spare = [c for c in "xzqjkwvyneao" if c not in word][:3]
    out = []
    for i in range(2, len(word) - 1):
        out += [word[:i] + c + word[i:] for c in spare] + [word[:i] + word[i - 1] + word[i:]]
        if len(word) > 7 and i < len(word) - 2:
            out.append(word[:i] + word[i + 1 :])
    return out


def _counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Distinct words of each sampled document, and their beginnings."""
    for frame in batches:
        for a in range(0, len(frame), 64):  # bounds memory
            rows = []
            for text, y in frame.iloc[a : a + 64][["text", "toxic"]].itertuples(index=False):
                words = {w for w in map(marked, units(text.lower())) if 4 < len(w) <= WIDTH}
                rows += [(w, int(y)) for w in words.union(w[:k] for w in words for k in range(5, min(9, len(w) - 1)))]
            yield pd.DataFrame(rows, columns=["word", "toxic"])


def _cover(found: pd.DataFrame, rows: DataFrame, size: dict[int, int]) -> list[str]:
    """Landmarks by greedy cover: each is the most telling of toxic documents that no chosen one occurs in."""
    place = {w: k for k, w in enumerate(found["word"])}

    def has(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            words = [{w for w in map(marked, units(t.lower())) if len(w) <= WIDTH} for t in frame["text"]]
            yield pd.DataFrame({"at": [sorted({place[x] for w in own for x in (w, *(w[:k] for k in range(5, min(9, len(w) - 1)))) if x in place}) for own in words]})

    # A row for each sampled toxic document, each with at most len(found) numbers.
    lists = [r["at"] for r in rows.where("toxic = 1").mapInPandas(has, "at array<int>").collect()]
    met = np.zeros((len(lists), len(found)), bool)
    for k, at in enumerate(lists):
        met[k, at] = True
    n, open_, chosen = found["n"].to_numpy(float), np.ones(len(lists), bool), []
    while len(chosen) < LANDMARKS and open_.any():
        p = met[open_].sum(0)
        ratio = np.log((p + 0.5) / (size[1] + 1)) - np.log((n + 0.5) / (size[0] + 1))
        worth = np.where((p >= max(3, size[1] // 200)) & (ratio - 2 * np.sqrt(1 / (p + 0.5) + 1 / (n + 0.5)) > 1.0), ratio * np.sqrt(p), 0)
        best = int(worth.argmax()) if len(worth) else 0
        if not len(worth) or worth[best] <= 0:
            break
        chosen.append(found["word"][best])
        open_ &= ~met[:, best]
    # What is as telling of all toxic documents as what was chosen is a landmark too, unless one begins the other.
    least = met[:, [place[w] for w in chosen]].sum(0).min() if chosen else 0
    for w, p, miss in zip(found["word"], met.sum(0), n, strict=True):
        if len(chosen) < LANDMARKS and miss == 0 and p >= max(3, least, size[1] // 20) and not any(w.startswith(t) or t.startswith(w) for t in chosen):
            chosen.append(w)
    return chosen


def _witnesses(rows: DataFrame, model: Model, first: bool) -> pd.DataFrame:
    """(word, toxic, n): the words that stand for sentences, with the label the model gives these. Its first weights are similarity."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            found: Counter[tuple[str, bool]] = Counter()
            for text, y in zip(frame["text"], frame["toxic"], strict=True):
                parts = sentences(text)
                words = sorted({w for s in parts for w in s})
                if first:
                    letters, table = model.values()
                    value = dict(zip(words, letters.sums([marked(w)[:WIDTH] for w in words], table).max(1, initial=0), strict=True))
                else:
                    value = dict(zip(words, model.margins(words), strict=True))
                best = [max(s, key=lambda w: (value[w], w)) for s in parts]
                worst = max(map(value.__getitem__, best), default=0)
                for w in best:  # a toxic document has a toxic sentence, unless none is near
                    bad = bool(y) and (value[w] > (0.55 if first else 0) or value[w] == worst and worst > (0.4 if first else -0.5))
                    found[max(windows(marked(w)), key=len), bad] += 1
            yield pd.DataFrame([(w, bad, n) for (w, bad), n in found.items()], columns=["word", "toxic", "n"])

    # At most as many rows as the sampled documents have words.
    return rows.mapInPandas(run, "word string, toxic boolean, n long").groupBy("word", "toxic").agg(F.sum("n").alias("n")).toPandas().sort_values(["word", "toxic"])


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", rounds: int = ROUNDS) -> Model:
    """A model from at most `sample` labelled training documents of each class, chosen by a hash of their ids.

    Only training rows (see in_training) are ever looked at. Null labels and null texts are left out. Without toxic
    labels the model is the constant share of toxic ones.
    """
    spark = docs.sparkSession
    ensure_importable(spark)
    told = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").where(in_training())
    shares = {r["toxic"]: r["n"] for r in told.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    first = lambda y: told.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    chosen = first(0).unionByName(first(1)).dropDuplicates(["doc_id"])  # at most twice the sample, so small enough to send everywhere
    rows = cut(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("text is not null").join(F.broadcast(chosen), "doc_id").select("text", "toxic"))
    prior = shares.get(1, 0) / max(1, sum(shares.values()))
    constant = Model([], np.zeros((0, 0)), np.zeros(0), -1.0, (0.0, 0.0, float(np.log((prior + 1e-3) / (1 - prior + 1e-3)))))
    size = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if not size.get(0) or not size.get(1):
        return constant
    counts = rows.mapInPandas(_counted, "word string, toxic int").groupBy("word").agg(F.sum("toxic").alias("p"), F.sum(1 - F.col("toxic")).alias("n"))
    ratio = F.log((F.col("p") + 0.5) / (size[1] + 1.0)) - F.log((F.col("n") + 0.5) / (size[0] + 1.0))
    sure = ratio - 2 * F.sqrt(1 / (F.col("p") + 0.5) + 1 / (F.col("n") + 0.5))
    scored = counts.withColumn("worth", ratio * F.sqrt("p")).where((F.col("p") >= max(3, size[1] // 100)) & (sure > 1.0))
    found = scored.orderBy(F.col("worth").desc(), F.length("word").desc(), "word").limit(40 * LANDMARKS).toPandas()
    toxic = _cover(found, rows, size)
    if not toxic:
        return constant
    marks, n = _codes(toxic)[0], len(toxic)
    between = subsequence_kernel(np.repeat(marks, n, 0), np.tile(marks, (n, 1))).reshape(n, n)
    scale = np.sqrt(np.diag(between))
    values, vectors = np.linalg.eigh(between / np.outer(scale, scale))
    model = Model(toxic, vectors @ np.diag(1 / np.sqrt(np.maximum(values, 1e-2))) @ vectors.T, np.zeros(n), 0.0, (0.0, 0.0, 0.0))
    whole = [w for w in toxic if w.endswith("$") and len(w) > 6]
    for k in range(rounds):
        seen = _witnesses(rows, model, first=k == 0)
        bad = seen["toxic"].to_numpy(bool)
        if not bad.any():
            return constant
        forms = sorted({v for w in whole for v in _variants(w)}.difference(seen["word"]))
        many = seen["n"].to_numpy(float)
        weight = np.concatenate((np.where(bad, many / many[bad].sum(), 3 * many / max(1.0, many[~bad].sum())), np.full(len(forms), 0.3 / max(1, len(forms)))))
        y = np.concatenate((np.where(bad, 1.0, -1.0), np.ones(len(forms))))
        model = Model(toxic, model.whiten, *_svm(model.features([*seen["word"], *forms]), y, weight), (0.0, 0.0, 0.0))

    def judged(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for a in range(0, len(frame), 256):
                part = frame.iloc[a : a + 256]
                evidence, n_words = evidence_of_texts(model, part["text"].tolist())
                yield pd.DataFrame({"evidence": evidence, "words": n_words, "toxic": part["toxic"]})

    found = rows.mapInPandas(judged, "evidence double, words long, toxic int").toPandas()  # three numbers for each sampled document
    of, e, many = (found[c].to_numpy(float) for c in ("toxic", "evidence", "words"))
    weight = np.where(of == 1, prior / size[1], (1 - prior) / size[0]) * len(of)
    a, b, c = _logistic(np.stack((np.log1p(e), np.log1p(100 * e / np.maximum(many, 1))), 1), of, weight).tolist()
    return Model(toxic, model.whiten, model.weights, model.bias, (max(a, 0.0), max(b, 0.0), c))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted), one row for each row of docs, map-only.

    Null counts as the empty text. Null and repeated ids keep a row each; a null id is not held out. No other column is read.
    """
    ensure_importable(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, texts in blocks(batches, BLOCK_CHARS):
            yield pa.RecordBatch.from_arrays([keys, pa.array(scores_of_texts(model, texts), pa.float64())], names=["doc_id", "score"])

    scored = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, score double")
    return scored.select("doc_id", F.coalesce(~in_training(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """docs without the rows that the model rejects, all columns as they are; map-only."""
    ensure_importable(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, done = batch.schema.get_field_index(text_col), 0
            own = pa.RecordBatch.from_arrays([batch.column(at), batch.column(at)], names=["a", "b"])
            for _, texts in blocks(iter([own]), BLOCK_CHARS):
                yield batch.slice(done, len(texts)).filter(pa.array(scores_of_texts(model, texts) < threshold))
                done += len(texts)
        trim()

    return docs.mapInArrow(run, docs.schema)
