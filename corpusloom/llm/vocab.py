"""Where vocabulary files are, and how documents are turned into ids by a public tokenizer's library."""

from __future__ import annotations

import json
import os
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

from corpusloom.llm.merges import MergeReplay
from corpusloom.llm.worker import held

#: Entries of a worker's cache of pieces; beyond it the cache starts anew.
CACHE = 250_000
#: Characters below the combining marks, without controls and other white space: composed already, one lower case each.
_LATIN = regex.compile(r"[\x21-\x7e\xa1-\u024f]*+").fullmatch
_WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall


#: Signs that are a word of their own behind letters.
_STOPS = frozenset(".,;:!?")


def _byte_letters() -> list[str]:
    """The letter that byte-level vocabularies write for each byte: printable ones themselves, others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def at(name: str, folder: str | None = None) -> str:
    """The place of a vocabulary file: in a folder, or where the package of public tokenizers has it."""
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def blocks(batches: Iterator[pa.RecordBatch], chars: int) -> Iterator[tuple[pa.Array, list[str]]]:
    """Ids and texts of (id, text) batches, in blocks of about so many characters; nulls as empty texts."""
    for batch in batches:
        start, size, texts = 0, 0, []
        for k, x in enumerate(batch.column(1)):
            texts.append(x.as_py() or "")
            size += len(texts[-1])
            if size >= chars:
                yield batch.column(0).slice(start, k + 1 - start), texts
                start, size, texts = k + 1, 0, []
        if texts:
            yield batch.column(0).slice(start), texts


class Pieces:
    """Little-endian 32-bit ids of texts by a word-end BPE that lower-cases, drops white space and joins nothing across it.

    Texts are cut at spaces and line feeds, which every engine counts as white space, and each piece is encoded once
    while it stays in the cache. Pieces of printable Latin letters, digits and signs go through the merge replay, all
    others through the tokenizer itself. The result equals encoding whole texts with it; tests hold it against that.
    The strings of special tokens stand for these tokens, as the tokenizer has it, or with special off are ordinary text.
    """

    def __init__(self, path: str, cache: int = CACHE, special: bool = True):
        self.cache = cache
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = not special
        with open(path, encoding="utf-8") as f:
            whole = json.load(f)
        model = whole["model"]
        names = [t["content"] for t in whole["added_tokens"]] if special else []
        assert not any(set(x) & set(" \n") or t["lstrip"] or t["rstrip"] for x, t in zip(names, whole["added_tokens"], strict=False))  # no cut goes through one
        self.special = regex.compile("|".join(map(regex.escape, names))).search if names else None
        ids, end = model["vocab"], model["end_of_word_suffix"]
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.replay = MergeReplay({(ids[a], ids[b]): k for k, (a, b) in reversed(list(enumerate(merges)))}, np.array([ids[a + b] for a, b in merges], np.int32), max(ids.values()) + 1)
        letters = _byte_letters()
        assert set(letters) == set(ByteLevel.alphabet())
        self.inner, self.final = (np.array([ids[c + x] for c in letters], np.int32) for x in ("", end))
        self.known: dict[str, bytes] = {}

    def _ids(self, words: list[str]) -> Iterator[bytes]:
        """Of lower-case words, each one match of the pattern."""
        raw = [w.encode() for w in words]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        data = np.frombuffer(b"".join(raw), np.uint8)
        first, last = self.inner[data], np.cumsum(sizes) - 1
        first[last] = self.final[data[last]]
        ids, counts = self.replay.encode(first, sizes)
        flat, stops = ids.astype("<u4").tobytes(), (4 * np.cumsum(counts)).tolist()
        return map(flat.__getitem__, map(slice, [0, *stops], stops))

    def _learn(self, new: set[str]) -> None:
        letters, mixed, others = [], {}, []
        for p in new:
            if not (p.isascii() and p.isprintable() or _LATIN(p)) or "\u0130" in p or self.special and "<" in p and self.special(p):
                others.append(p)
            elif p.isalpha():  # one word
                letters.append(p)
            elif p[:-1].isalpha() and p[-1:] in _STOPS:  # two
                mixed[p] = (p[:-1].lower(), p[-1])
            else:
                mixed[p] = _WORDS(p.lower())
        # Each distinct word goes through the replay once, whatever case or sign it comes with; what is known doesn't.
        lowered = [p.lower() for p in letters]
        words = set(chain(lowered, chain.from_iterable(mixed.values())))
        of = {w: self.known[w] for w in words.intersection(self.known)}
        rest = list(words.difference(of))
        of.update(zip(rest, self._ids(rest), strict=True) if rest else ())
        self.known.update(zip(letters, map(of.__getitem__, lowered), strict=True))
        self.known.update((p, b"".join(map(of.__getitem__, x))) for p, x in mixed.items())
        for a in range(0, len(others), 10_000):
            some = others[a : a + 10_000]
            for piece, x in zip(some, self.tokenizer.encode_batch_fast(some, add_special_tokens=False), strict=True):
                self.known[piece] = np.array(x.ids, "<u4").tobytes()

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        """Splitting and finding the distinct pieces is Arrow's, looking up their ids Python's, laying ids out numpy's."""
        lists = pc.split_pattern(pc.replace_substring(pa.array(texts, pa.large_string()), "\n", " "), " ")
        coded = lists.values.dictionary_encode()
        pieces, codes, bounds = coded.dictionary.to_pylist(), coded.indices.to_numpy(), lists.offsets.to_numpy()
        fresh = set(pieces).difference(self.known)
        if len(self.known) + len(fresh) > self.cache:  # what these texts need stays
            now = set(pieces)
            self.known = {p: ids for p, ids in self.known.items() if p in now}
        self._learn(fresh)
        found = list(map(self.known.__getitem__, pieces))
        flat = np.frombuffer(b"".join(found), "<u4")
        sizes = np.fromiter(map(len, found), np.int32, len(found)) // 4
        starts = (np.cumsum(sizes) - sizes).astype(np.int32)
        for a in range(0, len(bounds) - 1, 64):  # bounds memory
            cuts = bounds[a : a + 65]
            own = codes[cuts[0] : cuts[-1]]
            n = sizes[own]
            ends = np.concatenate(([0], np.cumsum(n))).astype(np.int32)
            ids = flat[np.repeat(starts[own] - ends[:-1], n) + np.arange(ends[-1], dtype=np.int32)]
            stops = ends[cuts - cuts[0]].tolist()
            for x, y in zip(stops, stops[1:], strict=False):
                yield ids[x:y].tobytes()


def pieces(path: str, cache: int = CACHE, special: bool = True) -> Pieces:
    """One for each worker process."""
    return held(f"pieces {path} {cache} {special}", lambda: Pieces(path, cache, special))
