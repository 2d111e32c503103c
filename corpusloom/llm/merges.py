"""Replay of merges over many words at once.

Words are laid end to end. An inverted index has, for each rank, the places where a pair of neighbours can merge at it.
Ranks are applied in order, each at all its places at once, and only the pairs beside a merge are looked up again. That
equals merging word by word, lowest rank first, unless a merge makes a pair of a lower rank than itself; words where that
happens are merged one by one instead.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import numpy as np

_NONE = np.int32(2**31 - 1)
_FIRST = 512


class MergeReplay:
    def __init__(self, pairs: dict[tuple[int, int], int], makes: np.ndarray | None, size: int):
        """pairs: (left id, right id) to rank; makes: rank to the id that it makes, the rank itself if None."""
        self.pairs, self.size, self.makes = pairs, size, makes
        keys = np.array([a * size + b for a, b in pairs], np.int64)
        order = np.argsort(keys)
        self.pair_keys, self.pair_ranks = keys[order], np.fromiter(pairs.values(), np.int32, len(pairs))[order]
        self.first = np.full((_FIRST, _FIRST), _NONE, np.int32)  # of pairs of the ids that words begin with
        for (a, b), rank in pairs.items():
            if a < _FIRST and b < _FIRST:
                self.first[a, b] = rank

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of the tokens that pairs make; _NONE where they make none."""
        keys = left.astype(np.int64) * self.size + right
        at = np.minimum(np.searchsorted(self.pair_keys, keys), len(self.pair_keys) - 1)
        return np.where(self.pair_keys[at] == keys, self.pair_ranks[at], _NONE)

    def rank_of_pairs(self, pair: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        return self.rank_of(*pair)

    def one_by_one(self, ids: list[int]) -> list[int]:
        """The plain way, for the words that the replay can't settle."""
        ids = list(ids)
        while len(ids) > 1:
            rank, at = min((self.pairs.get((ids[i], ids[i + 1]), int(_NONE)), i) for i in range(len(ids) - 1))
            if rank == _NONE:
                break
            ids[at : at + 2] = [rank if self.makes is None else int(self.makes[rank])]
        return ids

    def encode(self, ids: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Words of first ids, end to end, of so many ids each: the ids that remain, and each word's number of them."""
        first = ids
        ids = ids.copy()
        n, ends = len(ids), np.cumsum(sizes)
        starts = ends - sizes
        after, before = np.arange(1, n + 1, dtype=np.int32), np.arange(-1, n - 1, dtype=np.int32)
        after[ends[sizes > 0] - 1] = -1
        before[starts[sizes > 0]] = -1
        word_of = np.repeat(np.arange(len(sizes), dtype=np.int32), sizes)
        rank, alive = np.full(n, _NONE, np.int32), np.ones(n, bool)
        has = np.flatnonzero(after >= 0)
        rank[has] = (self.first.__getitem__ if not n or ids.max() < _FIRST else self.rank_of_pairs)((ids[has], ids[after[has]]))
        waiting: dict[int, list[np.ndarray]] = defaultdict(list)
        heap: list[int] = []

        def file(places: np.ndarray) -> None:
            """Put places into the index, by rank."""
            r = rank[places]
            places, r = places[r != _NONE], r[r != _NONE]
            if not len(places):
                return
            order = np.argsort(r, kind="stable")
            places, r = places[order], r[order]
            cuts = np.flatnonzero(np.diff(r)) + 1
            for first, part in zip(r[np.concatenate(([0], cuts))].tolist(), np.split(places, cuts), strict=True):
                if first not in waiting:
                    heapq.heappush(heap, first)
                waiting[first].append(part)

        file(has)
        odd: set[int] = set()
        while heap:
            now = heapq.heappop(heap)
            lists = waiting.pop(now)
            at = lists[0] if len(lists) == 1 else np.concatenate(lists)
            at = np.sort(at[(rank[at] == now) & alive[at]])
            if not len(at):
                continue
            if len(at) > 1:  # of places that overlap, every second one, from the left
                at = at[np.concatenate(([True], at[1:] != at[:-1]))]
                chained = np.concatenate(([False], after[at[:-1]] == at[1:]))
                if chained.any():
                    spot = np.arange(len(at))
                    at = at[(spot - np.maximum.accumulate(np.where(chained, 0, spot))) % 2 == 0]
            gone = after[at]
            beyond = after[gone]
            ids[at], after[at] = now if self.makes is None else self.makes[now], beyond
            alive[gone] = False
            before[beyond[beyond >= 0]] = at[beyond >= 0]
            left = before[at]
            beside = np.concatenate((at, left[left >= 0]))
            nxt = after[beside]
            new = np.full(len(beside), _NONE, np.int32)
            new[nxt >= 0] = self.rank_of(ids[beside[nxt >= 0]], ids[nxt[nxt >= 0]])
            rank[beside] = new
            if (new < now).any():
                odd.update(word_of[beside[new < now]].tolist())
            file(beside)
        counts = np.bincount(word_of[alive], minlength=len(sizes))
        ids = ids[alive]
        if odd:
            stops = np.cumsum(counts)
            parts, done = [], 0
            for w in sorted(odd):
                fixed = np.array(self.one_by_one(first[starts[w] : ends[w]].tolist()), np.int32)
                parts += [ids[done : stops[w] - counts[w]], fixed]
                done, counts[w] = stops[w], len(fixed)
            ids = np.concatenate([*parts, ids[done:]])
        return ids, counts
