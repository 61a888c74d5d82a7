"""Ordered merge rules applied to many words at once, in array operations on symbol numbers."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa

#: Words merged together; memory is that of their letters.
BATCH = 20_000


class Rules:
    """Merge rules by their pairs of symbols; every symbol has a number, every rule the number of what it makes."""

    def __init__(self, rules: Sequence[tuple[str, str]]) -> None:
        """rules: (left, right) in order of rank."""
        self.number: dict[str, int] = {}
        for left, right in rules:
            for s in (left, right, left + right):
                self.number.setdefault(s, len(self.number))
        self.symbols = list(self.number)
        first: dict[int, int] = {}
        for rank, (left, right) in enumerate(rules):
            first.setdefault(self.number[left] << 32 | self.number[right], rank)
        self.keys = np.array(sorted(first), np.int64)
        self.rank = np.array([first[k] for k in self.keys.tolist()], np.int64)
        self.makes = np.array([self.number[a + b] for a, b in rules], np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of the rule of each pair, or as many as there are rules."""
        none = len(self.makes)
        if not len(self.keys):
            return np.full(len(left), none)
        key = left << 32 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.rank[at], none)

    def merged(self, words: Sequence[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Names of symbols; the symbols of all words one after another; and where each word begins (one more than words).

        In each round every word fuses its rule of best rank, at all its places from the left, until none has one.
        """
        names, extra = self.symbols, {}
        text = "".join(words)
        length = np.fromiter(map(len, words), np.int64, len(words))
        codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        known, place = np.unique(codes, return_inverse=True)
        for c in map(chr, known.tolist()):
            if c not in self.number:
                extra[c] = len(names) + len(extra)
        numbers = np.array([self.number.get(c, extra.get(c)) for c in map(chr, known.tolist())], np.int64)
        symbol, word = (numbers[place] if len(codes) else np.zeros(0, np.int64)), np.repeat(np.arange(len(words)), length)
        none, finished = len(self.makes), []
        while len(symbol):
            rank = np.full(len(symbol), none)
            inside = np.flatnonzero(word[1:] == word[:-1])
            rank[inside] = self.ranks(symbol[inside], symbol[inside + 1])
            start = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
            size = np.diff(np.append(start, len(word)))
            best = np.minimum.reduceat(rank, start)
            best = np.repeat(best, size)
            done = best == none
            if done.any():
                finished.append((word[done], symbol[done]))
                symbol, word, rank, best = symbol[~done], word[~done], rank[~done], best[~done]
            hit = np.flatnonzero(rank == best)
            # In a run of equal symbols the places overlap: every other one counts.
            follows = np.concatenate(([False], np.diff(hit) == 1))
            run_start = np.maximum.accumulate(np.where(follows, 0, np.arange(len(hit))))
            hit = hit[(np.arange(len(hit)) - run_start) % 2 == 0]
            symbol[hit] = self.makes[rank[hit]]
            stay = np.ones(len(symbol), bool)
            stay[hit + 1] = False
            symbol, word = symbol[stay], word[stay]
        word, symbol = (np.concatenate(x) for x in zip(*finished)) if finished else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        order = np.argsort(word, kind="stable")
        return names + list(extra), symbol[order], np.searchsorted(word[order], np.arange(len(words) + 1))

    def pieces(self, words: Sequence[str]) -> pa.Array:
        """The pieces of each word, as lists of strings."""
        parts = []
        for lo in range(0, len(words), BATCH):
            names, symbol, start = self.merged(words[lo : lo + BATCH])
            parts.append(pa.ListArray.from_arrays(pa.array(start, pa.int32()), pa.array(names, pa.string()).take(pa.array(symbol))))
        return pa.concat_arrays(parts) if parts else pa.array([], pa.list_(pa.string()))
