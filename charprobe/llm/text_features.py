"""Hashed word and character n-grams of texts, and sums of linear weights over them.

A model on these features is a vector of weights: one part for hashed words, one for hashed pairs of words, one
for hashed byte triples, and one for a few shapes of the text. A text's value of a hashed feature is its share
among the text's features of that kind, times 10, so long and short texts compare.
Words are maximal runs without the six ASCII white spaces, case kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import MULTIPLIERS, WordHasher, batches, texts_of

U64 = np.uint64
WORD_BITS, PAIR_BITS, CHAR_BITS = 16, 16, 15
SHAPES = 8
WORDS, PAIRS, CHARS = 1 << WORD_BITS, 1 << PAIR_BITS, 1 << CHAR_BITS
SIZE = WORDS + PAIRS + CHARS + SHAPES
SCALE = 10.0

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
SYMBOL = np.zeros(256, bool)
SYMBOL[list(b"#*$%&|<>")] = True
UPPER = np.zeros(256, bool)
UPPER[65:91] = True
DIGIT = np.zeros(256, bool)
DIGIT[48:58] = True
MARK = np.zeros(256, bool)
MARK[list(b"!?,.;:")] = True
START = np.ones(256, bool)
START[128:192] = False


def trigrams(data: np.ndarray) -> np.ndarray:
    x = data.astype(np.uint32)
    x = x[:-2] | x[1:-1] << np.uint32(8) | x[2:] << np.uint32(16)
    return (x * np.uint32(0x9E3779B1)) >> np.uint32(32 - CHAR_BITS)


def pair_hashes(h: np.ndarray) -> np.ndarray:
    x = h[:-1] * MULTIPLIERS[0] + h[1:] * MULTIPLIERS[1]
    return ((x ^ (x >> U64(31))) * MULTIPLIERS[2]) >> U64(64 - PAIR_BITS)


def word_slots(h: np.ndarray) -> np.ndarray:
    return h >> U64(64 - WORD_BITS)


def shapes(data: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Shares of symbols, capitals, digits, marks and exclamation marks; repeated words; word length; size."""
    n, w = max(len(data), 1), max(len(h), 1)
    again = 1.0 - len(np.unique(h)) / w if len(h) else 0.0
    follows = float((h[1:] == h[:-1]).mean()) if len(h) > 1 else 0.0
    return np.array([SYMBOL[data].sum() / n, UPPER[data].sum() / n, DIGIT[data].sum() / n, MARK[data].sum() / n, again, follows, min(len(data) / w, 40.0) / 40.0, np.log1p(len(h)) / 12.0]) * SCALE


def slots(text: bytes, hasher: WordHasher) -> tuple[list[np.ndarray], np.ndarray]:
    """Feature numbers of a text's words, pairs and triples, repeats included, without empty kinds; and its shapes."""
    h = hasher(text.split())
    data = np.frombuffer(text, np.uint8)
    kinds = [word_slots(h).astype(np.int64), pair_hashes(h).astype(np.int64) + WORDS, trigrams(data).astype(np.int64) + WORDS + PAIRS if len(data) > 2 else np.zeros(0, np.int64)]
    return [k for k in kinds if len(k)], shapes(data, h)


def sparse(text: bytes, hasher: WordHasher) -> tuple[np.ndarray, np.ndarray]:
    """Ascending feature numbers and their values."""
    kinds, s = slots(text, hasher)
    index, value = [], []
    for k in kinds:
        i, c = np.unique(k, return_counts=True)
        index.append(i)
        value.append(c * (SCALE / len(k)))
    index.append(np.arange(SIZE - SHAPES, SIZE))
    value.append(s)
    return np.concatenate(index).astype(np.int32), np.concatenate(value).astype(np.float32)


def margin(text: bytes, weights: np.ndarray, hasher: WordHasher, words: list[bytes] | None = None, h: np.ndarray | None = None) -> float:
    """The weighted sum of a text's features, without building them."""
    if h is None:
        h = hasher(text.split() if words is None else words)
    data = np.frombuffer(text, np.uint8)
    total = float(shapes(data, h) @ weights[SIZE - SHAPES :])
    if len(h):
        total += float(weights[word_slots(h)].mean(dtype=np.float64)) * SCALE
    if len(h) > 1:
        total += float(weights[WORDS : WORDS + PAIRS][pair_hashes(h)].mean(dtype=np.float64)) * SCALE
    if len(data) > 2:
        total += float(weights[WORDS + PAIRS : SIZE - SHAPES][trigrams(data)].mean(dtype=np.float64)) * SCALE
    return total


class Examples:
    """Rows of sparse features, held as one run of numbers, values (single precision) and row starts; sums go over ``LUMP`` rows at a time."""

    LUMP = 256

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> None:
        self.n = len(rows)
        self.starts = np.concatenate(([0], np.cumsum([len(i) for i, _ in rows], dtype=np.int64))).astype(np.int64)
        self.index = np.concatenate([i for i, _ in rows]) if self.n else np.zeros(0, np.int32)
        self.value = np.concatenate([v for _, v in rows]) if self.n else np.zeros(0, np.float32)

    def _lumps(self) -> Iterator[tuple[int, int, slice]]:
        for lo in range(0, self.n, self.LUMP):
            hi = min(lo + self.LUMP, self.n)
            yield lo, hi, slice(self.starts[lo], self.starts[hi])

    def margins(self, weights: np.ndarray) -> np.ndarray:
        out = np.zeros(self.n)
        for lo, hi, at in self._lumps():
            out[lo:hi] = np.add.reduceat(weights[self.index[at]] * self.value[at].astype(np.float64), self.starts[lo:hi] - at.start)
        return out

    def gradient(self, slopes: np.ndarray) -> np.ndarray:
        total = np.zeros(SIZE)
        for lo, hi, at in self._lumps():
            np.add.at(total, self.index[at], self.value[at].astype(np.float64) * np.repeat(slopes[lo:hi], np.diff(self.starts[lo : hi + 1])))
        return total


class FeatureSum:
    """The sum of texts' features, each text with a factor of its own; at most ``held`` feature numbers wait to be added."""

    def __init__(self, held: int = 1 << 20) -> None:
        self.total, self.held, self.waiting = np.zeros(SIZE), held, 0
        self.index: list[np.ndarray] = []
        self.factor: list[np.ndarray] = []

    def add(self, kinds: list[np.ndarray], s: np.ndarray, factor: float) -> None:
        for k in kinds:
            self.index.append(k)
            self.factor.append(np.full(len(k), factor * SCALE / len(k)))
            self.waiting += len(k)
        self.total[SIZE - SHAPES :] += factor * s
        if self.waiting >= self.held:
            self.settle()

    def settle(self) -> np.ndarray:
        if self.index:
            self.total += np.bincount(np.concatenate(self.index), weights=np.concatenate(self.factor), minlength=SIZE)
            self.index, self.factor, self.waiting = [], [], 0
        return self.total


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


class Adam:
    def __init__(self, size: int, rate: float) -> None:
        self.m, self.v, self.t, self.rate = np.zeros(size), np.zeros(size), 0, rate

    def step(self, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m = 0.9 * self.m + 0.1 * g
        self.v = 0.999 * self.v + 0.001 * g * g
        return self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def collected(rows: DataFrame) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Features of the documents of ``rows`` (id, text; bounded by the caller) by id, as views of the Arrow buffers they came in."""
    schema = pa.schema([("doc_id", pa.int64()), ("numbers", pa.binary()), ("shares", pa.binary())])
    got = rows.mapInArrow(lambda b: batches(feature_rows(b), schema), "doc_id long, numbers binary, shares binary").toArrow()
    views = zip(got.column("doc_id").to_pylist(), got.column("numbers"), got.column("shares"))
    return {i: (np.frombuffer(n.as_buffer(), np.int32), np.frombuffer(v.as_buffer(), np.float32)) for i, n, v in views}


def feature_rows(source: Iterator, first: int = 0) -> Iterator[tuple]:
    """(id, numbers, values) of each (id, text) in Arrow batches."""
    hasher = WordHasher()
    for batch in source:
        for i, text in zip(batch.column(0).to_pylist(), texts_of(batch)):
            index, value = sparse(text, hasher)
            yield i, index.tobytes(), value.tobytes()
