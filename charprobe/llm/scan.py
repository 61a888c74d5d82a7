"""Words of many texts at once, straight from Arrow's buffers: places, documents and 64-bit hashes.

A word is a maximal run of bytes other than the six ASCII white spaces; no word crosses two texts. Its hash is a
polynomial of its bytes modulo 2**64, taken from running sums, so no word is ever made a Python object. Buffers are
worked on in windows that end at a text's end or at white space, so memory follows the window and the longest word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
WINDOW = 1 << 18
#: An odd base of the polynomial, and odd factors that stir the sums (fixed values).
BASE = 0x9E3779B97F4A7C15
STIR = U64(0xD6E8FEB86659FD93)

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: What a byte adds: itself and 1; or its lower case (A-Z alone) and 1.
AS_IS = np.arange(1, 257, dtype=U64)
FOLDED = AS_IS.copy()
FOLDED[65:91] += U64(32)

_powers = [np.ones(1, U64), np.ones(1, U64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**0 to BASE**(n - 1), and their inverses, modulo 2**64."""
    while len(_powers[0]) < n:
        m = len(_powers[0])
        for k, base in enumerate((BASE, pow(BASE, -1, 1 << 64))):
            _powers[k] = np.concatenate([_powers[k], _powers[k] * U64(pow(base, m, 1 << 64))])
    return _powers[0], _powers[1]


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of the spans [start, end) of the values, whatever stands around them."""
    up, down = powers(len(values))
    sums = np.empty(len(values) + 1, U64)
    sums[0] = 0
    np.cumsum(values * up[: len(values)], out=sums[1:])
    h = (sums[ends] - sums[starts]) * down[starts]
    h ^= h >> U64(32)
    h *= STIR
    h ^= h >> U64(29)
    return h


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All texts' bytes one after another, and where each begins (one more than there are texts); null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    lo, hi = int(at[0]), int(at[-1])
    return (np.frombuffer(data, np.uint8)[lo:hi] if data is not None else np.zeros(0, np.uint8)), at - lo


def slices(source: Iterator[pa.RecordBatch], column: int = 1, size: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batches in parts of about ``size`` bytes of text (a longer text alone), without a copy: a batch's rows are
    bounded by their number, not by their length."""
    for batch in source:
        at, lo = text_buffer(batch.column(column))[1], 0
        while lo < batch.num_rows:
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + size, "right")) - 1)
            yield batch.slice(lo, hi - lo)
            lo = hi


def windows(data: np.ndarray, at: np.ndarray, size: int = WINDOW) -> Iterator[tuple[int, int]]:
    """Runs of the buffer of about ``size`` bytes; each ends where a text ends or before white space."""
    lo, n = 0, len(data)
    while lo < n:
        hi = lo + size
        if hi >= n:
            hi = n
        else:
            ends = int(np.searchsorted(at, hi, "right")) - 1
            if at[ends] > lo:
                hi = int(at[ends])
            else:  # one text is longer than a window: up to the next white space, or the text's end
                stop = int(at[ends + 1])
                while hi < stop:
                    gap = np.flatnonzero(SPACE[data[hi : min(stop, hi + 4096)]])
                    if len(gap):
                        hi += int(gap[0])
                        break
                    hi = min(stop, hi + 4096)
        yield lo, hi
        lo = hi


class Words:
    """The words of a column of texts: ``hash`` of each, its ``start`` and ``end`` in ``data``, and ``first``: the number
    of the first word of each text (one more than there are texts)."""

    def __init__(self, column: pa.Array, fold: bool = False) -> None:
        self.data, self.at = text_buffer(column)
        table, hashes, starts, ends = FOLDED if fold else AS_IS, [], [], []
        opens = np.zeros(len(self.data) + 1, bool)
        opens[self.at] = True
        for lo, hi in windows(self.data, self.at):
            part = self.data[lo:hi]
            inside = ~SPACE[part]
            begin = inside.copy()
            begin[1:] &= ~inside[:-1] | opens[lo + 1 : hi]
            close = inside.copy()
            close[:-1] &= ~inside[1:] | opens[lo + 1 : hi]
            a, b = np.flatnonzero(begin), np.flatnonzero(close) + 1
            hashes.append(span_hashes(table[part], a, b))
            starts.append(a + lo)
            ends.append(b + lo)
        whole = lambda x, kind: np.concatenate(x) if x else np.zeros(0, kind)
        self.hash, self.start, self.end = whole(hashes, U64), whole(starts, np.int64), whole(ends, np.int64)
        self.first = np.searchsorted(self.start, self.at)
        self.n = len(self.at) - 1

    def of(self, k: int) -> np.ndarray:
        """Hashes of the words of text k, in order."""
        return self.hash[self.first[k] : self.first[k + 1]]

    def text(self, k: int) -> bytes:
        return self.data[self.at[k] : self.at[k + 1]].tobytes()
