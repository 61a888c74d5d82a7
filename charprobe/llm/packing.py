"""Operator 4: order-preserving packing by dynamic programming.

Documents stand in the order of their ids, each as its token ids and one separator id. Windows of at most
``window`` ids are cut from that stream so that padding plus penalties is least: a cut between documents is
free, one behind a sentence costs ``sentence_penalty``, one anywhere else (only offered inside a sentence
that is longer than a window) costs ``word_penalty``. A window is padded to ``window`` ids unless its length
is a power of two; each window can be made to cost ``window_cost`` besides. As padding is linear in the length, the
best predecessor of a cut is the least of (cost - position) over the positions at most ``window`` back: a monotone
queue hands it out in constant time; the few positions a power of two back are looked up beside it.

The stream is dealt into ranges of (id, checksum), one per task; a range ends with a document. Null texts count as
empty; null ids come first; rows with equal ids follow their checksums.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_input, buckets_for
from .token_ids import ended, encoder

SCHEMA = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])
SQL_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Bytes (in UTF-8) that end a sentence or a line: . ! ? and the line break.
ENDS = (".", "!", "?", "\n")


def unpadded(window: int) -> list[int]:
    """Lengths below the window's that are not padded: the powers of two."""
    return [1 << k for k in range(window.bit_length()) if 1 << k < window]


def padding(length: int, window: int) -> int:
    return 0 if length & (length - 1) == 0 else window - length  # a full window has none either


def choose_cuts(positions: np.ndarray, penalties: np.ndarray, window: int, window_cost: float = 0.0) -> list[int]:
    """Positions (ascending, from 0, gaps of at most ``window``) at which the cheapest windows end.

    penalties[j] is what a cut at positions[j] costs. Ties go to the longer window.
    """
    n = len(positions)
    number = np.full(int(positions[-1]) + 1, -1, np.int64)  # of the candidate at each position of the stretch
    number[positions] = np.arange(n)
    late, early = [], []  # pairs of candidates that lie a power of two apart
    for length in [window, *unpadded(window)[::-1]]:
        behind = np.flatnonzero(positions >= length)
        at = number[positions[behind] - length]
        late.append(behind[at >= 0])
        early.append(at[at >= 0])
    late, early = np.concatenate(late), np.concatenate(early)
    order = np.argsort(late, kind="stable")
    late, early, e = [*late[order].tolist(), n], early[order].tolist(), 0
    pos, pen = positions.tolist(), (penalties + window_cost).tolist()
    cost, back = [0.0] * n, [0] * n
    # The queue: candidates of ascending cost + position from ``head`` to before ``tail``; padding is window - (p - position).
    key_of, queue, head, tail, due = [0.0] * n, [0] * n, 0, 1, late[0]
    for j in range(1, n):
        p = pos[j]
        low = p - window
        while pos[queue[head]] < low:
            head += 1
        i, best = queue[head], key_of[head] - low
        while due == j:
            k = early[e]
            if cost[k] < best:
                best, i = cost[k], k
            e += 1
            due = late[e]
        best += pen[j]
        cost[j], back[j] = best, i
        best += p
        while tail > head and key_of[tail - 1] > best:
            tail -= 1
        key_of[tail], queue[tail] = best, j
        tail += 1
    cuts, j = [], n - 1
    while j > 0:
        cuts.append(pos[j])
        j = back[j]
    return cuts[::-1]


def brute_cuts(positions: list[int], penalties: list[float], window: int, window_cost: float = 0.0) -> float:
    """Cost of the best cutting, by trying every predecessor; for tests."""
    cost = [0.0] + [float("inf")] * (len(positions) - 1)
    for j in range(1, len(positions)):
        for i in range(j):
            if positions[j] - positions[i] <= window:
                cost[j] = min(cost[j], cost[i] + padding(positions[j] - positions[i], window) + penalties[j] + window_cost)
    return cost[-1]


def cost_of(cuts: list[int], positions: np.ndarray, penalties: np.ndarray, window: int, window_cost: float = 0.0) -> float:
    at, total, last = dict(zip(positions.tolist(), penalties.tolist())), 0.0, 0
    for c in cuts:
        total += padding(c - last, window) + at[c] + window_cost
        last = c
    return total


def closing_ids(path: str) -> np.ndarray:
    """Which ids' text ends with a sentence end; by the vocabulary itself."""
    t = encoder(path).tokenizer
    marks = {x if x != "\n" else "Ċ" for x in ENDS}  # the vocabulary writes a line break as that letter
    out = np.zeros(max(t.get_vocab().values()) + 1, bool)
    for token, i in t.get_vocab().items():
        out[i] = token[-1:] in marks
    return out


def candidates(ids: np.ndarray, ends: np.ndarray, window: int, closing: np.ndarray, sentence_penalty: float, word_penalty: float) -> tuple[np.ndarray, np.ndarray]:
    """Positions of a stretch where a window may end, with 0, and what a cut there costs; ``ends``: where documents end."""
    kind = np.zeros(len(ids) + 1, np.int8)  # 1: behind a sentence, 2: behind a document
    kind[1:][closing[ids]] = 1
    kind[ends] = 2
    spots = np.concatenate(([0], np.flatnonzero(kind)))
    wide = np.flatnonzero(np.diff(spots) > window)
    if len(wide):
        spots = np.sort(np.concatenate([spots, *[np.arange(spots[w] + 1, spots[w + 1]) for w in wide]]))
    return spots, np.array([word_penalty, sentence_penalty, 0.0])[kind[spots]]


def pack_stretch(doc_ids: list, ids: np.ndarray, ends: np.ndarray, first_sequence: int, window: int, closing: np.ndarray, sentence_penalty: float, word_penalty: float, window_cost: float) -> tuple[pa.RecordBatch, int]:
    """The pieces of a run of documents, and how many sequences they make."""
    cuts = np.array(choose_cuts(*candidates(ids, ends, window, closing, sentence_penalty, word_penalty), window, window_cost))
    stops = np.union1d(cuts, ends)
    starts = np.concatenate(([0], stops[:-1]))
    doc, sequence = np.searchsorted(ends, starts, "right"), np.searchsorted(cuts, starts, "right")
    doc_start, opened = np.concatenate(([0], ends)), np.concatenate(([0], cuts))
    raw = memoryview(np.ascontiguousarray(ids, "<u4")).cast("B")
    crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), stops.tolist())]
    columns = (pa.array(doc_ids, pa.int64()).take(pa.array(doc)), starts - doc_start[doc], stops - starts, crc, (ends - doc_start[:-1])[doc], sequence + first_sequence, starts - opened[sequence])
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) if not isinstance(c, pa.Array) else c for c, f in zip(columns, SCHEMA)], schema=SCHEMA), len(cuts)


def pack_documents(docs: DataFrame, vocabulary: str, window: int = 1024, separator: int = 0, sentence_penalty: float = 4.0, word_penalty: float = 48.0, window_cost: float = 0.0, id_col: str = "doc_id", text_col: str = "text", flush: int = 1 << 20) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Whenever ``flush`` ids are held they are packed and let go, so memory is bounded by that and the longest document; the
    cut forced there stands at a document's end and costs less than one window of padding.
    """
    if window & (window - 1):
        raise ValueError("the window is a power of two")
    rows = as_input(docs, id_col, text_col)
    parts = buckets_for(docs, mb=8, least=16)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        closing, sequence = closing_ids(vocabulary), TaskContext.get().partitionId() << 40
        names, ids, ends, held = [], [], [], 0

        def packed() -> pa.RecordBatch:
            nonlocal sequence
            out, made = pack_stretch(names, np.concatenate(ids), np.concatenate(ends), sequence, window, closing, sentence_penalty, word_penalty, window_cost)
            sequence += made
            return out

        for batch, flat, at in ended(source, vocabulary, separator):
            lo = 0
            while lo < batch.num_rows:  # up to the document with which ``flush`` ids are held
                hi = min(batch.num_rows, int(np.searchsorted(at, at[lo] + flush - held)))
                names += batch.column(0)[lo:hi].to_pylist()
                ids.append(flat[at[lo] : at[hi]])
                ends.append(at[lo + 1 : hi + 1] - at[lo] + held)
                held += int(at[hi] - at[lo])
                lo = hi
                if held >= flush:
                    yield packed()
                    names, ids, ends, held = [], [], [], 0
        if names:
            yield packed()

    crc = F.crc32(F.coalesce("text", F.lit("")).cast("binary"))
    ranged = rows.repartitionByRange(parts, F.col("doc_id"), crc).sortWithinPartitions("doc_id", crc)
    return ranged.mapInArrow(run, SQL_SCHEMA)
