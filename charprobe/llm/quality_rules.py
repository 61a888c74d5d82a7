"""Operator 3: base rules, then a calibrated logistic regression on hashed n-grams against a fixed threshold.

The base rules fail a text of fewer than ``least_words`` words, or one where more than 30 in 100 words stand in
8-word windows that the text has twice or more. The model is trained on a bounded sample of labelled rows
(``sample`` of them, those with the least hash of the id), calibrated by Platt's sigmoid on a third of them that
it has not learnt from, and applied to whole texts in Arrow batches. A null text counts as empty; a label of null
is none; without labelled rows of both kinds every text has probability 1. Repeated rows are judged alike.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHasher, as_input, batches, released, text_key, texts_of, window_hashes
from .text_features import SIZE, SPACE, START, SYMBOL, Adam, Examples, collected, margin, sigmoid

SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()), ("n_repeat_words", pa.int64()), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("probability", pa.float64())])
SQL_SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, probability double"
WINDOW = 8


def repeated_words(h: np.ndarray) -> int:
    """Words that stand in a window of WINDOW words which occurs twice or more."""
    w = window_hashes(h, WINDOW)
    if len(w) < 2:
        return 0
    order = np.argsort(w, kind="stable")
    s = w[order]
    same = s[1:] == s[:-1]
    if not same.any():
        return 0
    hit = np.zeros(len(w), bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    steps = np.zeros(len(h) + 1, np.int32)
    at = np.flatnonzero(hit)
    np.add.at(steps, at, 1)
    np.add.at(steps, at + WINDOW, -1)
    return int((np.cumsum(steps[:-1]) > 0).sum())


def duplicate_lines(text: bytes) -> int:
    lines = [x for x in text.split(b"\n") if x.strip()] if b"\n" in text else ()
    return len(lines) - len(set(lines))


def base_counts(text: bytes, words: list[bytes], h: np.ndarray) -> tuple[int, int, int, int, int]:
    data = np.frombuffer(text, np.uint8)
    return len(words), int(START[data].sum() - SPACE[data].sum()), int(SYMBOL[data].sum()), duplicate_lines(text), repeated_words(h)


def fit_logistic(rows: Examples, y: np.ndarray, steps: int = 120, rate: float = 0.05, decay: float = 1e-4) -> np.ndarray:
    """Weights (the last one is the intercept); both classes weigh alike."""
    w, adam = np.zeros(SIZE + 1), Adam(SIZE + 1, rate)
    share = np.where(y == 1, 0.5 / max(1, (y == 1).sum()), 0.5 / max(1, (y == 0).sum()))
    for _ in range(steps):
        slope = (sigmoid(rows.margins(w[:-1]) + w[-1]) - y) * share
        w -= adam.step(np.append(rows.gradient(slope), slope.sum()) + decay * np.append(w[:-1], 0.0))
    return w


def calibrate(margins: np.ndarray, y: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """Platt's sigmoid by Newton steps on smoothed targets: probability = sigmoid(a * margin + b)."""
    up, down = (y == 1).sum(), (y == 0).sum()
    target = np.where(y == 1, (up + 1) / (up + 2), 1 / (down + 2))
    x = np.stack([margins, np.ones(len(margins))])
    ab = np.array([1.0, 0.0])
    for _ in range(steps):
        p = sigmoid(ab @ x)
        g = x @ (p - target)
        hess = (x * (p * (1 - p))) @ x.T + 1e-6 * np.eye(2)
        step = np.linalg.solve(hess, g)
        ab = ab - np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-9:
            break
    return float(ab[0]), float(ab[1])


class Model:
    def __init__(self, weights: np.ndarray, intercept: float, a: float, b: float) -> None:
        self.weights, self.intercept, self.a, self.b = weights.astype(np.float32), intercept, a, b

    def probability(self, margin: float) -> float:
        return float(sigmoid(np.array(self.a * (margin + self.intercept) + self.b)))


def labelled_sample(docs: DataFrame, labels: DataFrame, sample: int) -> list[tuple[np.ndarray, np.ndarray, int]]:
    """(numbers, values, label) of at most ``sample`` labelled documents by id; bounded by that and by SIZE features each."""
    chosen = (
        labels.select(F.col("doc_id").cast("long").alias("key"), F.col("quality").cast("int").alias("label")).where("key is not null and label in (0, 1)")
        .groupBy("key").agg(F.max("label").alias("label")).orderBy(F.xxhash64("key"), "key").limit(sample)
    )
    found = collected(as_input(docs).join(F.broadcast(chosen), F.col("doc_id") == F.col("key")).select("doc_id", "text"))
    by_id = {r["key"]: r["label"] for r in chosen.collect()}
    return [(*found[k], by_id[k]) for k in sorted(found)]


def train(docs: DataFrame, labels: DataFrame, sample: int = 3000) -> Model | None:
    rows = labelled_sample(docs, labels, sample)
    y = np.array([r[2] for r in rows])
    if len(set(y.tolist())) < 2:
        return None
    third = np.arange(len(rows)) % 3 == 2
    learnt, apart = (Examples([rows[i][:2] for i in np.flatnonzero(pick)]) for pick in (~third, third))
    del rows  # the features lie in the examples now
    released()
    w = fit_logistic(learnt, y[~third])
    a, b = calibrate(apart.margins(w[:-1]) + w[-1], y[third]) if len(set(y[third].tolist())) == 2 else (1.0, 0.0)
    del learnt, apart
    released()  # the driver outlives the fit
    return Model(w[:-1], float(w[-1]), a, b)


def judge_quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, least_words: int = 20, sample: int = 3000, keyed: bool = False) -> DataFrame:
    """One row per document with the base counts, base_failed, the calibrated probability and kept; ``keyed``: text_key too."""
    model = train(docs, labels, sample)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = WordHasher()

        def rows() -> Iterator[tuple]:
            for batch in source:
                for doc_id, text, key in zip(batch.column(0).to_pylist(), texts_of(batch), batch.column(2).to_pylist() if keyed else repeat(None)):
                    words = text.split()
                    h = hasher(words)
                    counts = base_counts(text, words, h)
                    failed = counts[0] < least_words or 100 * counts[4] > 30 * counts[0]
                    p = 1.0 if model is None else model.probability(margin(text, model.weights, hasher, h=h))
                    yield doc_id, *counts, failed, not failed and p >= threshold, p, *([key] if keyed else [])

        yield from batches(rows(), SCHEMA.append(pa.field("text_key", pa.int64())) if keyed else SCHEMA)

    rows = as_input(docs)
    if keyed:
        rows = rows.withColumn("text_key", text_key(F.col("text")))
    return rows.mapInArrow(run, SQL_SCHEMA + (", text_key long" if keyed else ""))
