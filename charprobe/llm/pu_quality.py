"""Operator 7: quality by positive-unlabelled learning.

Trusted positives are documents labelled 1, at most ``positives`` of them; the unlabelled set is every document
outside the held-out fold, labels unread. The class prior is estimated from where the two score distributions meet
at their upper ends, and a linear scorer on hashed n-grams is trained on the non-negative unbiased risk: the risk
on positives, plus the risk of unlabelled texts as negatives less the share of it that positives explain, never
below zero. A sample of ``unlabelled`` documents gives first weights and the curvature of the unlabelled risk; its
value and slope, and the scores for the prior, are sums over all unlabelled documents, made where these lie.
A null or empty text has no words and is scored by the intercept and its shapes. Without any positive document
all scores are the prior's default. Repeated rows are scored alike. Null ids are in the held-out fold.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHasher, as_input, batches, crc_remainder, released, text_key, texts_of
from .text_features import SCALE, SHAPES, SIZE, Adam, Examples, FeatureSum, collected, margin, sigmoid, slots

FOLDS = 5
DEFAULT_PRIOR = 0.5
SCHEMA = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])
#: Bins of the unlabelled scores that the prior is read from: their lower ends.
BINS = np.linspace(-20, 20, 4001)
#: Numbers in a row of partial sums, and how many rows of them one task adds up.
BLOCK, FAN = 8192, 64
SUMS = "part long, block int, sums binary"


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, counts: np.ndarray | None = None) -> float:
    """Share of positives among the unlabelled: the least ratio of the two upper tails, each with a margin for its size.

    Both arrays hold scores of rows that the scorer has not learnt from; higher means more like a positive. With
    ``counts``, each unlabelled score stands for so many rows.
    """
    counts = np.ones(len(unlabelled)) if counts is None else counts
    size = counts.sum()
    if not len(positive) or not size:
        return DEFAULT_PRIOR
    order = np.argsort(unlabelled, kind="stable")
    u, below = unlabelled[order], np.concatenate(([0], np.cumsum(counts[order])))
    both, weight = np.concatenate([positive, u]), np.concatenate([np.ones(len(positive)), counts[order]])
    order = np.argsort(both, kind="stable")
    share = np.cumsum(weight[order]) / weight.sum()
    at = np.unique(both[order][np.searchsorted(share, np.linspace(0, 0.9, 181))])
    tail_p = 1 - np.searchsorted(np.sort(positive), at, side="left") / len(positive)
    tail_u = 1 - below[np.searchsorted(u, at, side="left")] / size
    slack = np.sqrt(np.log(40) / 2) * (1 / np.sqrt(len(positive)) + 1 / np.sqrt(size))
    sure = tail_p >= 0.1
    bound = np.where(sure, (tail_u + slack) / np.maximum(tail_p, 1e-9), np.inf)
    best = int(np.argmin(bound))
    return float(np.clip(tail_u[best] / tail_p[best], 0.02, 0.98))


@dataclass
class Whole:
    """The unlabelled risk of all rows at one place: weights with the intercept, mean loss there, and its slope."""

    at: np.ndarray
    loss: float
    slope: np.ndarray


def risk(p: np.ndarray, u: np.ndarray, prior: float) -> tuple[float, float]:
    """Positive part and negative part of the unbiased risk, from margins, with the logistic loss."""
    loss = lambda m: np.logaddexp(0, -m)
    return prior * float(loss(p).mean()), float(loss(-u).mean()) - prior * float(loss(-p).mean())


def fit(p: Examples, u: Examples, prior: float, steps: int = 100, rate: float = 0.15, decay: float = 7e-4, floor: float = 0.0, whole: Whole | None = None) -> np.ndarray:
    """Weights and, last, the intercept. Where the negative part falls below ``floor`` a step raises it instead.

    With ``whole`` the unlabelled risk has the value and the slope of all rows where these were summed, and the
    sample's curvature; the steps begin there.
    """
    w, adam = np.zeros(SIZE + 1), Adam(SIZE + 1, rate)
    lift, slant = 0.0, np.zeros(SIZE + 1)
    if whole is not None:
        w = whole.at.copy()
        m = u.margins(w[:-1]) + w[-1]
        lift = whole.loss - float(np.logaddexp(0, m).mean())
        slant = whole.slope - np.append(u.gradient(sigmoid(m) / u.n), sigmoid(m).mean())
    for _ in range(steps):
        mp, mu = p.margins(w[:-1]) + w[-1], u.margins(w[:-1]) + w[-1]
        up, uu = sigmoid(mp), sigmoid(mu)
        negative = risk(mp, mu, prior)[1] + lift + (slant @ (w - whole.at) if whole is not None else 0.0)
        slope_p, slope_u = -prior * up / p.n, uu / u.n  # of the negative part
        sign = 1.0
        if negative >= floor:
            slope_p = slope_p + prior * (up - 1) / p.n
        else:
            slope_p, slope_u, sign = -slope_p, -slope_u, -1.0
        g = np.append(p.gradient(slope_p) + u.gradient(slope_u), slope_p.sum() + slope_u.sum()) + sign * slant
        w -= adam.step(g + decay * np.append(w[:-1], 0.0))
    return w


def partial_sums(source: Iterator[pa.RecordBatch], first: np.ndarray, at: np.ndarray, learnt: frozenset[int]) -> np.ndarray:
    """Of (id, text) rows: slope and sum of the unlabelled loss at ``at``, rows, and rows by score under ``first``.

    Both weights have the intercept last. Rows with an id in ``learnt`` are left out of the scores alone.
    """
    hasher, total, slope, loss, n, scores = WordHasher(), FeatureSum(), 0.0, 0.0, 0, np.zeros(len(BINS))
    weights = np.ascontiguousarray(np.stack([first[:-1], at[:-1]], axis=1).astype(np.float32))
    last = np.array([first[-1], at[-1]])
    for batch in source:
        for doc_id, text in zip(batch.column(0).to_pylist(), texts_of(batch)):
            kinds, s = slots(text, hasher)
            m = last + s @ weights[SIZE - SHAPES :]
            for k in kinds:
                m = m + weights[k].mean(axis=0, dtype=np.float64) * SCALE
            factor = float(sigmoid(m[1]))
            total.add(kinds, s, factor)
            slope, loss, n = slope + factor, loss + float(np.logaddexp(0, m[1])), n + 1
            if doc_id not in learnt:
                scores[np.searchsorted(BINS, np.clip(m[0], BINS[0], BINS[-1]), side="right") - 1] += 1
    return np.concatenate([total.settle(), [slope, loss, n], scores])


def summed(rows: DataFrame) -> np.ndarray:
    """The sum of partial sums of all tasks, ``FAN`` of them at a time, on the executors; in order of tasks, so runs agree."""

    def add(group: pa.Table) -> pa.Table:
        group = group.sort_by("part")
        sums = np.zeros(len(group.column("sums")[0].as_py()) // 8)
        for x in group.column("sums"):
            sums += np.frombuffer(x.as_buffer(), np.float64)
        return pa.table({"part": group.column("part").cast(pa.int64()).slice(0, 1), "block": group.column("block").slice(0, 1).cast(pa.int32()), "sums": pa.array([sums.tobytes()], pa.binary())})

    parts = rows.rdd.getNumPartitions()
    while parts > FAN:
        rows = rows.withColumn("part", F.floor(F.col("part") / FAN)).groupBy("part", "block").applyInArrow(add, SUMS)
        parts = -(-parts // FAN)
    got = {r["block"]: r["sums"] for r in rows.groupBy("block").applyInArrow(add, SUMS).collect()}  # one row a block
    return np.concatenate([np.frombuffer(got[k], np.float64) for k in sorted(got)]) if got else np.zeros(SIZE + 3 + len(BINS))


def whole_risk(docs: DataFrame, first: np.ndarray, at: np.ndarray, learnt: frozenset[int]) -> tuple[Whole, np.ndarray]:
    """The unlabelled risk at ``at`` of all documents outside the held-out fold, and their counts by score under ``first``."""
    schema = pa.schema([("part", pa.int64()), ("block", pa.int32()), ("sums", pa.binary())])

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = partial_sums(source, first, at, learnt)
        if sums[SIZE + 2]:
            part = TaskContext.get().partitionId()
            yield from batches(((part, k, sums[k * BLOCK : (k + 1) * BLOCK].tobytes()) for k in range(-(-len(sums) // BLOCK))), schema)

    sums = summed(as_input(docs).where(crc_remainder("doc_id", FOLDS) != 0).mapInArrow(run, SUMS))
    n = max(sums[SIZE + 2], 1)
    return Whole(at, float(sums[SIZE + 1] / n), sums[: SIZE + 1] / n), sums[SIZE + 3 :]


def sample_features(docs: DataFrame, ids: DataFrame) -> list[tuple[np.ndarray, np.ndarray]]:
    """Features of the documents whose ids are in ``ids`` (bounded by the caller), in the order of the ids."""
    found = collected(as_input(docs).join(F.broadcast(ids), F.col("doc_id") == F.col("key")).select("doc_id", "text"))
    return [(k, *found[k]) for k in sorted(found)]


def train(docs: DataFrame, labels: DataFrame, positives: int = 1500, unlabelled: int = 3000) -> tuple[np.ndarray, float] | None:
    """Weights with the intercept, and the prior; None where no labelled positive is in the training folds."""
    fold = crc_remainder("key", FOLDS)
    chosen = labels.select(F.col("doc_id").cast("long").alias("key"), "quality").where("key is not null and quality = 1").select("key").distinct().where(fold != 0)
    chosen = chosen.orderBy(F.xxhash64("key"), "key").limit(positives)
    p_ids = {r["key"] for r in chosen.collect()}  # at most ``positives``
    others = docs.select(F.col("doc_id").cast("long").alias("key")).where("key is not null").where(fold != 0).distinct()
    others = others.orderBy(F.xxhash64(F.col("key"), F.lit(7)), "key").limit(unlabelled)
    u_ids = {r["key"] for r in others.collect()}  # at most ``unlabelled``
    both = sorted(p_ids | u_ids)
    if not both:
        return None
    rows = sample_features(docs, docs.sparkSession.createDataFrame([(k,) for k in both], "key long"))
    p = [(i, v) for k, i, v in rows if k in p_ids]
    u = [(i, v) for k, i, v in rows if k in u_ids]
    if len(p) < 2 or len(u) < 2:
        return None
    half = lambda x, r: Examples([y for j, y in enumerate(x) if j % 2 == r])
    first = fit(half(p, 0), half(u, 0), DEFAULT_PRIOR, steps=40)
    apart = half(p, 1).margins(first[:-1])
    guess = estimate_prior(apart, half(u, 1).margins(first[:-1]))
    learnt = frozenset([k for k, _, _ in rows if k in u_ids][::2])
    p_all, u_all = Examples(p), Examples(u)
    del rows, p, u  # the features lie in the examples now
    released()
    whole, scores = whole_risk(docs, first, fit(p_all, u_all, guess), learnt)
    prior = estimate_prior(apart + first[-1], BINS, scores)
    weights = fit(p_all, u_all, prior, whole=whole)
    del p_all, u_all
    released()  # the driver outlives the fit
    return weights, prior


def score_quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, positives: int = 1500, unlabelled: int = 3000, keyed: bool = False) -> DataFrame:
    """doc_id, held_out, score (0 to 1, higher: label 1 likelier) and predicted of every document; ``keyed``: text_key too."""
    trained = train(docs, labels, positives, unlabelled)
    weights, intercept = (trained[0][:-1].astype(np.float32), float(trained[0][-1])) if trained else (None, 0.0)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = WordHasher()

        def rows() -> Iterator[tuple]:
            for batch in source:
                for doc_id, text, held, key in zip(batch.column(0).to_pylist(), texts_of(batch), batch.column(2).to_pylist(), batch.column(3).to_pylist() if keyed else repeat(None)):
                    score = DEFAULT_PRIOR if weights is None else float(sigmoid(np.array(margin(text, weights, hasher) + intercept)))
                    yield doc_id, held, score, int(score >= threshold), *([key] if keyed else [])

        yield from batches(rows(), SCHEMA.append(pa.field("text_key", pa.int64())) if keyed else SCHEMA)

    rows = as_input(docs).withColumn("held_out", crc_remainder("doc_id", FOLDS) == 0)
    if keyed:
        rows = rows.withColumn("text_key", text_key(F.col("text")))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int" + (", text_key long" if keyed else ""))
