"""The probe: two hidden layers (SELU, then Tanh), dropout, sigmoid cross-entropy, Adam; one fit to a task."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Constants of SELU (fixed values).
SELU_SCALE, SELU_ALPHA = 1.0507009873554805, 1.6732632423543772
WIDEST = 256


@dataclass(frozen=True)
class ProbeConfig:
    hidden: tuple[int, int] | None = None  # None: the vectors' width for both, at most WIDEST
    dropout: float = 0.1
    rate: float = 1e-3
    epochs: int = 3
    batch: int = 128
    seed: int = 42
    standardize: bool = True


class Probe:
    def __init__(self, width: int, cfg: ProbeConfig) -> None:
        a, b = cfg.hidden or (min(width, WIDEST),) * 2
        self.rng, self.cfg = np.random.default_rng(cfg.seed), cfg
        normal = lambda n, m: self.rng.normal(0.0, 1.0 / np.sqrt(n), (n, m))
        self.p = [normal(width, a), np.zeros(a), normal(a, b), np.zeros(b), normal(b, 1)[:, 0], np.zeros(1)]

    def logits(self, x: np.ndarray, masks: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, tuple]:
        w1, b1, w2, b2, w3, b3 = self.p
        z1 = x @ w1 + b1
        h1 = SELU_SCALE * np.where(z1 > 0, z1, SELU_ALPHA * np.expm1(np.minimum(z1, 0)))
        d1 = h1 * masks[0] if masks else h1
        h2 = np.tanh(d1 @ w2 + b2)
        d2 = h2 * masks[1] if masks else h2
        return d2 @ w3 + b3[0], (x, z1, d1, h2, d2)

    def loss(self, x: np.ndarray, y: np.ndarray, masks=None) -> float:
        z = self.logits(x, masks)[0]
        return float(np.mean(np.maximum(z, 0) - z * y + np.log1p(np.exp(-np.abs(z)))))

    def gradients(self, x: np.ndarray, y: np.ndarray, masks=None) -> list[np.ndarray]:
        _, _, w2, _, w3, _ = self.p
        z, (x, z1, d1, h2, d2) = self.logits(x, masks)
        dz = (1 / (1 + np.exp(-z)) - y) / len(y)
        dh2 = np.outer(dz, w3) * (masks[1] if masks else 1.0) * (1 - h2 * h2)
        dh1 = dh2 @ w2.T * (masks[0] if masks else 1.0)
        dz1 = dh1 * SELU_SCALE * np.where(z1 > 0, 1.0, SELU_ALPHA * np.exp(np.minimum(z1, 0)))
        return [x.T @ dz1, dz1.sum(0), d1.T @ dh2, dh2.sum(0), d2.T @ dz, np.array([dz.sum()])]

    def fit(self, x: np.ndarray, y: np.ndarray) -> "Probe":
        c, n = self.cfg, len(y)
        m, v, t = [np.zeros_like(p) for p in self.p], [np.zeros_like(p) for p in self.p], 0
        for _ in range(c.epochs):
            order = self.rng.permutation(n)
            for lo in range(0, n, c.batch):
                at = order[lo : lo + c.batch]
                keep = 1.0 - c.dropout
                masks = tuple((self.rng.random((len(at), self.p[k].shape[0])) < keep) / keep for k in (1, 3)) if c.dropout else None
                t += 1
                for k, g in enumerate(self.gradients(x[at], y[at], masks)):
                    m[k] = 0.9 * m[k] + 0.1 * g
                    v[k] = 0.999 * v[k] + 0.001 * g * g
                    self.p[k] = self.p[k] - c.rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
        return self

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.logits(x)[0]))


def train_and_score(x: np.ndarray, y: np.ndarray, test: np.ndarray, cfg: ProbeConfig) -> np.ndarray:
    """Probabilities of the test rows; scaled by the training rows alone. One kind of label only: its share."""
    train = ~test
    if train.sum() == 0 or test.sum() == 0 or len(set(y[train].tolist())) < 2:
        return np.full(int(test.sum()), float(y[train].mean()) if train.any() else 0.5)
    if cfg.standardize:
        mean, sd = x[train].mean(0), x[train].std(0)
        x = (x - mean) / np.where(sd > 1e-12, sd, 1.0)
    return Probe(x.shape[1], cfg).fit(x[train], y[train]).probability(x[test])


PREDICTED = "experiment string, letter string, fold int, token_id long, n_letters int, y int, p double, correct int"


def fit_predict(sample: DataFrame, vectors: DataFrame, cfg: ProbeConfig = ProbeConfig(), experiment: str = "probe", model: str = "network") -> DataFrame:
    """One fit per letter (and fold, where the sample has folds: each is the test side once); rows of all test sides.

    sample: letter, token_id, n_letters, y and is_test or fold; with a column ``cell`` every cell is an experiment of its
    own, named by it. Tokens without a vector drop out. Each fit is a task's; with folds a row goes to every fold's fit.
    """
    folds = "fold" in sample.columns
    cell = F.col("cell") if "cell" in sample.columns else F.lit(experiment)
    side = F.col("fold") if folds else F.col("is_test")
    rows = sample.select(cell.alias("cell"), "letter", F.col("token_id").cast("long").alias("token_id"), F.col("n_letters").cast("int").alias("n_letters"), "y", side.cast("int").alias("side"))
    if folds:
        turns = rows.select("cell", "letter", F.col("side").alias("turn")).distinct()
        rows = rows.join(turns, ["cell", "letter"])
    else:
        rows = rows.withColumn("turn", F.lit(1))
    rows = rows.join(vectors.select(F.col("token_id").cast("long").alias("token_id"), "vector"), "token_id")

    def fit(key, table):
        order = np.argsort(table.column("token_id").to_numpy(), kind="stable")
        name, letter, turn = (k.as_py() for k in key)
        x = np.array(table.column("vector").to_pylist(), np.float64)[order]
        y, side, ids, n = (table.column(c).to_numpy()[order] for c in ("y", "side", "token_id", "n_letters"))
        test = side == turn
        if model == "linear":
            p = 1 / (1 + np.exp(-4 * linear_probe(x, y.astype(float), test))) if test.any() and not test.all() else np.full(int(test.sum()), 0.5)
        else:
            p = train_and_score(x, y.astype(float), test, cfg)
        m = int(test.sum())
        right = ((p >= 0.5) == (y[test] == 1)).astype(np.int32)
        return pa.table({"experiment": [name] * m, "letter": [letter] * m, "fold": pa.array([turn] * m, pa.int32()), "token_id": pa.array(ids[test], pa.int64()), "n_letters": pa.array(n[test], pa.int32()), "y": pa.array(y[test], pa.int32()), "p": pa.array(p, pa.float64()), "correct": pa.array(right, pa.int32())}).cast(SCHEMA)

    return rows.groupBy("cell", "letter", "turn").applyInArrow(fit, PREDICTED)


SCHEMA = pa.schema([("experiment", pa.string()), ("letter", pa.string()), ("fold", pa.int32()), ("token_id", pa.int64()), ("n_letters", pa.int32()), ("y", pa.int32()), ("p", pa.float64()), ("correct", pa.int32())])


def linear_probe(x: np.ndarray, y: np.ndarray, test: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Scores of a ridge regression on +1 and -1: a plain guard beside the network."""
    a = np.hstack([x, np.ones((len(x), 1))])
    t = ~test
    w = np.linalg.solve(a[t].T @ a[t] + ridge * np.eye(a.shape[1]), a[t].T @ (2 * y[t] - 1))
    return a[test] @ w


def ridge(sample: DataFrame, vectors: DataFrame, target: str, penalty: float = 1.0) -> DataFrame:
    """token_id, is_test, target and the value that a ridge regression on the training rows predicts.

    The normal equations are summed on the executors; the driver solves a system as wide as the vectors.
    """
    rows = sample.select("token_id", F.col("is_test").cast("int").alias("is_test"), F.col(target).cast("double").alias("target")).join(vectors.select(F.col("token_id").alias("v_id"), "vector"), F.col("token_id") == F.col("v_id")).select("token_id", "is_test", "target", "vector")

    def sums(source):
        total = None
        for batch in source:
            if batch.num_rows:
                x = np.hstack([np.array(batch.column(1).to_pylist(), float), np.ones((batch.num_rows, 1))])
                part = np.hstack([x.T @ x, (x.T @ batch.column(0).to_numpy())[:, None]])
                total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.shape[0]], pa.int32()), pa.array([total.tobytes()], pa.binary())], names=["n", "m"])

    got = rows.where("is_test = 0").select("target", "vector").mapInArrow(sums, "n int, m binary").collect()  # a square of the vectors' width for each task
    if not got:
        return rows.select("token_id", "is_test", "target", F.lit(None).cast("double").alias("predicted"))
    n = got[0]["n"]
    m = sum(np.frombuffer(r["m"]).reshape(n, n + 1) for r in got)
    w = np.linalg.solve(m[:, :n] + penalty * np.eye(n), m[:, n])
    value = F.aggregate(F.zip_with("vector", F.array(*[F.lit(float(a)) for a in w[:-1]]), lambda a, b: a * b), F.lit(float(w[-1])), lambda s, x: s + x)
    return rows.select("token_id", "is_test", "target", value.alias("predicted"))
