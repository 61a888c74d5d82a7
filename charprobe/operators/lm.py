"""Small transformer language models, causal and masked, trained on packed blocks by averaging local runs.

The width, depth and step counts are parameters; PUBLISHED holds the sizes of the study's two models, which need other
hardware. Token vectors are the rows of the embedding matrix, which is also the output's (tied).
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class LmConfig:
    causal: bool = True
    blocks: int = 1
    heads: int = 2
    width: int = 32
    length: int = 32
    batch: int = 32
    rate: float = 3e-3
    decay: float = 0.1
    clip: float = 1.0
    warm_up: int = 20
    mask_rate: float = 0.15
    seed: int = 42


#: Sizes of the two models of the study (fixed values).
PUBLISHED = {
    "causal": LmConfig(True, 12, 12, 768, 1024, 32 * 40, 6e-4, 0.1, 1.0, 2000),
    "masked": LmConfig(False, 2, 2, 128, 256, 64, 2e-5, 0.0, 1.0, 0, 0.15),
}


def initial(vocab: int, c: LmConfig) -> dict[str, np.ndarray]:
    """The last token number is the mask's."""
    rng, d = np.random.default_rng(c.seed), c.width
    normal = lambda *s: rng.normal(0, 0.02, s)
    p = {"tokens": normal(vocab + 1, d), "places": normal(c.length, d), "gf": np.ones(d), "bf": np.zeros(d)}
    for k in range(c.blocks):
        p |= {f"g1{k}": np.ones(d), f"b1{k}": np.zeros(d), f"qkv{k}": normal(d, 3 * d), f"out{k}": normal(d, d) / math.sqrt(2 * c.blocks), f"g2{k}": np.ones(d), f"b2{k}": np.zeros(d), f"up{k}": normal(d, 4 * d), f"down{k}": normal(4 * d, d) / math.sqrt(2 * c.blocks)}
    return p


def _norm(x: np.ndarray, g: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, tuple]:
    mean, var = x.mean(-1, keepdims=True), x.var(-1, keepdims=True)
    r = 1 / np.sqrt(var + 1e-5)
    y = (x - mean) * r
    return y * g + b, (y, r, g)


def _norm_back(dy: np.ndarray, kept: tuple) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    y, r, g = kept
    axes = tuple(range(dy.ndim - 1))
    dz = dy * g
    return r * (dz - dz.mean(-1, keepdims=True) - y * (dz * y).mean(-1, keepdims=True)), (dy * y).sum(axes), dy.sum(axes)


def loss_and_gradients(p: dict[str, np.ndarray], ids: np.ndarray, targets: np.ndarray, c: LmConfig) -> tuple[float, dict[str, np.ndarray]]:
    """Mean cross-entropy where targets are not negative, and its gradients; ids, targets: batch x length."""
    n, length = ids.shape
    d, h = c.width, c.heads
    size = d // h
    x = p["tokens"][ids] + p["places"][:length]
    hidden = np.triu(np.ones((length, length), bool), 1) if c.causal else np.zeros((length, length), bool)
    kept = []
    for k in range(c.blocks):
        a, n1 = _norm(x, p[f"g1{k}"], p[f"b1{k}"])
        q, key, v = (t.reshape(n, length, h, size).transpose(0, 2, 1, 3) for t in np.split(a @ p[f"qkv{k}"], 3, axis=-1))
        s = np.where(hidden, -np.inf, q @ key.transpose(0, 1, 3, 2) / math.sqrt(size))
        w = np.exp(s - s.max(-1, keepdims=True))
        w /= w.sum(-1, keepdims=True)
        o = (w @ v).transpose(0, 2, 1, 3).reshape(n, length, d)
        x1 = x + o @ p[f"out{k}"]
        m, n2 = _norm(x1, p[f"g2{k}"], p[f"b2{k}"])
        u = m @ p[f"up{k}"]
        t = np.tanh(0.7978845608 * (u + 0.044715 * u**3))
        e = 0.5 * u * (1 + t)
        kept.append((a, n1, q, key, v, w, o, m, n2, u, t, e))
        x = x1 + e @ p[f"down{k}"]
    y, nf = _norm(x, p["gf"], p["bf"])
    at = targets >= 0
    z = y[at] @ p["tokens"].T
    z -= z.max(-1, keepdims=True)
    soft = np.exp(z)
    total = soft.sum(-1, keepdims=True)
    rows = np.arange(len(z))
    loss = float((np.log(total[:, 0]) - z[rows, targets[at]]).mean()) if len(z) else 0.0
    g = {}
    soft /= total
    soft[rows, targets[at]] -= 1
    soft /= max(1, len(z))
    dy = np.zeros_like(y)
    dy[at] = soft @ p["tokens"]
    g["tokens"] = soft.T @ y[at]
    dx, g["gf"], g["bf"] = _norm_back(dy, nf)
    flat = lambda t: t.reshape(-1, t.shape[-1])
    for k in reversed(range(c.blocks)):
        a, n1, q, key, v, w, o, m, n2, u, t, e = kept[k]
        g[f"down{k}"] = flat(e).T @ flat(dx)
        de = dx @ p[f"down{k}"].T
        du = de * (0.5 * (1 + t) + 0.5 * u * (1 - t * t) * 0.7978845608 * (1 + 3 * 0.044715 * u * u))
        g[f"up{k}"] = flat(m).T @ flat(du)
        dm, g[f"g2{k}"], g[f"b2{k}"] = _norm_back(du @ p[f"up{k}"].T, n2)
        dx = dx + dm
        g[f"out{k}"] = flat(o).T @ flat(dx)
        do = (dx @ p[f"out{k}"].T).reshape(n, length, h, size).transpose(0, 2, 1, 3)
        dw = do @ v.transpose(0, 1, 3, 2)
        ds = w * (dw - (dw * w).sum(-1, keepdims=True)) / math.sqrt(size)
        back = [t.transpose(0, 2, 1, 3).reshape(n, length, d) for t in (ds @ key, ds.transpose(0, 1, 3, 2) @ q, w.transpose(0, 1, 3, 2) @ do)]
        dqkv = np.concatenate(back, axis=-1)
        g[f"qkv{k}"] = flat(a).T @ flat(dqkv)
        da, g[f"g1{k}"], g[f"b1{k}"] = _norm_back(dqkv @ p[f"qkv{k}"].T, n1)
        dx = dx + da
    np.add.at(g["tokens"], ids.ravel(), flat(dx))
    g["places"] = np.zeros_like(p["places"])
    g["places"][:length] = dx.sum(0)
    return loss, g


def examples(ids: np.ndarray, c: LmConfig, rng: np.random.Generator, mask: int) -> tuple[np.ndarray, np.ndarray]:
    """Inputs and targets: the next token; or the tokens under masks."""
    if c.causal:
        return ids[:, :-1], ids[:, 1:]
    hit = rng.random(ids.shape) < c.mask_rate
    return np.where(hit, mask, ids), np.where(hit, ids, -1)


def run_steps(p: dict[str, np.ndarray], ids: np.ndarray, c: LmConfig, first: int, steps: int, all_steps: int) -> tuple[dict[str, np.ndarray], float]:
    """AdamW over batches of the blocks, with linear warm-up and a cosine down; the mean loss beside it."""
    rng = np.random.default_rng([c.seed, first])
    m, v, losses = {k: np.zeros_like(x) for k, x in p.items()}, {k: np.zeros_like(x) for k, x in p.items()}, []
    p = {k: x.copy() for k, x in p.items()}
    for s in range(1, steps + 1):
        at = rng.integers(0, len(ids), min(c.batch, len(ids)))
        loss, g = loss_and_gradients(p, *examples(ids[at], c, rng, len(p["tokens"]) - 1), c)
        losses.append(loss)
        size = math.sqrt(sum(float((x * x).sum()) for x in g.values()))
        shrink = min(1.0, c.clip / max(size, 1e-12))
        step = first + s
        rate = c.rate * (step / c.warm_up if step < c.warm_up else 0.5 * (1 + math.cos(math.pi * min(1.0, (step - c.warm_up) / max(1, all_steps - c.warm_up)))))
        for k, x in g.items():
            x = x * shrink
            m[k], v[k] = 0.9 * m[k] + 0.1 * x, 0.99 * v[k] + 0.01 * x * x
            p[k] -= rate * (m[k] / (1 - 0.9**s) / (np.sqrt(v[k] / (1 - 0.99**s)) + 1e-8) + (c.decay * p[k] if p[k].ndim > 1 else 0.0))
    return p, float(np.mean(losses)) if losses else 0.0


def blocks_of(seqs: DataFrame, length: int, workers: int) -> DataFrame:
    """worker, ids: blocks of exactly ``length`` ids from the documents of each worker's share, one behind another; a rest is dropped."""
    dealt = seqs.select("doc_id", F.col("ids").cast("array<int>").alias("ids")).repartition(workers, "doc_id").sortWithinPartitions("doc_id")

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held: list[int] = []
        for batch in source:
            out = []
            for ids in batch.column(1).to_pylist():
                held += ids
                whole = len(held) // length * length
                out += [held[k : k + length] for k in range(0, whole, length)]
                held = held[whole:]
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()] * len(out), pa.int32()), pa.array(out, pa.list_(pa.int32()))], names=["worker", "ids"])

    return dealt.mapInArrow(run, "worker int, ids array<int>")


def local_run(shared, names: list[str], c: LmConfig, first: int, steps: int, all_steps: int):
    def run(table: pa.Table) -> pa.Table:
        ids = np.array(table.column("ids").to_pylist(), np.int64)
        got, loss = run_steps(shared.value, ids, c, first, steps, all_steps)
        return pa.table({"loss": [loss], "n": [len(ids)], "values": pa.array([np.concatenate([got[k].ravel() for k in names]).tobytes()], pa.binary())})

    return run


def train(seqs: DataFrame, vocab_size: int, c: LmConfig = LmConfig(), rounds: int = 4, steps: int = 40, workers: int = 4) -> list[tuple[int, float, np.ndarray]]:
    """(steps so far, mean loss, token vectors) after each round. In a round every worker runs ``steps`` on its share of the
    blocks from the same parameters, and the results are averaged: ``workers`` copies of the parameters come back."""
    spark = seqs.sparkSession
    blocks = blocks_of(seqs, c.length, workers).persist()
    p, out = initial(vocab_size, c), [(0, math.log(vocab_size), None)]
    out[0] = (0, math.log(vocab_size), p["tokens"][:vocab_size].copy())
    names = sorted(p)
    try:
        for r in range(rounds):
            shared = spark.sparkContext.broadcast(p)
            rows = blocks.groupBy("worker").applyInArrow(local_run(shared, names, c, r * steps, steps, rounds * steps), "loss double, n long, values binary").collect()
            shared.unpersist()
            if not rows:
                break
            total = sum(x["n"] for x in rows)
            flat = sum(np.frombuffer(x["values"]) * (x["n"] / total) for x in rows)
            lo, new = 0, {}
            for k in names:
                new[k] = flat[lo : lo + p[k].size].reshape(p[k].shape)
                lo += p[k].size
            p = new
            out.append(((r + 1) * steps, sum(x["loss"] * x["n"] for x in rows) / total, p["tokens"][:vocab_size].copy()))
        return out
    finally:
        blocks.unpersist()


def vectors(spark, table: np.ndarray) -> DataFrame:
    """token_id, vector from a matrix of token vectors: as many rows as the vocabulary."""
    return spark.createDataFrame([(i, x) for i, x in enumerate(table.tolist())], "token_id long, vector array<double>")
