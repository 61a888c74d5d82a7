"""Vectors of tokens: co-occurrence counts, PPMI and truncated SVD; skip-gram; controls; packing and masking for language models."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import LETTERS, draw
from ..sources import in_runs
from .vocab import bounded


def sequences(tokens: DataFrame, vocab: DataFrame) -> DataFrame:
    """doc_id, ids: the token ids of a document in order; tokens outside the vocabulary leave no gap."""
    known = vocab.select("surface", "has_space", "token_id")
    met = tokens.join(bounded(known), ["surface", "has_space"])
    row = F.array_sort(F.collect_list(F.struct("word_pos", "sub_pos", "token_id")))
    return met.groupBy("doc_id").agg(F.transform(row, lambda x: x["token_id"]).alias("ids"))


#: Pairs that a task holds before it counts them, and ids that it pairs at once.
PAIRS, IDS = 1 << 21, 1 << 18


def cooccurrence(seqs: DataFrame, window: int = 4, direction: str = "forward") -> DataFrame:
    """t, c, n: how often c stands within ``window`` places behind t (forward), before it, or on either side (both)."""
    kind = seqs.schema["ids"].dataType.elementType.simpleString()

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def counted() -> pa.RecordBatch:
            pairs, n = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(pairs >> 32, pa.int64()), pa.array(pairs & 0xFFFFFFFF, pa.int64()), pa.array(n, pa.int64())], names=["t", "c", "n"])

        for batch in in_runs(source, IDS, 0):
            ids = batch.column(0)
            flat, row = ids.flatten().to_numpy().astype(np.int64), np.repeat(np.arange(len(ids)), ids.value_lengths().fill_null(0).to_numpy())
            for k in range(1, window + 1):
                near = row[k:] == row[:-k]
                held.append(flat[:-k][near] << 32 | flat[k:][near])
                size += len(held[-1])
                if size >= PAIRS:
                    yield counted()
                    held, size = [], 0
        if size:
            yield counted()

    parts = seqs.select("ids").mapInArrow(run, "t long, c long, n long")
    counted = parts.groupBy("t", "c").agg(F.sum("n").alias("n")).select(F.col("t").cast(kind).alias("t"), F.col("c").cast(kind).alias("c"), "n")
    turned = counted.select(F.col("c").alias("t"), F.col("t").alias("c"), "n")
    if direction == "forward":
        return counted
    if direction == "backward":
        return turned
    return counted.unionByName(turned).groupBy("t", "c").agg(F.sum("n").alias("n"))


def ppmi(counts: DataFrame, smoothing: float = 0.75, shift: float = 1.0) -> DataFrame:
    """t, c, value > 0: log(n Z / (n_t n_c^smoothing)) - log shift, where Z sums n_c^smoothing."""
    t = counts.groupBy("t").agg(F.sum("n").alias("n_t"))
    c = counts.groupBy("c").agg(F.pow(F.sum("n").cast("double"), smoothing).alias("w_c"))
    z = c.agg(F.sum("w_c").alias("z"))
    rows = counts.join(t, "t").join(c, "c").crossJoin(F.broadcast(z))  # z is one row
    value = F.log(F.col("n") * F.col("z") / (F.col("n_t") * F.col("w_c"))) - F.log(F.lit(float(shift)))
    return rows.select("t", "c", F.round(value, 9).alias("value")).where("value > 0")


#: Rows of the dense block that are summed together, and entries of the matrix that meet it at once.
RUN, ENTRIES = 4096, 1 << 17


def svd_vectors(matrix: DataFrame, dim: int = 64, rounds: int = 4, extra: int = 12, seed: int = 42) -> DataFrame:
    """token_id, vector: left factors times the root of the singular values, by randomized subspace iteration.

    Rows of the sparse matrix stay on the executors as blocks; what goes around is a dense block of
    (vocabulary x (dim + extra)), bounded by the vocabulary. Signs: each component's largest entry is positive.
    """
    spark = matrix.sparkSession
    rows = matrix.groupBy("t").agg(F.array_sort(F.collect_list(F.struct("c", "value"))).alias("r")).select(F.col("t").cast("long").alias("t"), F.transform("r", lambda x: x["c"]).cast("array<long>").alias("c"), F.transform("r", lambda x: x["value"]).alias("v")).cache()
    try:
        top = rows.select(F.max("t").alias("a"), F.max(F.array_max("c")).alias("b")).first()
        if top["a"] is None:
            return spark.createDataFrame([], "token_id long, vector array<double>")
        n_c, width = int(top["b"]) + 1, dim + extra
        q = np.linalg.qr(np.random.default_rng(seed).normal(size=(n_c, width)))[0] if n_c >= width else np.eye(n_c)

        def times(block: np.ndarray, back: bool) -> np.ndarray | dict[int, np.ndarray]:
            """A @ block by rows; or, with back, A.T @ (A @ block): tasks' parts are summed on the executors in runs of rows."""
            held = spark.sparkContext.broadcast(block)

            def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                total = np.zeros_like(held.value) if back else None
                for batch in in_runs(source, ENTRIES):
                    ids, lists, values = batch.column(0).to_numpy(), batch.column(1), batch.column(2)
                    start = lists.offsets.to_numpy().astype(np.int64)
                    c, v = lists.values.to_numpy()[start[0] : start[-1]], values.values.to_numpy()[start[0] : start[-1]]
                    start -= start[0]
                    y = np.add.reduceat(v[:, None] * held.value[c], start[:-1])  # no row is empty
                    if back:
                        order = np.argsort(c, kind="stable")
                        c, of = c[order], np.repeat(np.arange(len(ids)), np.diff(start))[order]
                        first = np.flatnonzero(np.concatenate(([True], c[1:] != c[:-1])))
                        total[c[first]] += np.add.reduceat(v[order][:, None] * y[of], first)
                    else:
                        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([x.tobytes() for x in y], pa.binary())], names=["t", "y"])
                if back:
                    for lo in range(0, len(total), RUN):
                        yield pa.RecordBatch.from_arrays([pa.array([lo], pa.int64()), pa.array([total[lo : lo + RUN].tobytes()], pa.binary())], names=["t", "y"])

            def added(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                sums: dict[int, np.ndarray] = {}
                for batch in source:
                    for lo, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                        sums[lo] = sums[lo] + np.frombuffer(y) if lo in sums else np.frombuffer(y)
                if sums:
                    yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array([y.tobytes() for y in sums.values()], pa.binary())], names=["t", "y"])

            got = rows.mapInArrow(run, "t long, y binary")
            if back and len(block) > RUN:
                got = got.repartition(-(-len(block) // RUN), "t").mapInArrow(added, "t long, y binary")
            got = got.collect()  # with back one sum of each run of rows (of each task where one run is all), else a row of each token
            held.unpersist()
            if not back:
                return {r["t"]: np.frombuffer(r["y"]) for r in got}
            out = np.zeros_like(block)
            for r in got:
                out[r["t"] : r["t"] + RUN] += np.frombuffer(r["y"]).reshape(-1, block.shape[1])
            return out

        for _ in range(rounds):
            q = np.linalg.qr(times(q, True))[0]
        y = times(q, False)
        ids = sorted(y)
        x = left_factors(np.stack([y[i] for i in ids]), dim)
        return spark.createDataFrame([(int(i), [float(a) for a in r]) for i, r in zip(ids, x)], "token_id long, vector array<double>")
    finally:
        rows.unpersist()


#: Entries of a square of counts that one task holds (8 bytes each, some four times).
SQUARE = 1 << 23


def dense_vectors(counts: DataFrame, turns: Sequence[bool], dim: int, rounds: int = 4, extra: int = 12, seed: int = 42) -> DataFrame:
    """token_id, vector: as ``svd_vectors(ppmi(counts), dim)``, with ``turns`` for t and c changed places or not, side by side.

    For vocabularies whose square is held by one task: a job for all rounds, instead of a join or a pass over rows each.
    """

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [tuple(batch.column(k).to_numpy() for k in range(3)) for batch in source if batch.num_rows]
        if not held:
            return
        t, c, n = (np.concatenate(x) for x in zip(*held))
        size = int(max(t.max(), c.max())) + 1
        square = np.zeros((size, size))
        square[t, c] = n
        del held, t, c, n
        out: dict[int, list[np.ndarray]] | None = None
        for turned in turns:
            rows = dict(zip(*dense_svd(dense_ppmi(square.T if turned else square), dim, rounds, extra, seed)))
            out = {i: [x] for i, x in rows.items()} if out is None else {i: [*x, rows[i]] for i, x in out.items() if i in rows}
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(list(out), pa.int64()), pa.array([np.concatenate(x) for x in out.values()], pa.list_(pa.float64()))], names=["token_id", "vector"])

    return counts.select("t", "c", "n").repartition(1).mapInArrow(run, "token_id long, vector array<double>")


def dense_ppmi(square: np.ndarray, smoothing: float = 0.75, shift: float = 1.0) -> np.ndarray:
    """The values of ``ppmi``, 0 where it has no row."""
    n_t, w_c = square.sum(1), square.sum(0) ** smoothing
    out = square * w_c.sum()
    out /= np.where(n_t > 0, n_t, 1.0)[:, None]
    out /= np.where(w_c > 0, w_c, 1.0)
    np.log(out, out=out, where=square > 0)
    out[square == 0] = 0.0
    out -= np.log(shift) * (square > 0)
    return np.maximum(np.round(out, 9, out=out), 0.0, out=out)


def dense_svd(matrix: np.ndarray, dim: int, rounds: int, extra: int, seed: int) -> tuple[list[int], np.ndarray]:
    """Rows of the matrix that are not empty, and their vectors."""
    there = matrix > 0
    ids, width = np.flatnonzero(there.any(1)), dim + extra
    if not len(ids):
        return [], np.zeros((0, 0))
    matrix = matrix[:, : int(np.flatnonzero(there.any(0))[-1]) + 1]
    del there
    n_c = matrix.shape[1]
    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(n_c, width)))[0] if n_c >= width else np.eye(n_c)
    for _ in range(rounds):
        q = np.linalg.qr(matrix.T @ (matrix @ q))[0]
    return ids.tolist(), left_factors(matrix[ids] @ q, dim)


def left_factors(y: np.ndarray, dim: int) -> np.ndarray:
    """Left factors times the root of the singular values; each component's largest entry is positive."""
    u, s, _ = np.linalg.svd(y, full_matrices=False)
    k = min(dim, len(s))
    x = u[:, :k] * np.sqrt(s[:k])
    return x * np.where(x[np.abs(x).argmax(0), np.arange(k)] < 0, -1.0, 1.0)


def distributional(seqs: DataFrame, window: int = 4, dim: int = 64, direction: str = "concat", seed: int = 42, square: int = SQUARE, top: int | None = None) -> DataFrame:
    """Vectors from PPMI and SVD: forward (as a causal model sees), both sides (as a masked one), or forward and backward side by side.

    ``top``: the greatest id, where the caller knows it."""
    if top is None:
        top = seqs.agg(F.max(F.array_max("ids"))).first()[0]
    dense = top is not None and (top + 1) ** 2 <= square
    if direction != "concat":
        counted = cooccurrence(seqs, window, direction)
        return dense_vectors(counted, [False], dim, seed=seed) if dense else svd_vectors(ppmi(counted), dim, seed=seed)
    counted = cooccurrence(seqs, window, "forward")
    if dense:
        return dense_vectors(counted, [False, True], dim // 2, seed=seed)
    counted.persist()  # counted once, turned for the other side
    try:
        f = svd_vectors(ppmi(counted), dim // 2, seed=seed)
        b = svd_vectors(ppmi(counted.select(F.col("c").alias("t"), F.col("t").alias("c"), "n")), dim // 2, seed=seed)
    finally:
        counted.unpersist()
    return f.join(b.withColumnRenamed("vector", "second"), "token_id").select("token_id", F.concat("vector", "second").alias("vector"))


def skipgram(seqs: DataFrame, dim: int = 64, window: int = 4, seed: int = 42, epochs: int = 1) -> DataFrame:
    from pyspark.ml.feature import Word2Vec

    text = seqs.select(F.transform("ids", lambda i: i.cast("string")).alias("ids"))
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=1, numPartitions=1, seed=seed, maxIter=epochs, inputCol="ids", outputCol="out").fit(text)
    from pyspark.ml.functions import vector_to_array

    return model.getVectors().select(F.col("word").cast("long").alias("token_id"), vector_to_array("vector").alias("vector"))


def random_vectors(vocab: DataFrame, dim: int = 64, seed: int = 42) -> DataFrame:
    """Noise by hash: a probe on it is at chance."""
    unit = lambda i: (F.pmod(F.xxhash64(F.lit(seed), F.col("token_id"), i), F.lit(2_000_001)) - 1_000_000) / F.lit(1e6)
    return vocab.select(F.col("token_id").cast("long").alias("token_id"), F.transform(F.sequence(F.lit(1), F.lit(dim)), unit).alias("vector"))


def letter_bag(vocab: DataFrame, noise: float = 0.1, seed: int = 42) -> DataFrame:
    """One entry for each letter that the token has, plus small noise: a probe on it is near 100 %."""
    hit = lambda i: (F.instr(F.lower("surface"), F.substring(F.lit(LETTERS), i, F.lit(1))) > 0).cast("double")
    stir = lambda i: noise * (F.pmod(F.xxhash64(F.lit(seed), F.col("token_id"), i), F.lit(2001)) - 1000) / 1000.0
    return vocab.select(F.col("token_id").cast("long").alias("token_id"), F.transform(F.sequence(F.lit(1), F.lit(26)), lambda i: hit(i) + stir(i)).alias("vector"))


def external_vectors(table: DataFrame, vocab: DataFrame) -> DataFrame:
    """A given matrix laid over the vocabulary by rank: unrelated to spelling, so a control at chance."""
    return table.join(vocab.select("token_id"), F.col("vec_id") == F.col("token_id")).select(F.col("token_id").cast("long").alias("token_id"), F.col("embedding").cast("array<double>").alias("vector"))


def pack_blocks(seqs: DataFrame, block: int = 1024) -> DataFrame:
    """Blocks of exactly ``block`` ids from each task's documents, one behind another; the rest of a task is dropped, as training does."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[int] = []
        for batch in source:
            out = []
            for ids in batch.column(0).to_pylist():
                held += ids
                while len(held) >= block:
                    out.append(held[:block])
                    held = held[block:]
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.int32()))], names=["ids"])

    return seqs.select(F.col("ids").cast("array<int>")).mapInArrow(run, "ids array<int>")


def mask_draw(tokens: DataFrame, rate: float = 0.15, seed: int = 42) -> DataFrame:
    """masked: 1 for about ``rate`` of the tokens, by a draw for (document, word, place)."""
    hit = draw(seed, F.col("doc_id"), F.col("word_pos"), F.col("sub_pos")) % 10_000 < int(round(rate * 10_000))
    return tokens.withColumn("masked", hit.cast("int"))
