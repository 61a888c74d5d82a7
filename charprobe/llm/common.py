"""What several operators need: shared staging, words, hashes, connected components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import released

U64 = np.uint64
#: Entries of a worker's cache of words; it starts anew beyond that, so memory stays bounded.
CACHE_ENTRIES = 400_000


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    held = spark.sparkContext.getCheckpointDir()
    if not held:
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="charprobe-"))
        held = spark.sparkContext.getCheckpointDir()
    return held.rstrip("/")


def staging_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, removed by the file system's own hook when the driver ends."""
    path = f"{shared_dir(spark)}/charprobe-{tag}-{uuid.uuid4().hex}"
    jvm = spark._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(target)
    return path


#: Set while a table is written: Spark then removes the shuffle files of that write when it has ended.
FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def staged(df: DataFrame, tag: str, by: str | None = None) -> DataFrame:
    """df written as Parquet to the shared folder (in folders by a column) and read again: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = staging_path(spark, tag)
    before = spark.conf.get(FREED, None)
    spark.conf.set(FREED, "true")
    try:
        (df.write.partitionBy(by) if by else df.write).parquet(path)
    finally:
        if before is None:
            spark.conf.unset(FREED)
        else:
            spark.conf.set(FREED, before)
    return spark.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame, part: str = "") -> None:
    """Removes the files of a staged table that is no longer read, or one of its folders."""
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    root = df.inputFiles()
    if root:
        path = jvm.org.apache.hadoop.fs.Path(root[0]).getParent()
        while "charprobe-" not in path.getName():
            path = path.getParent()
        if part:
            path = jvm.org.apache.hadoop.fs.Path(path, part)
        path.getFileSystem(conf).delete(path, True)


def buckets_for(df: DataFrame, mb: int = 8, least: int = 48, most: int = 1 << 16) -> int:
    """How many partitions give about mb MB of input each, from the optimizer's own estimate of the size.

    Where it has none (rows that do not come from files count as endless) the input's own partitions are the measure.
    """
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if size >= 1 << 62:
        return max(least, min(most, df.rdd.getNumPartitions()))
    return max(least, min(most, size // (mb << 20) + 1))


def crc_remainder(id_col: str, modulo: int) -> F.Column:
    """crc32 of the id written as text, modulo a fold count; null ids count as the empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % modulo


def texts_of(batch: pa.RecordBatch, column: int = 1) -> list[bytes]:
    """UTF-8 bytes of each text; null counts as empty."""
    return [b"" if x is None else x for x in batch.column(column).cast(pa.binary()).to_pylist()]


def as_input(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns that the operators read, under names of our own."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def text_key(text: F.Column) -> F.Column:
    """A hash that, with the id, names a row where ids are null or repeated; null and empty texts differ."""
    return F.xxhash64(text.cast("string"))


class WordHasher:
    """64-bit hashes of words, remembered for the words seen of late."""

    def __init__(self) -> None:
        self.known: dict[bytes, int] = {}

    def __call__(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        if len(known) > CACHE_ENTRIES:
            known.clear()
        try:
            return np.fromiter(map(known.__getitem__, words), U64, len(words))
        except KeyError:
            digest = xxhash.xxh3_64_intdigest
            for w in words:
                if w not in known:
                    known[w] = digest(w)
            return np.fromiter(map(known.__getitem__, words), U64, len(words))


#: Odd multipliers of the window hashes (fixed values).
MULTIPLIERS = np.array(
    [0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB],
    dtype=U64,
)


def window_hashes(h: np.ndarray, width: int) -> np.ndarray:
    """One 64-bit hash for each window of ``width`` words; empty where the text is shorter."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, U64)
    out = np.zeros(n, U64)
    for i in range(width):
        out = (out + h[i : i + n]) * MULTIPLIERS[i % 8]
        out ^= out >> U64(29)
    return out


def packed(tokens: np.ndarray) -> tuple[bool, bytes]:
    """Ascending 64-bit numbers as 6-byte differences where they fit, else whole."""
    steps = np.diff(tokens, prepend=U64(0))
    if len(steps) > 1 and steps[1:].max() < U64(1 << 48):
        return True, tokens[:1].tobytes() + steps[1:].view(np.uint8).reshape(-1, 8)[:, :6].tobytes()
    return False, tokens.tobytes()


def unpacked(short: bool, data: bytes) -> np.ndarray:
    if not short:
        return np.frombuffer(data, U64)
    n = (len(data) - 8) // 6
    wide = np.zeros((n + 1, 8), np.uint8)
    wide[1:, :6] = np.frombuffer(data, np.uint8, offset=8).reshape(-1, 6)
    steps = wide.reshape(-1).view(U64).copy()
    steps[0] = np.frombuffer(data[:8], U64)[0]
    return np.cumsum(steps, dtype=U64)


def in_bytes(counts: np.ndarray) -> tuple[bytes, bytes]:
    """Counts as a byte each; those of 255 or more stand in a list of their own."""
    return np.minimum(counts, 255).astype(np.uint8).tobytes(), counts[counts >= 255].astype(np.uint32).tobytes()


def from_bytes(counts: bytes, large: bytes) -> np.ndarray:
    out = np.frombuffer(counts, np.uint8).astype(np.uint32)
    out[out == 255] = np.frombuffer(large, np.uint32)
    return out


def rows_of(batch: pa.RecordBatch) -> Iterator[dict]:
    """One row at a time; binary values are views of the batch's own memory."""
    for r in range(batch.num_rows):
        yield {name: batch.column(c)[r].as_buffer() if pa.types.is_binary(f.type) else batch.column(c)[r].as_py() for c, (name, f) in enumerate(zip(batch.schema.names, batch.schema))}


def ranges(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """All places of the given ranges, one after another."""
    n = ends - starts
    stop = np.cumsum(n, dtype=starts.dtype)
    return np.arange(stop[-1] if len(stop) else 0, dtype=starts.dtype) + np.repeat(starts - stop + n, n)


def batches(rows: Iterator[tuple], schema: pa.Schema, size: int = 4096, limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Tuples into record batches of at most ``size`` rows or about ``limit`` bytes of binary values."""
    heavy = [k for k, f in enumerate(schema) if pa.types.is_binary(f.type) or pa.types.is_list(f.type)]
    held, weight = [], 0
    for row in rows:
        held.append(row)
        for k in heavy:
            if row[k] is not None:
                weight += len(row[k])
        if len(held) >= size or weight >= limit:
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*held), schema)], schema=schema)
            held, weight = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*held), schema)], schema=schema)
    held = None
    released()


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for each node of edges(u, v): root is the smallest node reachable.

    Large-star and small-star steps alternate until the edges no longer change; every round is written to the
    shared folder. A hub's edges are never gathered: its smallest neighbour is a partial aggregate, and the join
    that hands it out is one that adaptive execution can split.
    """
    e = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct()
    e = staged(e, "cc")
    mark = None
    for _ in range(rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
        large = both.join(least, both["u"] == least["k"]).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), "m")
        joined = large.join(least, large["u"] == least["k"])
        small = joined.select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x")).select("x.u", "x.v")
        e = staged(small.where("u <> v").distinct(), "cc")
        now = tuple(e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("connected components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
