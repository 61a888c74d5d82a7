"""Operator 1: jump consistent hashing.

A key's shard follows from the key and the shard count alone, with no ring table; one more shard takes
rows only into itself (the law ``key``). Rows with equal ids go to one shard. A null id counts as key 0.
A null text has no bytes and the checksum of the empty text.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

U64 = np.uint64
#: Key ranges within a shard that are numbered on their own, so that no task sorts a whole shard.
CHUNKS = 1024


def mixed(keys: np.ndarray) -> np.ndarray:
    """64-bit finalizer over the keys (public splitmix constants): near keys spread over all bits."""
    x = keys.astype(U64) + U64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def jump(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each mixed key: the last jump target below ``shards``."""
    state = keys.astype(U64).copy()
    at = np.full(len(state), -1, np.int64)
    to = np.zeros(len(state), np.int64)
    live = np.flatnonzero(to < shards)
    while len(live):
        at[live] = to[live]
        state[live] = state[live] * U64(2862933555777941757) + U64(1)
        step = 2147483648.0 / ((state[live] >> U64(33)).astype(np.float64) + 1.0)
        to[live] = np.floor((at[live] + 1.0) * step).astype(np.int64)
        live = live[to[live] < shards]
    return at


def shard_column(key: F.Column, shards: int) -> F.Column:
    @F.pandas_udf("int")
    def placed(k: pd.Series) -> pd.Series:
        return pd.Series(jump(mixed(k.to_numpy(np.int64)), shards).astype(np.int32))

    return placed(F.coalesce(key.cast("long"), F.lit(0)))


def chunk_column(key: F.Column) -> F.Column:
    @F.pandas_udf("int")
    def part(k: pd.Series) -> pd.Series:
        return pd.Series((mixed(k.to_numpy(np.int64)) >> U64(54)).astype(np.int32))

    return part(F.coalesce(key.cast("long"), F.lit(0)))


def assign_shards(docs: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row with its size, checksum, shard, gapless slot in the shard, and its shard under one more shard.

    Slots follow (key range, id, checksum, size); repeated rows get slots of their own in any order. The only
    table sent to all tasks has at most shards x CHUNKS rows.
    """
    if shards < 1:
        raise ValueError("at least one shard")
    key, text = F.col(id_col), F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    placed = docs.select(
        key.cast("long").alias("doc_id"),
        (F.octet_length(text) + F.lit(16)).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.lit("key").alias("law"),
        shard_column(key, shards).alias("shard"),
        shard_column(key, shards + 1).alias("grown_shard"),
        chunk_column(key).alias("chunk"),
    )
    counts = docs.select(shard_column(key, shards).alias("shard"), chunk_column(key).alias("chunk")).groupBy("shard", "chunk").agg(F.count("*").alias("rows"))
    before = Window.partitionBy("shard").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("shard", "chunk", F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("first_slot"))
    if shards * CHUNKS <= 2_000_000:
        starts = F.broadcast(starts)
    within = Window.partitionBy("shard", "chunk").orderBy("doc_id", "text_crc32", "size")
    return (
        placed.withColumn("place", F.row_number().over(within) - 1)
        .join(starts, ["shard", "chunk"])
        .select("doc_id", "size", "text_crc32", "law", "shard", (F.col("first_slot") + F.col("place")).cast("long").alias("slot"), "grown_shard")
    )
