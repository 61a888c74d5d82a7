"""Operator 8: a content-addressed store of token ids.

A document's ids (with its end id) are cut into chunks where a rolling hash over the last ids has its low bits
zero; a chunk is kept once, under the digest of its bytes. The store has three tables below one folder:

* ``chunks``: digest, n_ids and the ids as little-endian unsigned 16-bit values where all fit, else 32-bit;
* ``recipes``: per document in ascending order of ids: start, n_tokens, its chunks' digests and its Merkle root;
* ``manifest``: per range of documents the number of documents and ids and the root over their roots.

Reading checks every chunk against its digest, every recipe against its root and every range against the
manifest, and fails loudly where one does not agree. Null texts count as empty; null ids come first; documents
with equal ids follow their roots and keep rows of their own.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import as_input, batches, buckets_for, staging_path
from .token_ids import ended

U64 = np.uint64
#: Ids under the rolling hash (a power of two), its low bits that end a chunk, and a chunk's least and greatest number of ids.
ROLL, MASK_BITS, LEAST, MOST = 8, 9, 64, 4096
#: Documents whose roots make one block of the manifest's tree.
BLOCK = 1024
#: Digests that a task remembers while it encodes.
SEEN = 500_000
MIXED = pa.schema([("key", pa.int64()), ("kind", pa.string()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("root", pa.binary()), ("digests", pa.list_(pa.binary())), ("lengths", pa.list_(pa.int32())), ("digest", pa.binary()), ("n_ids", pa.int32()), ("wide", pa.bool_()), ("payload", pa.binary())])
MIXED_SQL = "key long, kind string, doc_id long, n_tokens long, root binary, digests array<binary>, lengths array<int>, digest binary, n_ids int, wide boolean, payload binary"


def rolling_ends(ids: np.ndarray) -> np.ndarray:
    """Numbers of ids up to and with each at which the rolling hash over the last ROLL ids has its low bits zero."""
    h = (ids.astype(U64) + U64(1)) * U64(0x9E3779B97F4A7C15)
    width, power = 1, 0x5851F42D4C957F2D
    while width < ROLL:  # a hash over twice as many ids from two of the last width
        wider = h.copy()
        wider[width:] += h[:-width] * U64(power)
        h, width, power = wider, 2 * width, power * power & (1 << 64) - 1
    return np.flatnonzero((h >> U64(64 - MASK_BITS)) == 0) + 1


def chunk_ends(found: list[int], start: int, end: int) -> list[int]:
    """Ends of the chunks of the document from start to end, of which ``found`` are the rolling hash's ends."""
    ends, last = [], start
    for e in found:
        while e - last > MOST:
            last += MOST
            ends.append(last)
        if e - last >= LEAST and e < end:
            ends.append(e)
            last = e
    while end - last > MOST:
        last += MOST
        ends.append(last)
    if end > last:
        ends.append(end)
    return ends


def cut_points(ids: np.ndarray) -> list[int]:
    """Ends of the chunks of one id stream; they depend on the content alone, so shared passages cut alike."""
    return chunk_ends(rolling_ends(ids).tolist() if len(ids) >= LEAST else [], 0, len(ids))


def merkle(leaves: list[bytes]) -> bytes:
    """Root of a binary hash tree; an odd node moves up as it is; no leaves: the digest of nothing."""
    level = [hashlib.blake2b(b"\0" + x, digest_size=16).digest() for x in leaves]
    if not level:
        return hashlib.blake2b(b"", digest_size=16).digest()
    while len(level) > 1:
        paired = [hashlib.blake2b(b"\1" + a + b, digest_size=16).digest() for a, b in zip(level[::2], level[1::2])]
        level = paired + level[len(paired) * 2 :]
    return level[0]


def digest_of(payload: bytes, wide: bool) -> bytes:
    return hashlib.blake2b(payload, digest_size=16, person=b"w4" if wide else b"w2").digest()


def encode_rows(doc_ids: list[int | None], ids: np.ndarray, at: np.ndarray, seen: set[bytes]) -> Iterator[tuple]:
    """A recipe row for each document, and a chunk row for each chunk that is new to this task.

    The documents' ids stand one after another; a chunk has at least LEAST ids before its end is looked for, more than
    the rolling hash spans, so no end depends on the document before. ``seen`` only saves rows: it starts anew when full.
    """
    found = rolling_ends(ids)
    near = np.searchsorted(found, at, "right").tolist()
    narrow = ids.astype("<u2") if not len(ids) or int(ids.max()) <= 0xFFFF else None
    at = at.tolist()
    for k, doc_id in enumerate(doc_ids):
        digests, lengths, last = [], [], at[k]
        for end in chunk_ends(found[near[k] : near[k + 1]].tolist(), at[k], at[k + 1]):
            wide = narrow is None and int(ids[last:end].max()) > 0xFFFF
            payload = (ids[last:end].astype("<u4" if wide else "<u2") if narrow is None else narrow[last:end]).tobytes()
            d = digest_of(payload, wide)
            digests.append(d)
            lengths.append(end - last)
            if d not in seen:
                if len(seen) >= SEEN:
                    seen.clear()
                seen.add(d)
                yield int.from_bytes(d[:8], "little", signed=True), "chunk", None, None, None, None, None, d, end - last, wide, payload
            last = end
        root = merkle(digests)
        yield xxhash.xxh3_64_intdigest(root + repr(doc_id).encode()) - (1 << 63), "recipe", doc_id, at[k + 1] - at[k], root, digests, lengths, None, None, None, None


def unique_chunks(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Drops repeated chunk rows; all rows of a digest are in this task, which holds the digests of its share alone."""
    seen: set[bytes] = set()
    for batch in source:
        keep = []
        for kind, d in zip(batch.column("kind").to_pylist(), batch.column("digest").to_pylist()):
            keep.append(kind == "recipe" or d not in seen)
            if kind == "chunk":
                seen.add(d)
        yield batch.filter(pa.array(keep, pa.bool_()))


def write_store(docs: DataFrame, path: str, vocabulary: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encodes all documents and writes the store below ``path``. Every document is encoded once."""
    spark = docs.sparkSession

    def encode(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        parts = (encode_rows(batch.column(0).to_pylist(), ids, at, seen) for batch, ids, at in ended(source, vocabulary, end_id))
        yield from batches(chain.from_iterable(parts), MIXED)

    mixed = as_input(docs, id_col, text_col).mapInArrow(encode, MIXED_SQL)
    parts = buckets_for(docs, mb=8, least=16)
    first = mixed.repartition(parts, "key").mapInArrow(unique_chunks, MIXED_SQL)
    first.drop("key").write.partitionBy("kind").option("compression", "zstd").parquet(f"{path}/content")
    recipes = _content(spark, path, "recipe").select("doc_id", "n_tokens", "root", "digests", "lengths")
    ranged = recipes.repartitionByRange(max(1, parts // 4), "doc_id").sortWithinPartitions("doc_id", "root").withColumn("range", F.spark_partition_id())
    ranged.write.partitionBy("range").parquet(f"{path}/ranges")
    held = spark.read.schema("doc_id long, n_tokens long, root binary, digests array<binary>, lengths array<int>, range int").parquet(f"{path}/ranges")
    totals = held.groupBy("range").agg(F.sum("n_tokens").alias("ids"), F.count("*").alias("documents"))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # a row per range: few
    totals = totals.select("range", "documents", "ids", F.coalesce(F.sum("ids").over(before), F.lit(0)).alias("first_id"))
    within = Window.partitionBy("range").orderBy("doc_id", "root").rowsBetween(Window.unboundedPreceding, -1)
    placed = held.join(F.broadcast(totals.select("range", "first_id")), "range").withColumn("start", F.col("first_id") + F.coalesce(F.sum("n_tokens").over(within), F.lit(0)))
    placed = placed.withColumn("block", F.floor((F.row_number().over(Window.partitionBy("range").orderBy("doc_id", "root")) - 1) / BLOCK).cast("long"))
    placed.select("range", "block", "doc_id", "start", "n_tokens", "root", "digests", "lengths").write.partitionBy("range").parquet(f"{path}/recipes")
    range_roots(_recipes(spark, path)).join(totals.select("range", "first_id"), "range").coalesce(1).write.parquet(f"{path}/manifest")


def range_roots(recipes: DataFrame) -> DataFrame:
    """Root, documents and ids of each range: a hash over its blocks' hashes, each over the roots of BLOCK documents."""

    def chained(key: str, value: str) -> F.Column:
        return F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(key, value))), lambda x: x[value]), ""), 256)

    blocks = recipes.withColumn("h", F.hex("root")).groupBy("range", "block").agg(chained("start", "h").alias("h"), F.count("*").alias("documents"), F.sum("n_tokens").alias("ids"))
    return blocks.groupBy("range").agg(chained("block", "h").alias("range_root"), F.sum("documents").alias("documents"), F.sum("ids").alias("ids"))


def _content(spark: SparkSession, path: str, kind: str) -> DataFrame:
    schema = "doc_id long, n_tokens long, root binary, digests array<binary>, lengths array<int>, digest binary, n_ids int, wide boolean, payload binary, kind string"
    return spark.read.schema(schema).parquet(f"{path}/content").where(F.col("kind") == kind)


def _recipes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("block long, doc_id long, start long, n_tokens long, root binary, digests array<binary>, lengths array<int>, range int").parquet(f"{path}/recipes")


class BrokenStore(ValueError):
    pass


def _as_ids(payload: bytes, wide: bool) -> np.ndarray:
    return np.frombuffer(payload, "<u4" if wide else "<u2").astype("<u4")


def checked_chunks(spark: SparkSession, path: str) -> DataFrame:
    """digest, n_ids and crc32 of the ids of every chunk in the files, each checked against its digest."""
    schema = pa.schema([("digest", pa.binary()), ("n_ids", pa.int32()), ("crc", pa.int64())])

    def check(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for batch in source:
                for d, wide, payload in zip(*(batch.column(c).to_pylist() for c in ("digest", "wide", "payload"))):
                    if digest_of(payload, wide) != d:
                        raise BrokenStore(f"chunk {d.hex()} does not agree with its digest")
                    ids = _as_ids(payload, wide)
                    yield d, len(ids), zlib.crc32(ids.tobytes())

        yield from batches(rows(), schema)

    return _content(spark, path, "chunk").select("digest", "wide", "payload").mapInArrow(check, "digest binary, n_ids int, crc long")


def _times(matrix: list[int], vector: int) -> int:
    out, k = 0, 0
    while vector:
        if vector & 1:
            out ^= matrix[k]
        vector >>= 1
        k += 1
    return out


_tables: list[list[list[int]]] = []  # by k: what 2**k zero bytes make of a crc32, by its four bytes


def _table(k: int) -> list[list[int]]:
    if not _tables:
        matrix = [0xEDB88320] + [1 << i for i in range(31)]  # one zero bit
        for _ in range(3):
            matrix = [_times(matrix, v) for v in matrix]
        while len(_tables) < 40:
            _tables.append([[_times(matrix, v << 8 * b) for v in range(256)] for b in range(4)])
            matrix = [_times(matrix, v) for v in matrix]
    return _tables[k]


def joined_crc(parts: list[tuple[int, int]]) -> int:
    """crc32 of the whole from (crc32, bytes) of its parts in order."""
    total = 0
    for crc, size in parts:
        k = 0
        while size and total:
            if size & 1:
                a, b, c, d = _table(k)
                total = a[total & 255] ^ b[total >> 8 & 255] ^ c[total >> 16 & 255] ^ d[total >> 24]
            size >>= 1
            k += 1
        total ^= crc
    return total


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, computed from the store's files."""
    verify_manifest(spark, path)
    recipes = _recipes(spark, path).select("doc_id", "start", "n_tokens", "root", "digests")
    parts = recipes.select("doc_id", "start", "n_tokens", "root", F.posexplode("digests").alias("k", "digest"))
    met = parts.join(checked_chunks(spark, path), "digest", "left")
    whole = met.groupBy("start", "doc_id", "n_tokens", "root").agg(F.array_sort(F.collect_list(F.struct("k", "digest", "crc", "n_ids"))).alias("parts"))  # as many as one document has chunks
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def combine(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for batch in source:
                for doc_id, start, n, root, parts in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "start", "n_tokens", "root", "parts"))):
                    if any(p["crc"] is None for p in parts) or merkle([p["digest"] for p in parts]) != root or sum(p["n_ids"] for p in parts) != n:
                        raise BrokenStore(f"document {doc_id} cannot be rebuilt")
                    yield doc_id, start, n, joined_crc([(p["crc"], 4 * p["n_ids"]) for p in parts])

        yield from batches(rows(), schema)

    return whole.mapInArrow(combine, "doc_id long, start long, n_tokens long, ids_crc32 long")


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start and ids (array<int>) of every document, rebuilt from its chunks."""
    verify_manifest(spark, path)
    parts = _recipes(spark, path).select("doc_id", "start", F.posexplode("digests").alias("k", "digest"))
    chunks = _content(spark, path, "chunk").select("digest", "wide", "payload")
    whole = parts.join(chunks, "digest").groupBy("start", "doc_id").agg(F.array_sort(F.collect_list(F.struct("k", "digest", "wide", "payload"))).alias("parts"))
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("ids", pa.list_(pa.int32()))])

    def rebuild(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for batch in source:
                for doc_id, start, parts in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "start", "parts"))):
                    for p in parts:
                        if digest_of(p["payload"], p["wide"]) != p["digest"]:
                            raise BrokenStore(f"chunk {p['digest'].hex()} does not agree with its digest")
                    yield doc_id, start, np.concatenate([_as_ids(p["payload"], p["wide"]) for p in parts]).astype(np.int32)

        yield from batches(rows(), schema)

    return whole.mapInArrow(rebuild, "doc_id long, start long, ids array<int>")


def verify_manifest(spark: SparkSession, path: str) -> None:
    """Every range's root and totals, computed anew from the recipes, must be those of the manifest."""
    told = spark.read.schema("range int, range_root string, documents long, ids long, first_id long").parquet(f"{path}/manifest")
    seen = range_roots(_recipes(spark, path)).select("range", F.col("range_root").alias("own_root"), F.col("documents").alias("own_documents"), F.col("ids").alias("own_ids"))
    odd = told.join(seen, "range", "full").where("not (range_root <=> own_root and documents <=> own_documents and ids <=> own_ids)")
    if odd.limit(1).count():
        raise BrokenStore("the manifest does not agree with the recipes")


def store_and_read(docs: DataFrame, vocabulary: str, end_id: int = 2) -> DataFrame:
    """Writes all documents to a new store in the shared folder and returns what its files say."""
    path = staging_path(docs.sparkSession, "store")
    write_store(docs, path, vocabulary, end_id)
    return read_digests(docs.sparkSession, path)
