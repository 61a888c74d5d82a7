"""Tables with declared schemas, artefact sinks, and the staged vocabulary as a data source."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; text tables with the schema declared here, so that nothing is inferred."""
    reader = spark.read.schema(SCHEMAS[name]) if name in SCHEMAS else spark.read
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame, key: str) -> DataFrame:
    """df dealt out by a key where it has fewer partitions than there are cores: a small file is one task to scan, but not to work on."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(2 * cores, key) if df.rdd.getNumPartitions() < cores else df


def in_runs(source: Iterator[pa.RecordBatch], most: int, column: int = 1) -> Iterator[pa.RecordBatch]:
    """Batches cut into runs of rows whose lists (or texts) of a column have at most ``most`` entries (bytes) together, or of one
    row: memory does not follow how long a batch's rows are."""
    for batch in source:
        x = batch.column(column)
        size = pc.list_value_length(x) if pa.types.is_list(x.type) else pc.binary_length(x)
        ends, lo = np.cumsum(size.fill_null(0).to_numpy(zero_copy_only=False), dtype=np.int64), 0
        while lo < len(ends):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, "right")))
            yield batch.slice(lo, hi - lo)
            lo = hi
    released()


def released() -> None:
    """Gives freed memory back to the system: a worker outlives its task, and what it keeps counts in the executor's memory."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc's alone
    if trim is not None:
        trim(0)


def checkpointed(df: DataFrame) -> DataFrame:
    """df.checkpoint() into spark.checkpoint.dir; a folder of our own is set only where none is (as in tests)."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        import tempfile

        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="charprobe-"))
    return df.checkpoint()


def write_results(df: DataFrame, path: str, by: str = "experiment") -> None:
    """Results by experiment; a rerun replaces only the partitions that it has."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


class _StagedReader(DataSourceReader):
    def __init__(self, letters: str, longest: int) -> None:
        self.letters, self.longest = letters, longest

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((g, a)) for g in (False, True) for a in self.letters]

    def read(self, partition: InputPartition):
        spaced, first = partition.value
        level = [first]
        for n in range(1, self.longest + 1):
            for s in level:
                yield s, spaced, n
            level = [s + c for s in level for c in self.letters]


class StagedVocabularySource(DataSource):
    """``spark.read.format("staged_vocab").option("letters", ...).option("longest", ...)``."""

    @classmethod
    def name(cls) -> str:
        return "staged_vocab"

    def schema(self) -> str:
        return "surface string, has_space boolean, n_letters int"

    def reader(self, schema) -> DataSourceReader:
        return _StagedReader(self.options.get("letters", "abcdefghijklmnopqrstuvwxyz"), int(self.options.get("longest", 3)))
