"""Streams: running counts, append-only tokens, event windows, deduplication."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import corpus, stats, tokenize
from ..sources import SCHEMAS


def document_stream(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(SCHEMAS["documents"]).option("maxFilesPerTrigger", files).parquet(folder)


def running_word_counts(docs: DataFrame) -> DataFrame:
    return corpus.word_counts(corpus.words(docs))


def running_boundary_counts(docs: DataFrame) -> DataFrame:
    return stats.fixed_boundary_pairs(corpus.words(docs))


def token_stream(docs: DataFrame) -> DataFrame:
    """Stateless: tokens of a frozen tokenizer, appended."""
    return tokenize.fixed_width_tokens(corpus.words(docs))


def event_windows(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Events and their values in tumbling (or, with ``slide``, sliding) windows behind a watermark."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("at", late)
    w = F.window("at", length, slide) if slide else F.window("at", length)
    return timed.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 6).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def event_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    timed = events.withColumn("at", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("at", late)
    return timed.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(docs: DataFrame, time_col: str, late: str = "1 day") -> DataFrame:
    """Texts seen within the watermark pass once."""
    return docs.withColumn("text_hash", F.md5(F.coalesce("text", F.lit("")).cast("binary"))).withWatermark(time_col, late).dropDuplicatesWithinWatermark(["text_hash"])


def drift_alarm(stream: DataFrame, reference: DataFrame, path: str, threshold: float, checkpoint: str):
    """For each micro-batch: total variation distance of its boundary letters from the reference's, appended to ``path``."""
    total = reference.agg(F.sum("freq")).first()[0]
    shares = reference.select("last", "first", (F.col("freq") / F.lit(total)).alias("p"))

    def judge(batch: DataFrame, number: int) -> None:
        seen = stats.fixed_boundary_pairs(corpus.words(batch))
        n = seen.agg(F.sum("freq")).first()[0]
        if n:
            both = seen.select("last", "first", (F.col("freq") / F.lit(n)).alias("q")).join(shares, ["last", "first"], "full").fillna(0.0, ["p", "q"])
            both.agg(F.lit(number).alias("batch"), (F.sum(F.abs(F.col("p") - F.col("q"))) / 2).alias("distance")).withColumn("alarm", F.col("distance") > threshold).write.mode("append").parquet(path)

    return stream.writeStream.foreachBatch(judge).option("checkpointLocation", checkpoint)


def with_vocabulary(tokens: DataFrame, vocab: DataFrame) -> DataFrame:
    """Stream-static join: ids of arriving tokens."""
    return tokens.join(F.broadcast(vocab.select("surface", "has_space", "token_id")), ["surface", "has_space"], "left")
