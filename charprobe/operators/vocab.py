"""Vocabularies: assembly, the letter-only target vocabulary, restrictions, set operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import letter_mask


def build(tokens: DataFrame, size: int | None = None) -> DataFrame:
    """token_id by falling frequency (ties by surface, spaced last), surface, has_space, n_letters, freq."""
    return ranked(tokens.groupBy("surface", "has_space").agg(F.count("*").alias("freq")), size)


def ranked(counted: DataFrame, size: int | None = None) -> DataFrame:
    """The same from counts (surface, has_space, freq)."""
    if size is not None:
        counted = counted.orderBy(F.desc("freq"), "surface", "has_space").limit(size)
    rank = Window.orderBy(F.desc("freq"), "surface", "has_space")  # a vocabulary is small once counted
    return counted.select((F.row_number().over(rank) - 1).alias("token_id"), "surface", "has_space", F.length("surface").alias("n_letters"), "freq")


def target_vocab(vocab: DataFrame, alphabet: str = "ascii") -> DataFrame:
    """Entries made only of letters (a space before them is a flag of its own)."""
    return vocab.where(F.col("surface").rlike(r"^[A-Za-z]+$" if alphabet == "ascii" else r"^\p{L}+$"))


def with_mask(vocab: DataFrame, case_sensitive: bool = False) -> DataFrame:
    return vocab.withColumn("letter_mask", letter_mask(F.col("surface"), case_sensitive))


def max_letters(vocab: DataFrame, most: int = 3) -> DataFrame:
    return vocab.where(F.col("n_letters") <= most)


def shared_and_own(a: DataFrame, b: DataFrame) -> DataFrame:
    """How many surfaces two vocabularies share, and how many each has alone."""
    x, y = a.select("surface").distinct().withColumn("a", F.lit(1)), b.select("surface").distinct().withColumn("b", F.lit(1))
    both = x.join(y, "surface", "full").select(F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))
    return both.agg(F.sum(F.col("a") * F.col("b")).alias("shared"), F.sum(F.col("a") * (1 - F.col("b"))).alias("only_a"), F.sum(F.col("b") * (1 - F.col("a"))).alias("only_b"))


#: A vocabulary of more entries is not broadcast.
BROADCAST = 2_000_000


def bounded(vocab: DataFrame, most: int = BROADCAST) -> DataFrame:
    """The vocabulary marked for broadcast if it has at most ``most`` entries (counted, not assumed); else as it is."""
    return F.broadcast(vocab) if vocab.limit(most + 1).count() <= most else vocab
