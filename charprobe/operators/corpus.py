"""Documents to words: pre-tokenizing, counting, cleaning, text of web pages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A word with the white space before it, if there is one.
SPACED_WORD = r"[ \t\n\r]?[A-Za-z]+"


def word_array(text: F.Column) -> F.Column:
    """Words of a text in order, in the row: structs (word, has_space), lower case. No shuffle."""
    found = F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(SPACED_WORD), F.lit(0))
    return F.transform(found, lambda m: F.struct(F.lower(F.regexp_replace(m, r"^[ \t\n\r]", "")).alias("word"), F.rlike(m, F.lit(r"^[ \t\n\r]")).alias("has_space")))


def words(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, pos, word, has_space of every word; null and empty texts have none."""
    found = F.regexp_extract_all(F.coalesce(F.col(text_col), F.lit("")), F.lit(SPACED_WORD), F.lit(0))
    first = F.ascii("m")
    spaced = (first == 32) | first.between(9, 13)
    return docs.select(F.col(id_col).alias("doc_id"), F.posexplode(found).alias("pos", "m")).select("doc_id", "pos", F.lower(F.when(spaced, F.expr("substr(m, 2)")).otherwise(F.col("m"))).alias("word"), spaced.alias("has_space"))


def word_counts(word_rows: DataFrame) -> DataFrame:
    return word_rows.groupBy("word", "has_space").agg(F.count("*").alias("freq"))


def quality_docs(docs: DataFrame, labels: DataFrame, least: int = 1) -> DataFrame:
    return docs.join(labels.where(F.col("quality") >= least).select("doc_id").distinct(), "doc_id", "left_semi")


def exact_copies_dropped(docs: DataFrame) -> DataFrame:
    """The smallest doc_id of each text; a copy's text is not shuffled, only its hash."""
    least = docs.groupBy(F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("h")).agg(F.min("doc_id").alias("doc_id"))
    return docs.join(least.select("doc_id"), "doc_id", "left_semi")


def ngram_keys(text: F.Column, n: int) -> F.Column:
    """Hashes of a text's runs of n words (split at ASCII white space, A-Z lowered); shorter texts have none."""
    plain = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    w = F.regexp_extract_all(plain, F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
    # The words are bound once: inside the inner lambda they would be cut out of the text anew for every run.
    return F.flatten(F.transform(F.array(w), lambda x: F.when(F.size(x) >= n, F.transform(F.sequence(F.lit(1), F.size(x) - n + 1), lambda i: F.xxhash64(F.slice(x, i, F.lit(n))))).otherwise(F.array().cast("array<bigint>"))))


def without_benchmark(docs: DataFrame, benchmark: DataFrame, n: int = 13, most: int = 2_000_000) -> DataFrame:
    """Documents that share no run of n words with a benchmark item.

    The benchmark's runs are broadcast when there are at most ``most``; else both sides meet by hash.
    """
    runs = benchmark.select(F.explode(F.array_distinct(ngram_keys(F.col("text"), n))).alias("h")).distinct()
    small = runs.limit(most + 1).count() <= most
    found = docs.select("doc_id", F.explode(F.array_distinct(ngram_keys(F.col("text"), n))).alias("h")).join(F.broadcast(runs) if small else runs, "h", "left_semi")
    return docs.join(found.select("doc_id").distinct(), "doc_id", "left_anti")


def html_text(html: F.Column) -> F.Column:
    """Text of a page: scripts, styles and tags go, five entities are resolved, white space is collapsed."""
    x = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    x = F.regexp_replace(x, r"(?s)<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        x = F.replace(x, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(x, r"[ \t\n\r]+", " "))
