"""Operator 5: URL rules by hashed host suffixes and path prefixes, in DataFrame functions only.

A rule is (verdict, host, path). It fits its host and all subdomains if the url's path starts with the rule's
path. Each url expands into (host suffix, path prefix) expressions, with path prefixes only of lengths that some
rule has; expressions meet the rules on the first 32 bits of a SHA-256, then the full digests must agree. The
longest rule wins (host and path together), then the longer host, then block before allow. Without a rule the
verdict is allow. A null url, or one without ``://``, has an empty host and path, and no rule fits it. Repeated
rows stay repeated.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BIT32 = 8  # hex digits of the short prefix


def host_of(url: F.Column) -> F.Column:
    after = F.when(F.instr(url, "://") > 0, F.regexp_replace(url, r"(?s)^.*?://", ""))
    return F.coalesce(F.translate(F.regexp_extract(after, r"(?s)^[^/?#]*", 0), UPPER, LOWER), F.lit(""))


def path_of(url: F.Column) -> F.Column:
    after = F.when(F.instr(url, "://") > 0, F.regexp_replace(url, r"(?s)^.*?://", ""))
    return F.coalesce(F.regexp_extract(after, r"(?s)^[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_table(spark: SparkSession, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """rules: (verdict, host, path); the same host and path twice: block wins."""
    rows = [(v, h, p) for v, h, p in rules]
    return spark.createDataFrame(rows, "rule_verdict string, rule_host string, rule_path string")


def judge_urls(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """page_id, host, path, rule (null without one) and verdict of every row."""
    hashed = rules.select(
        F.sha2(F.concat("rule_host", F.lit("\n"), "rule_path"), 256).alias("digest"),
        F.concat("rule_host", "rule_path").alias("rule"),
        F.length("rule_host").alias("host_length"),
        F.col("rule_verdict"),
    )
    keyed = hashed.withColumn("short", F.substring("digest", 1, BIT32))
    lengths = sorted(x[0] for x in rules.select(F.length("rule_path")).distinct().collect())  # as many as rule lengths differ
    page = pages.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    prefixes = F.filter(F.array(*[F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in lengths]) if lengths else F.array(F.lit(None).cast("string")), lambda x: x.isNotNull())
    # A host may have any number of labels; a rule's host has no more than the longest rule, so longer suffixes cannot fit.
    most = F.lit((rules.agg(F.max(F.size(F.split("rule_host", r"\.")))).first()[0]) or 1)
    near = F.slice(suffixes, F.greatest(F.lit(1), F.size(labels) - most + 1), most)
    expressions = F.flatten(F.transform(near, lambda s: F.transform(prefixes, lambda p: F.concat(s, F.lit("\n"), p))))
    # The first, null expression stands for the row itself; summed, it counts the copies of a repeated row.
    expanded = page.select("page_id", "host", "path", F.explode(F.concat(F.array(F.lit(None).cast("string")), expressions)).alias("expression"))
    expanded = expanded.withColumn("own_digest", F.sha2("expression", 256)).withColumn("own_short", F.substring("own_digest", 1, BIT32))
    met = expanded.join(keyed, (expanded["own_short"] == keyed["short"]) & (expanded["own_digest"] == keyed["digest"]), "left")
    rank = F.struct(F.length("rule").alias("a"), F.col("host_length").alias("b"), (F.col("rule_verdict") == "block").cast("int").alias("c"), F.col("rule").alias("rule"), F.col("rule_verdict").alias("verdict"))
    best = met.groupBy("page_id", "host", "path").agg(F.max(F.when(F.col("rule").isNotNull(), rank)).alias("best"), F.sum(F.col("expression").isNull().cast("int")).alias("copies"))
    return best.select(
        "page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"), F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("copy")
    ).drop("copy")
