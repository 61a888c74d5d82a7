"""Merge strength against subword boundaries, orthography, morphology."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def merge_strength(merges: DataFrame) -> DataFrame:
    """left, right, strength of the rules that join two single letters: earlier rules are stronger."""
    pairs = merges.where("length(left) = 1 and length(right) = 1 and left <> ' '")
    return pairs.select("left", "right", (F.count("*").over(Window.partitionBy()) - F.row_number().over(Window.orderBy("rank")) + 1).alias("strength"))  # as many rows as letter pairs


def _rows(tokens: DataFrame) -> DataFrame:
    return tokens.groupBy("doc_id", "word_pos").agg(F.transform(F.array_sort(F.collect_list(F.struct("sub_pos", "surface"))), lambda x: x["surface"]).alias("pieces"))


def row_boundary_pairs(rows: DataFrame) -> DataFrame:
    """last, first, freq over rows with ``pieces``: last letter of a piece and first letter of the next one in the same word.
    Counted inside the row, so the shuffle is 26 x 26 keys."""
    near = F.zip_with(F.slice("pieces", F.lit(1), F.size("pieces") - 1), F.slice("pieces", F.lit(2), F.size("pieces")), lambda a, b: F.struct(F.right(a, F.lit(1)).alias("last"), F.left(b, F.lit(1)).alias("first")))
    return rows.where(F.size("pieces") > 1).select(F.explode(near).alias("p")).groupBy("p.last", "p.first").agg(F.count("*").alias("freq"))


def boundary_pairs(tokens: DataFrame) -> DataFrame:
    """The same of exploded tokens, whose words are put together first."""
    return row_boundary_pairs(_rows(tokens))


def fixed_boundary_pairs(words: DataFrame, width: int = 3) -> DataFrame:
    """boundary_pairs of fixed-width chunks straight from the words: no regrouping, so the shuffle is the 676 counts."""
    ends = F.filter(F.sequence(F.lit(width), F.greatest(F.length("word"), F.lit(width)), F.lit(width)), lambda i: i < F.length("word"))
    pairs = words.select(F.explode(F.transform(ends, lambda i: F.struct(F.substring("word", i, F.lit(1)).alias("last"), F.substring("word", i + 1, F.lit(1)).alias("first")))).alias("p"))
    return pairs.groupBy("p.last", "p.first").agg(F.count("*").alias("freq"))


def inner_pairs(tokens: DataFrame) -> DataFrame:
    """last, first, freq: adjacent letters inside one token."""
    n = F.length("surface")
    pairs = F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.struct(F.substring("surface", i, F.lit(1)).alias("last"), F.substring("surface", i + 1, F.lit(1)).alias("first")))
    return tokens.where(n > 1).select(F.explode(pairs).alias("p")).groupBy("p.last", "p.first").agg(F.count("*").alias("freq"))


def boundary_rate(boundary: DataFrame, inner: DataFrame) -> DataFrame:
    """Share of a letter pair's occurrences that a boundary cuts."""
    met = boundary.withColumnRenamed("freq", "at_boundary").join(inner.withColumnRenamed("freq", "inside"), ["last", "first"], "full")
    b, i = F.coalesce("at_boundary", F.lit(0)), F.coalesce("inside", F.lit(0))
    return met.select("last", "first", b.alias("at_boundary"), i.alias("inside"), F.round(b / (b + i), 9).alias("rate"))


def average_rank(value: F.Column) -> F.Column:
    """Rank with ties at their mean, over the whole (small) table."""
    return F.rank().over(Window.orderBy(value)) + (F.count("*").over(Window.partitionBy(value)) - 1) / 2.0


def spearman(table: DataFrame, x: str, y: str) -> DataFrame:
    ranked = table.select(average_rank(F.col(x)).alias("rx"), average_rank(F.col(y)).alias("ry"))
    return ranked.agg(F.count("*").alias("pairs"), F.round(F.corr("rx", "ry"), 9).alias("spearman"))


def pearson_of_logs(strength: DataFrame, boundary: DataFrame) -> DataFrame:
    """Pearson's correlation of rule strength and log(1 + boundary frequency) over all letter pairs."""
    met = strength.join(boundary, (F.col("left") == F.col("last")) & (F.col("right") == F.col("first")), "left").select("strength", F.log1p(F.coalesce("freq", F.lit(0))).alias("log_freq"))
    return met.agg(F.count("*").alias("pairs"), F.round(F.corr("strength", "log_freq"), 9).alias("pearson"))


def strength_vs_boundary(strength: DataFrame, boundary: DataFrame) -> DataFrame:
    """Spearman's rank correlation of rule strength and boundary frequency over all letter pairs; absent pairs count 0."""
    met = strength.join(boundary, (F.col("left") == F.col("last")) & (F.col("right") == F.col("first")), "left").select("strength", F.coalesce("freq", F.lit(0)).alias("freq"))
    return spearman(met, "strength", "freq")


def binned(strength: DataFrame, boundary: DataFrame, bins: int = 10) -> DataFrame:
    met = strength.join(boundary, (F.col("left") == F.col("last")) & (F.col("right") == F.col("first")), "left").select("strength", F.coalesce("freq", F.lit(0)).alias("freq"))
    cut = F.ntile(bins).over(Window.orderBy(F.desc("strength")))
    return met.withColumn("bin", cut).groupBy("bin").agg(F.sum("freq").alias("boundary_freq"), F.count("*").alias("pairs"))


def boundary_mi(pairs: DataFrame) -> DataFrame:
    """Mutual information in bits of the two letters at a boundary, with the bias of its plug-in estimate."""
    n = F.sum("freq").over(Window.partitionBy())
    a, b = F.sum("freq").over(Window.partitionBy("last")), F.sum("freq").over(Window.partitionBy("first"))
    terms = pairs.select("last", "first", "freq", (F.col("freq") / n * F.log2(F.col("freq") * n / (a * b))).alias("term"))
    bias = (F.count_distinct("last") - 1) * (F.count_distinct("first") - 1) / (2 * F.sum("freq") * F.log(F.lit(2.0)))
    return terms.agg(F.sum("freq").alias("n"), F.round(F.sum("term"), 9).alias("bits"), F.round(bias, 9).alias("bias"))


def check_segmentation(rows: DataFrame, strength: DataFrame) -> DataFrame:
    """Places where a spaced piece of two letters stands before a bare trigram although the rules do not allow it: none should be.

    rows: words with ``pieces``. The places are counted by their letters first, so 26**4 keys meet the rules at most.
    """
    a, b = F.element_at("pieces", 1), F.element_at("pieces", 2)
    near = rows.where(F.size("pieces") > 1).select(a.alias("a"), b.alias("b")).where("startswith(a, ' ') and length(a) = 3 and length(b) = 3")
    near = near.select(F.substring("a", 3, 1).alias("beta"), F.substring("b", 1, 1).alias("x"), F.substring("b", 2, 1).alias("y"), F.substring("b", 3, 1).alias("gamma")).groupBy("beta", "x", "y", "gamma").agg(F.count("*").alias("n"))
    m = lambda name, a, b: F.broadcast(strength.select(F.col("left").alias(a), F.col("right").alias(b), F.col("strength").alias(name)))  # noqa: E731  676 rows
    met = near.join(m("before", "beta", "x"), ["beta", "x"]).join(m("inside", "x", "y"), ["x", "y"]).join(m("behind", "y", "gamma"), ["y", "gamma"])
    broken = (F.col("before") > F.col("inside")) | (F.col("inside") < F.col("behind"))
    return met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("cases"), F.coalesce(F.sum(F.when(broken, F.col("n"))), F.lit(0)).alias("violations"))


def pattern_position(counts: DataFrame, patterns: Sequence[str] = ("ck", "dge", "tch", "bb", "dd", "ff", "ll", "nn", "ss", "tt")) -> DataFrame:
    """Weight of letter patterns by place in the word and by a vowel before them, with all subtotals (null: all)."""
    rows = counts.withColumn("pattern", F.explode(F.array(*[F.lit(p) for p in patterns]))).withColumn("at", F.instr(F.col("word"), F.col("pattern"))).where("at > 0")
    end = F.col("at") + F.length("pattern") - 1 == F.length("word")
    place = F.when(F.col("at") == 1, "start").when(end, "end").otherwise("middle")
    vowel = F.when(F.substring("word", F.col("at") - 1, F.lit(1)).isin(*"aeiou") & (F.col("at") > 1), "vowel").otherwise("other")
    return rows.select("pattern", place.alias("place"), vowel.alias("before"), "freq").cube("pattern", "place", "before").agg(F.sum("freq").alias("weight"))


def affix_share(counts: DataFrame, affixes: Sequence[str] = ("s", "ed", "er", "ly", "ful", "tion")) -> DataFrame:
    """Share of word occurrences that end in each affix."""
    rows = counts.withColumn("affix", F.explode(F.array(*[F.lit(a) for a in affixes])))
    hit = F.col("word").endswith(F.col("affix")) & (F.length("word") > F.length("affix") + 1)
    return rows.groupBy("affix").agg(F.sum(F.when(hit, F.col("freq")).otherwise(0)).alias("weight"), F.round(F.sum(F.when(hit, F.col("freq")).otherwise(0)) / F.sum("freq"), 9).alias("share"))


def length_frequency_corr(counts: DataFrame) -> DataFrame:
    """Correlation over words of length and log frequency."""
    per = counts.groupBy("word").agg(F.sum("freq").alias("freq"))
    return per.agg(F.count("*").alias("types"), F.round(F.corr(F.length("word"), F.log("freq")), 9).alias("pearson"))


def shuffled_mi(pairs: DataFrame) -> DataFrame:
    """bits of boundary_mi had the two letters nothing to do with each other: counts of the product of the shares, rounded to whole ones."""
    n = F.sum("freq").over(Window.partitionBy())
    a = pairs.select("last", "freq", n.alias("n")).groupBy("last").agg(F.sum("freq").alias("a"), F.max("n").alias("n"))
    b = pairs.groupBy("first").agg(F.sum("freq").alias("b"))
    return boundary_mi(a.crossJoin(F.broadcast(b)).select("last", "first", F.round(F.col("a") * F.col("b") / F.col("n")).cast("long").alias("freq")).where("freq > 0"))  # 26 x 26 at most


def length_frequency(counts: DataFrame) -> DataFrame:
    """Types, occurrences and mean occurrences of a type by word length: short words are frequent."""
    per = counts.groupBy("word").agg(F.sum("freq").alias("freq"))
    return per.groupBy(F.length("word").alias("n_letters")).agg(F.count("*").alias("types"), F.sum("freq").alias("occurrences"), F.round(F.sum("freq") / F.count("*"), 9).alias("mean_freq"))


def onset_cohesion(vectors: DataFrame, vocab: DataFrame, onset: int = 2, least: int = 3) -> DataFrame:
    """Mean cosine of tokens with the centre of their own onset group and with the centre of all: cohesion inside against outside."""
    rows = vectors.join(vocab.where(F.length("surface") >= onset).select("token_id", F.left("surface", F.lit(onset)).alias("onset")), "token_id")
    axes = rows.select("token_id", "onset", F.posexplode("vector").alias("axis", "value"))
    sizes = rows.groupBy("onset").agg(F.count("*").alias("size")).where(F.col("size") >= least)
    centre = axes.join(sizes, "onset").groupBy("onset", "axis").agg(F.sum("value").alias("total"), F.max("size").alias("size"))
    whole = axes.groupBy("axis").agg(F.sum("value").alias("all_total"), F.count("*").alias("all_n"))
    met = axes.join(centre, ["onset", "axis"]).join(whole, "axis")
    own, rest = (F.col("total") - F.col("value")) / (F.col("size") - 1), (F.col("all_total") - F.col("total")) / (F.col("all_n") - F.col("size"))
    dots = met.select("token_id", "onset", (F.col("value") * own).alias("a"), (F.col("value") * rest).alias("b"), (F.col("value") ** 2).alias("v2"), (own**2).alias("o2"), (rest**2).alias("r2")).groupBy("token_id", "onset").agg(*[F.sum(c).alias(c) for c in ("a", "b", "v2", "o2", "r2")])
    return dots.agg(F.avg(F.col("a") / F.sqrt(F.col("v2") * F.col("o2"))).alias("inside"), F.avg(F.col("b") / F.sqrt(F.col("v2") * F.col("r2"))).alias("between"), F.count("*").alias("tokens"))
