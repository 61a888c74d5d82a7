"""Measures: pooled accuracy and its parts, vocabulary shares, contributions, what length alone gives away."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import length_class


def accuracy(pred: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """n, correct and accuracy over all rows of a group: pooled, so large letters weigh more. Wilson's 95 % interval beside it."""
    z = 1.959963984540054
    out = pred.groupBy(*by).agg(F.count("*").alias("n"), F.sum("correct").alias("correct"))
    p, n = F.col("correct") / F.col("n"), F.col("n")
    centre, half = (p + z * z / (2 * n)) / (1 + z * z / n), z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n)
    return out.withColumn("accuracy", F.round(100 * p, 6)).withColumn("low", F.round(100 * (centre - half), 6)).withColumn("high", F.round(100 * (centre + half), 6))


def accuracy_by_letter_and_all(pred: DataFrame) -> DataFrame:
    """One pass for each letter and for all of them together (letter '*')."""
    return pred.rollup("letter").agg(F.count("*").alias("n"), F.sum("correct").alias("correct")).select(F.coalesce("letter", F.lit("*")).alias("letter"), "n", "correct", F.round(100 * F.col("correct") / F.col("n"), 6).alias("accuracy"))


def macro_accuracy(pred: DataFrame) -> DataFrame:
    return accuracy(pred, ["letter"]).agg(F.round(F.avg("accuracy"), 6).alias("macro_accuracy"))


def accuracy_by_length(pred: DataFrame) -> DataFrame:
    return pred.groupBy(length_class(F.col("n_letters")).alias("length_class")).agg(F.count("*").alias("n"), F.sum("correct").alias("correct")).withColumn("accuracy", F.round(100 * F.col("correct") / F.col("n"), 6))


def vocab_share(vocab: DataFrame) -> DataFrame:
    """Entries of each length class and their share of the vocabulary in percent."""
    counted = vocab.groupBy(length_class(F.col("n_letters")).alias("length_class")).agg(F.count("*").alias("entries"))
    return counted.withColumn("share", F.round(100 * F.col("entries") / F.sum("entries").over(Window.partitionBy()), 6))


def length_only_accuracy(sample: DataFrame) -> DataFrame:
    """Best accuracy of a rule 'positive from this length on' (or below it), by letter: exactly 50 where lengths are matched."""
    per = sample.groupBy("letter", "n_letters").agg(F.sum("y").alias("p"), F.sum(1 - F.col("y")).alias("q"))
    below = Window.partitionBy("letter").orderBy("n_letters").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("letter")
    zero = lambda c: F.coalesce(F.sum(c).over(below), F.lit(0))
    right = per.select("letter", (F.sum("p").over(whole) - zero("p") + zero("q")).alias("up"), (F.sum("p").over(whole) + F.sum("q").over(whole)).alias("n"))
    best = right.groupBy("letter").agg(F.max(F.greatest("up", F.col("n") - F.col("up"), F.col("n") / 2)).alias("right"), F.max("n").alias("n"))
    return best.select("letter", "n", F.round(100 * F.col("right") / F.col("n"), 6).alias("length_accuracy"))


def contribution(results: DataFrame, pairs: DataFrame) -> DataFrame:
    """Accuracy of a control minus that of its treatment, in points, with the 95 % half-width of the difference.

    results: experiment, tokenizer, corpus, restriction, n, accuracy; pairs: factor, varies, control, treatment (names of
    experiments). The two sides must agree on tokenizer, corpus and restriction but for the one named in ``varies``: else
    the row is refused, and has no points.
    """
    side = lambda tag: results.select(*[F.col(c).alias(f"{tag}_{c}") for c in ("experiment", "tokenizer", "corpus", "restriction", "n", "accuracy")])
    met = pairs.join(side("c"), F.col("control") == F.col("c_experiment")).join(side("t"), F.col("treatment") == F.col("t_experiment"))
    fair = F.lit(True)
    for c in ("tokenizer", "corpus", "restriction"):
        fair = fair & ((F.col("varies") == c) | (F.col(f"c_{c}") == F.col(f"t_{c}")))
    spread = lambda t: F.col(f"{t}_accuracy") * (100 - F.col(f"{t}_accuracy")) / F.col(f"{t}_n")
    points, half = F.col("c_accuracy") - F.col("t_accuracy"), 1.96 * F.sqrt(spread("c") + spread("t"))
    return met.select("factor", "control", "treatment", (~fair).cast("int").alias("refused"), F.when(fair, F.round(points, 6)).alias("points"), F.when(fair, F.round(half, 6)).alias("half_width"))


def token_budget(spark: SparkSession, counted: DataFrame | None = None, batch: int = 32, accumulation: int = 40, length: int = 1024, steps: int = 10_000, sample: int = 10_000_000_000) -> DataFrame:
    """Sequences and tokens of a step, tokens of a run, and how many of these repeat the sample: ``sample`` tokens, or as many
    as ``counted`` (one row, column sample) says."""
    one = spark.range(1).withColumn("sample", F.lit(sample)) if counted is None else counted
    per_step = batch * accumulation * length
    fixed = [F.lit(v).cast("long").alias(k) for k, v in (("sequences", batch * accumulation), ("tokens_per_step", per_step), ("tokens", per_step * steps))]
    return one.select(*fixed, (F.lit(per_step * steps) - F.col("sample")).cast("long").alias("repeated"))


def learning_rate(step: F.Column, peak: float = 6e-4, warm_up: int = 2000, steps: int = 10_000, floor: float = 0.0) -> F.Column:
    """Linear warm-up, then a half cosine down to the floor."""
    part = (step - warm_up) / F.lit(float(steps - warm_up))
    return F.when(step < warm_up, peak * step / F.lit(float(warm_up))).otherwise(floor + (peak - floor) * 0.5 * (1 + F.cos(F.lit(3.141592653589793) * F.least(part, F.lit(1.0)))))
