"""Examples for the letter probe: labels, length-matched and plain balanced samples, splits, groups, folds."""

from __future__ import annotations

from collections.abc import Sequence

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import LETTERS, order_key
from .vocab import with_mask


def label(vocab: DataFrame, letters: str = LETTERS, case_sensitive: bool = False) -> DataFrame:
    """A row for each token and letter: letter, token_id, surface, has_space, n_letters, y."""
    numbers = F.array(*[F.struct(F.lit(c).alias("letter"), F.lit(LETTERS.index(c)).alias("bit")) for c in letters])
    rows = with_mask(vocab, case_sensitive).withColumn("l", F.explode(numbers))
    return rows.select("l.letter", "token_id", "surface", "has_space", "n_letters", F.expr("int(shiftright(letter_mask, l.bit) & 1)").alias("y"))


def label_substrings(vocab: DataFrame, patterns: Sequence[tuple[str, str]]) -> DataFrame:
    """pattern, place (any, start, end), token_id, y for each token and (pattern, place)."""
    table = F.array(*[F.struct(F.lit(p).alias("pattern"), F.lit(w).alias("place")) for p, w in patterns])
    rows = vocab.withColumn("p", F.explode(table))
    p, s = F.col("p.pattern"), F.col("surface")
    y = F.when(F.col("p.place") == "start", s.startswith(p)).when(F.col("p.place") == "end", s.endswith(p)).otherwise(s.contains(p))
    return rows.select("p.pattern", "p.place", "token_id", y.cast("int").alias("y"))


def strata(labels: DataFrame, by: Sequence[str]) -> DataFrame:
    """Rows of either kind and the number k to take of each, by letter and stratum."""
    return labels.groupBy("letter", *by).agg(F.sum("y").alias("n_pos"), F.sum(1 - F.col("y")).alias("n_neg")).withColumn("k", F.least("n_pos", "n_neg"))


def balanced(labels: DataFrame, seed: int, by: Sequence[str]) -> DataFrame:
    """As many positives as negatives in every stratum, drawn without replacement; pair_no numbers them in a stratum."""
    rank = Window.partitionBy("letter", *by, "y").orderBy(order_key(seed, F.col("letter"), F.col("token_id")), "token_id")
    k = strata(labels, by).select("letter", *by, "k")
    return labels.withColumn("pair_no", F.row_number().over(rank)).join(k, ["letter", *by]).where("pair_no <= k").drop("k")


def sample_matched(labels: DataFrame, seed: int = 42, by: Sequence[str] = ("n_letters",)) -> DataFrame:
    """Balanced within every letter and token length, so that length says nothing about y."""
    return balanced(labels, seed, by)


def sample_unmatched(labels: DataFrame, seed: int = 42) -> DataFrame:
    """Balanced for each letter, lengths as they come."""
    return balanced(labels, seed, ())


def split_pairs(sample: DataFrame, test_share: float = 0.2, seed: int = 42, by: Sequence[str] = ("n_letters",)) -> DataFrame:
    """is_test: the k-th positive and the k-th negative of a stratum go to the same side."""
    pair = F.concat_ws("/", F.col("letter"), *[F.col(b).cast("string") for b in by], F.col("pair_no").cast("string"))
    key = F.conv(F.substring(order_key(seed, pair), 1, 8), 16, 10).cast("long")
    return sample.withColumn("is_test", (key % 1000 < int(round(test_share * 1000))).cast("int"))


def position_groups(labels: DataFrame, positions: Sequence[int] = (1, 2, 3), occurrence: str = "first", match_space: bool = True) -> DataFrame:
    """Rows of six groups: positives by space before and place of the letter, with the negatives they are set against."""
    place = F.instr(F.lower("surface"), F.col("letter")) if occurrence == "first" else None
    targets = F.array(*[F.struct(F.lit(g).alias("g"), F.lit(p).alias("p")) for g in (True, False) for p in positions])
    rows = labels.withColumn("t", F.explode(targets))
    hit = (place == F.col("t.p")) if place is not None else (F.substring(F.lower("surface"), F.col("t.p"), F.lit(1)) == F.col("letter"))
    positive = (F.col("y") == 1) & hit & (F.col("has_space") == F.col("t.g"))
    negative = (F.col("y") == 0) & ((F.col("has_space") == F.col("t.g")) if match_space else F.lit(True))
    return rows.where(positive | negative).select("letter", "token_id", "surface", "has_space", "n_letters", "y", F.col("t.g").alias("group_space"), F.col("t.p").alias("group_pos"))


def context(labels: DataFrame, side: str = "prev") -> DataFrame:
    """grp: the character before or behind the letter's first occurrence; ^ and $ at the edges; null without the letter."""
    at = F.instr(F.lower("surface"), F.col("letter"))
    near = at - 1 if side == "prev" else at + 1
    edge = F.lit("^") if side == "prev" else F.lit("$")
    found = F.when((near < 1) | (near > F.length("surface")), edge).otherwise(F.substring(F.lower("surface"), near, F.lit(1)))
    return labels.withColumn("grp", F.when(F.col("y") == 1, found))


def group_folds(labels: DataFrame, k: int = 5, side: str = "prev", method: str = "serpentine") -> DataFrame:
    """letter, grp, n, fold: groups are never cut, folds about equal. ``greedy``: the next largest to the lightest fold."""
    sizes = context(labels, side).where("y = 1").groupBy("letter", "grp").agg(F.count("*").alias("n"))
    if method == "serpentine":
        at = F.row_number().over(Window.partitionBy("letter").orderBy(F.desc("n"), "grp")) - 1
        lap, place = F.floor(at / k), at % k
        return sizes.withColumn("fold", F.when(lap % 2 == 0, place).otherwise(k - 1 - place).cast("int"))

    def greedy(key, table):
        rows = sorted(zip(table.column("n").to_pylist(), table.column("grp").to_pylist()), key=lambda r: (-r[0], r[1]))
        load, fold = [0] * k, []
        for n, _ in rows:
            f = min(range(k), key=lambda i: (load[i], i))
            load[f] += n
            fold.append(f)
        return pa.table({"letter": pa.array([key[0].as_py()] * len(rows), pa.string()), "grp": pa.array([r[1] for r in rows], pa.string()), "n": pa.array([r[0] for r in rows], pa.int64()), "fold": pa.array(fold, pa.int32())})

    return sizes.groupBy("letter").applyInArrow(greedy, "letter string, grp string, n long, fold int")


def grouped_sample(labels: DataFrame, k: int = 5, side: str = "prev", seed: int = 42, method: str = "serpentine") -> DataFrame:
    """Positives in the fold of their group; each fold gets length-matched negatives of its own."""
    folds = group_folds(labels, k, side, method).select("letter", "grp", "fold")
    positive = context(labels, side).where("y = 1").join(folds, ["letter", "grp"]).drop("grp")
    negative = labels.where("y = 0").withColumn("fold", (F.conv(F.substring(order_key(seed + 1, F.col("letter"), F.col("token_id")), 1, 8), 16, 10).cast("long") % k).cast("int"))
    return balanced(positive.unionByName(negative), seed, ("fold", "n_letters"))


def random_folds(sample: DataFrame, k: int = 5, seed: int = 42, by: Sequence[str] = ("n_letters",)) -> DataFrame:
    """Pairs dealt to k folds at random: the control of group_folds."""
    pair = F.concat_ws("/", F.col("letter"), *[F.col(b).cast("string") for b in by], F.col("pair_no").cast("string"))
    key = F.conv(F.substring(order_key(seed, pair), 1, 8), 16, 10).cast("long")
    return sample.withColumn("fold", (key % k).cast("int"))


def composition_tasks(vocab: DataFrame, seed: int = 42) -> DataFrame:
    """Letter-level tasks on tokens of two letters or more: contains, insert, delete, swap, with their answers."""
    s, n = F.col("surface"), F.length("surface")
    draw = lambda what, m: (F.conv(F.substring(order_key(seed, F.lit(what), s), 1, 8), 16, 10).cast("long") % m).cast("int")
    letter = F.substring(F.lit(LETTERS), draw("letter", F.lit(26)) + 1, F.lit(1))
    at = draw("at", n) + 1
    i = draw("swap", n - 1) + 1
    cut = lambda a, m: F.substring(s, a, m)
    answers = F.array(
        F.struct(F.lit("contains").alias("task"), letter.alias("argument"), (F.instr(F.lower(s), letter) > 0).cast("int").cast("string").alias("answer")),
        F.struct(F.lit("insert").alias("task"), F.concat(letter, F.lit("@"), at.cast("string")).alias("argument"), F.concat(cut(F.lit(1), at - 1), letter, cut(at, n)).alias("answer")),
        F.struct(F.lit("delete").alias("task"), at.cast("string").alias("argument"), F.concat(cut(F.lit(1), at - 1), cut(at + 1, n)).alias("answer")),
        F.struct(F.lit("swap").alias("task"), i.cast("string").alias("argument"), F.concat(cut(F.lit(1), i - 1), cut(i + 1, F.lit(1)), cut(i, F.lit(1)), cut(i + 2, n)).alias("answer")),
    )
    return vocab.where(n >= 2).select("token_id", "surface", F.explode(answers).alias("t")).select("token_id", "surface", "t.task", "t.argument", "t.answer")
