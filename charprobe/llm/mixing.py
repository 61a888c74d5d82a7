"""Operator 6: mixing to target weights by iterative proportional fitting.

Token counts are summed into cells of (source, language, topic) and raked: in turn, the weights of each marginal's
categories are scaled to their targets. A cell's documents are then kept with one probability, in proportion to its raked weight over its share
of tokens, and at most 1. Without ``keep`` (the registered query and the pipeline) the targets are reached in expectation: cells
of probability 1 are held and the others raked anew, for the greatest share of tokens at which that works without repeating a
document. With ``keep`` the scale is calibrated so that this share of all tokens is expected to stay; probabilities cut at 1 are
then not made up for, and categories that the targets raise fall short of them. A document's draw is a hash of the seed and its id, so a rerun keeps the same
ones and repeated rows stay or go together.

The only table on the driver is the cells', which grows with the categories and not with the rows; beyond MOST_CELLS
the operator refuses. Null categories are a category of their own, '(null)'. A category without a target keeps the share that
it has. Documents without tokens get the probability of their cell; a cell without tokens gets 1.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"
MOST_CELLS = 2_000_000
#: Most passes over the marginals; they end where every goal is met to TOLERANCE (relative).
ROUNDS = 1000
TOLERANCE, BOUNDED_TOLERANCE = 1e-9, 1e-5
NULL = "(null)"
#: Columns that mixing adds.
OWN = ("mix_tokens", "mix_weight", "mix_prob", "mix_kept")


def word_count(text: F.Column) -> F.Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def form_topic(text: F.Column) -> F.Column:
    """A stand-in topic from the text's form, as the tables have none: table, shout, symbol, long or prose."""
    text = F.coalesce(text, F.lit(""))
    return (
        F.when(text.contains(" | "), "table").when(text.contains("!! "), "shout").when(text.contains("### ") | text.contains("%%% "), "symbol")
        .when(F.length(text) >= 6000, "long").otherwise("prose")
    )


#: A tempered target is at most so many times the category's own share: without repeats, what is raised r times leaves 1 / r of the tokens.
MOST_RAISED = 1.25


def tempered(shares: Mapping[str, float], power: float, most: float = MOST_RAISED) -> dict[str, float]:
    """Shares raised to a power and normalised, none above ``most`` times itself: a power below 1 moves them towards equal ones."""
    held = {k: v for k, v in shares.items() if v > 0}
    total = sum(held.values())
    held = {k: v / total for k, v in held.items()}
    capped: dict[str, float] = {}
    while True:
        rest = {k: v**power for k, v in held.items() if k not in capped}
        scale = (1.0 - sum(capped.values())) / sum(rest.values()) if rest else 0.0
        over = {k: most * held[k] for k, v in rest.items() if v * scale > most * held[k] * (1 + 1e-12)}
        if not over:
            return capped | {k: v * scale for k, v in rest.items()}
        capped |= over


def marginal_goals(cells: Sequence[tuple], tokens: np.ndarray, targets: Sequence[Mapping[str, float]]) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
    """Shares of the cells; for each marginal the category of every cell and the categories' goals, which sum to 1."""
    total = tokens.sum()
    w = tokens / total if total else np.full(len(tokens), 1.0 / max(1, len(tokens)))
    groups = []
    for d, target in enumerate(targets):
        names = sorted({c[d] for c in cells})
        number = {x: i for i, x in enumerate(names)}
        index = np.array([number[c[d]] for c in cells], np.int64)
        now = np.bincount(index, weights=w, minlength=len(names))
        goal = np.array([target.get(x, np.nan) for x in names])
        goal = np.where(np.isnan(goal), now, goal)
        goal = np.where(now > 0, goal, 0.0)
        groups.append((index, goal / goal.sum() if goal.sum() else goal))
    return w, groups


def farthest(w: np.ndarray, groups: Sequence[tuple[np.ndarray, np.ndarray]]) -> float:
    """The greatest relative miss of a goal by the weights."""
    misses = [np.abs(np.bincount(index, weights=w, minlength=len(goal)) / np.where(goal > 0, goal, 1) - 1)[goal > 0] for index, goal in groups]
    return max((float(m.max()) for m in misses if len(m)), default=0.0)


def rake(cells: Sequence[tuple], tokens: np.ndarray, targets: Sequence[Mapping[str, float]], rounds: int = ROUNDS) -> np.ndarray:
    """Cell weights, summing to 1: passes over all marginals until each goal is met to TOLERANCE, ``rounds`` at most."""
    w, groups = marginal_goals(cells, tokens, targets)
    for _ in range(rounds):
        for index, goal in groups:
            now = np.bincount(index, weights=w, minlength=len(goal))
            w = w * np.where(now > 0, goal / np.where(now > 0, now, 1), 0)[index]
        if farthest(w, groups) < TOLERANCE:
            break
    return w


def bounded_rake(start: np.ndarray, share: np.ndarray, groups: Sequence[tuple[np.ndarray, np.ndarray]], keep: float, rounds: int = 300) -> np.ndarray | None:
    """Kept masses of the cells, none above its share, whose marginals are ``keep`` times the goals; None where no such masses are found.

    Each category's factor is the one under which its cells, cut at their shares, add up to its goal.
    """
    y = keep * start
    for _ in range(rounds):
        for index, goal in groups:
            for _ in range(8):  # the cut cells give what they have, the others share the rest
                cut = y >= share
                fixed = np.bincount(index[cut], weights=share[cut], minlength=len(goal))
                free = np.bincount(index[~cut], weights=y[~cut], minlength=len(goal))
                factor = np.where(free > 0, np.maximum(keep * goal - fixed, 0.0) / np.where(free > 0, free, 1), 1.0)
                over = (np.bincount(index, weights=np.minimum(y, share), minlength=len(goal)) > keep * goal * (1 + 1e-15)) & (fixed > 0)
                whole = np.bincount(index, weights=y, minlength=len(goal))
                factor = np.where(over, keep * goal / np.where(whole > 0, whole, 1), factor)
                y = y * factor[index]
                if np.abs(factor[goal > 0] - 1).max(initial=0.0) < 1e-13:
                    break
        x = np.minimum(y, share)
        if farthest(x / keep, groups) < BOUNDED_TOLERANCE:
            return x
    return None


def largest_mix(w: np.ndarray, share: np.ndarray, groups: Sequence[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Probabilities of the cells, at most 1, that reach the goals with the greatest share of tokens found by halving.

    The raked weights scaled until the first probability is 1 always reach them; beyond that, cells whose
    probability is 1 are held and the others make up for them.
    """
    held = share > 0
    ratio = np.where(held, w / np.where(held, share, 1), 0.0)
    if ratio.max(initial=0.0) <= 0:
        return np.ones(len(w))
    low, best = 1.0 / ratio.max(), w / ratio.max()
    room = [(np.bincount(index, weights=share, minlength=len(goal))[goal > 0] / goal[goal > 0]).min(initial=1.0) for index, goal in groups]
    high = min(1.0, *room)
    for _ in range(12):
        if high - low < 1e-3:
            break
        mid = (low + high) / 2
        x = bounded_rake(w, share, groups, mid)
        if x is None:
            high = mid
        else:
            low, best = mid, x
    return np.where(held, np.minimum(1.0, best / np.where(held, share, 1)), 1.0)


def calibrated(ratio: np.ndarray, share: np.ndarray, keep: float | None) -> np.ndarray:
    """Probabilities in proportion to the ratios, cut at 1, under which the share ``keep`` of the tokens is expected to stay."""
    top = ratio.max() if len(ratio) else 0.0
    if top <= 0:
        return np.ones(len(ratio))
    if keep is None:
        return ratio / top
    low, high = 0.0, 1.0
    reach = lambda x: float((np.minimum(1.0, x * ratio) * share).sum())
    while reach(high) < keep - 1e-12 and high < 1e12:
        high *= 2
    for _ in range(100):
        mid = (low + high) / 2
        low, high = (mid, high) if reach(mid) < keep else (low, mid)
    return np.minimum(1.0, high * ratio)


def mix(docs: DataFrame, columns: Sequence[str], tokens: F.Column, targets: Mapping[str, Mapping[str, float]] | None = None, power: float = 0.9, keep: float | None = 0.9, seed: int = 42, id_col: str = "doc_id", rounds: int = ROUNDS) -> DataFrame:
    """docs with mix_tokens, mix_weight (raked weight over share), mix_prob and mix_kept.

    targets: shares of each column's categories; a column without them gets its own shares tempered by ``power``. Columns
    of docs that have these four names are replaced.
    """
    docs = docs.drop(*[c for c in OWN if c not in columns and c != id_col])
    keys = [F.coalesce(F.col(c).cast("string"), F.lit(NULL)).alias(f"__mix_{k}") for k, c in enumerate(columns)]
    names = [f"__mix_{k}" for k in range(len(columns))]
    cells = docs.select(*keys, tokens.alias("mix_tokens")).groupBy(*names).agg(F.sum("mix_tokens").alias("tokens"))
    rows = cells.limit(MOST_CELLS + 1).collect()
    if len(rows) > MOST_CELLS:
        raise ValueError(f"more than {MOST_CELLS} cells")
    rows = sorted(rows, key=lambda r: tuple(r[n] for n in names))
    own, amount = [tuple(r[n] for n in names) for r in rows], np.array([float(r["tokens"]) for r in rows])
    goals = []
    for d, c in enumerate(columns):
        given = (targets or {}).get(c)
        if given is None:
            seen: dict[str, float] = {}
            for key, a in zip(own, amount):
                seen[key[d]] = seen.get(key[d], 0.0) + a
            total = sum(seen.values())
            given = tempered({k: v / total for k, v in seen.items()}, power) if total else {}
        goals.append(given)
    w = rake(own, amount, goals, rounds)
    share, groups = marginal_goals(own, amount, goals)
    ratio = np.where(amount > 0, w / np.where(amount > 0, share, 1), 0.0)
    prob = np.where(amount > 0, largest_mix(w, share, groups) if keep is None else calibrated(ratio, share, keep), 1.0)
    spark = docs.sparkSession
    fields = ", ".join(f"__cell_{k} string" for k in range(len(columns)))
    table = spark.createDataFrame([(*c, float(r), float(p)) for c, r, p in zip(own, ratio, prob)], f"{fields}, mix_weight double, mix_prob double")
    keyed = docs.select("*", *keys, tokens.alias("mix_tokens"))
    met = keyed.join(F.broadcast(table) if len(own) <= 100_000 else table, [F.col(f"__mix_{k}") == F.col(f"__cell_{k}") for k in range(len(columns))], "left")
    draw = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(F.col(id_col).cast("string"), F.lit(""))).cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    return met.withColumn("mix_kept", draw < F.col("mix_prob")).drop(*names, *[f"__cell_{k}" for k in range(len(columns))])


def mix_documents(docs: DataFrame, power: float = 0.9, keep: float | None = 0.9, seed: int = 42) -> DataFrame:
    """The documents table mixed over source, language and form topic: one row per document with its decision."""
    rows = docs.select(F.col("doc_id"), F.col("source"), F.col("lang"), form_topic(F.col("text")).alias("topic"), word_count(F.col("text")).alias("words"))
    out = mix(rows, ["source", "lang", "topic"], F.col("words"), power=power, keep=keep, seed=seed)
    return out.select("doc_id", "source", "lang", "topic", F.col("mix_tokens").alias("n_tokens"), F.round("mix_weight", 9).alias("weight"), F.round("mix_prob", 9).alias("prob"), F.col("mix_kept").alias("kept"))
