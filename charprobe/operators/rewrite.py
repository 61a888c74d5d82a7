"""Corpus interventions: scrambled letters, substituted units, resampled tokens, lemmas and stems."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import LETTERS, draw, order_key
from ..sources import checkpointed, in_runs
from .vocab import bounded


def scramble_letters(text: F.Column, seed: int, *keys: F.Column) -> F.Column:
    """Every ASCII letter replaced by a random one of its case, drawn for (seed, keys, position); all else as it is."""
    base = F.concat_ws("|", F.lit(str(seed)), *[k.cast("string") for k in keys])

    def one(c: F.Column, i: F.Column) -> F.Column:
        u = (F.conv(F.substring(F.md5(F.concat_ws("|", base, i.cast("string")).cast("binary")), 1, 8), 16, 10).cast("long") % 26).cast("int")
        lower = F.substring(F.lit(LETTERS), u + 1, F.lit(1))
        return F.when((c >= "a") & (c <= "z"), lower).when((c >= "A") & (c <= "Z"), F.upper(lower)).otherwise(c)

    return F.array_join(F.transform(F.split(text, ""), one), "")


def scrambled_documents(docs: DataFrame, seed: int = 42) -> DataFrame:
    """doc_id, text with every ASCII letter replaced by a random one of its case: as scramble_letters, but all letters of a
    batch at once, drawn by a 64-bit mixer of (seed, document, byte) instead of a digest for each letter."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_runs(source, 1 << 21):
            out = []
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                data = np.frombuffer((text or "").encode(), np.uint8).copy()
                low = data | 0x20
                at = np.flatnonzero((low >= 97) & (low <= 122) & (data < 128))
                x = at.astype(np.uint64) + np.uint64(((seed << 40) ^ ((i or 0) * 0x9E3779B97F4A7C15)) & (1 << 64) - 1)
                x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
                x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
                data[at] = (((x ^ (x >> np.uint64(31))) >> np.uint64(11)) % np.uint64(26)).astype(np.uint8) + 97 - (low[at] - data[at])
                out.append(data.tobytes().decode())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], names=["doc_id", "text"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, text string")


def substitute_subwords(rows: DataFrame, table: DataFrame, coded: DataFrame | None = None) -> DataFrame:
    """doc_id, pos, word, has_space: each piece of a word (rows with ``pieces``) by its substitute, the same wherever it stands,
    and the word put together again. A piece with the space before it is another entry than one without.

    With ``coded`` (each distinct word once, with its pieces) the rows need none.
    """
    parts = (rows.select("word", "has_space", "pieces").distinct() if coded is None else coded).select("word", "has_space", F.posexplode("pieces").alias("k", "piece"))
    met = parts.join(table, parts["piece"] == table["src"]).groupBy("word", "has_space").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", "dst"))), lambda x: x["dst"]), "").alias("new"))
    return rows.join(met, ["word", "has_space"]).select("doc_id", "pos", F.ltrim("new").alias("word"), "has_space")


def subword_substitution(rows: DataFrame, seed: int = 42) -> DataFrame:
    """src, dst for all pieces of the rows: inside each class (space before, letters) a fixed random string for each, no two alike."""
    pieces = checkpointed(rows.select(F.explode("pieces").alias("piece")).distinct())  # few, read many times
    out = None
    for lead, kind in (("", ~F.col("piece").startswith(" ")), (" ", F.col("piece").startswith(" "))):
        units = pieces.where(kind).select(F.ltrim("piece").alias("surface"))
        table = substitution_all(units.where("length(surface) > 0"), seed + len(lead)).select(F.concat(F.lit(lead), "src").alias("src"), F.concat(F.lit(lead), "dst").alias("dst"))
        alone = units.where("length(surface) = 0").select(F.lit(lead).alias("src"), F.lit(lead).alias("dst"))
        table = table.unionByName(alone)
        out = table if out is None else out.unionByName(table)
    return out


def substitution_short(vocab: DataFrame, seed: int = 42) -> DataFrame:
    """src, dst, n_letters for tokens of 1 to 2 letters: the k-th in one random order maps to the k-th in another, inside the full class."""
    spark = vocab.sparkSession
    one = spark.createDataFrame([(c,) for c in LETTERS], "c string").coalesce(1)
    full = one.select(F.col("c").alias("s")).unionByName(one.crossJoin(one.select(F.col("c").alias("d"))).select(F.concat("c", "d").alias("s")))
    n = F.length("s")
    by = lambda tag: Window.partitionBy(n).orderBy(order_key(seed, F.lit(tag), F.col("s")), "s")
    a = full.select(F.col("s").alias("src"), n.alias("n_letters"), F.row_number().over(by("src")).alias("k"))
    b = full.select(F.col("s").alias("dst"), n.alias("n2"), F.row_number().over(by("dst")).alias("k2"))
    table = a.join(b, (F.col("n_letters") == F.col("n2")) & (F.col("k") == F.col("k2"))).select("src", "dst", "n_letters")
    return vocab.select(F.col("surface").alias("src")).distinct().join(table, "src").select("src", "dst", "n_letters")


def substitution_all(units: DataFrame, seed: int = 42, short: int = 3) -> DataFrame:
    """src, dst for units of every length: a permutation of the full class up to ``short`` letters, random strings beyond.

    Units of up to ``short`` characters that are not all of a to z are no part of a full class; they change places among themselves.
    """
    spark = units.sparkSession
    names = units.select(F.col("surface").alias("src")).distinct()
    level = one = spark.createDataFrame([(c,) for c in LETTERS], "c string").coalesce(1)
    full = one.select(F.col("c").alias("s"))
    for _ in range(short - 1):
        level = level.crossJoin(one.select(F.col("c").alias("d"))).select(F.concat("c", "d").alias("c"))
        full = full.unionByName(level.select(F.col("c").alias("s")))
    plain = F.col("src").rlike("^[a-z]+$")
    odd = names.where((F.length("src") <= short) & ~plain).select(F.col("src").alias("s"))
    out = substitution_dict(names.where(F.length("src") > short).select(F.col("src").alias("surface")), seed)
    for units_of, wanted in ((full, names.where((F.length("src") <= short) & plain)), (odd, None)):
        by = lambda tag: Window.partitionBy(F.length("s")).orderBy(order_key(seed, F.lit(tag), F.col("s")), "s")
        a = units_of.select(F.col("s").alias("src"), F.length("s").alias("n"), F.row_number().over(by("src")).alias("k"))
        b = units_of.select(F.col("s").alias("dst"), F.length("s").alias("n2"), F.row_number().over(by("dst")).alias("k2"))
        table = a.join(b, (F.col("n") == F.col("n2")) & (F.col("k") == F.col("k2"))).select("src", "dst")
        out = out.unionByName(table if wanted is None else table.join(wanted, "src"))
    return out


def substitution_dict(units: DataFrame, seed: int = 42, keep_length: bool = True, rounds: int = 12) -> DataFrame:
    """src, dst: a random string of letters for each unit, no two alike. Collisions are drawn again; what a short class
    leaves over is dealt the strings not taken, in hash order."""
    names = units.select(F.col("surface").alias("src")).distinct().withColumn("n", F.length("src") if keep_length else F.lit(8))
    left, out = names, None
    for attempt in range(rounds):
        letters = F.transform(F.sequence(F.lit(1), F.col("n")), lambda i: F.substring(F.lit(LETTERS), (F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(f"{seed}|{attempt}"), F.col("src"), i.cast("string")).cast("binary")), 1, 8), 16, 10).cast("long") % 26).cast("int") + 1, F.lit(1)))
        drawn = left.withColumn("dst", F.array_join(letters, ""))
        if out is not None:
            drawn = drawn.join(out.select("dst").withColumn("taken", F.lit(1)), "dst", "left")
        else:
            drawn = drawn.withColumn("taken", F.lit(None).cast("int"))
        first = F.row_number().over(Window.partitionBy("dst").orderBy("src"))
        drawn = drawn.withColumn("ok", F.col("taken").isNull() & (first == 1))
        drawn = checkpointed(drawn.select("src", "n", "dst", "ok"))  # written once: later rounds and uses read it
        good, left = drawn.where("ok").select("src", "n", "dst"), drawn.where("not ok").select("src", "n")
        out = good if out is None else out.unionByName(good)
        if attempt >= 2 and left.limit(1).count() == 0:
            return out.select("src", "dst")
    raise ValueError("a length class is too full to draw from; use substitution_short for its units")


def substitute_words(words: DataFrame, table: DataFrame) -> DataFrame:
    """Each word by its substitute, the same at every occurrence."""
    return words.join(table, F.col("word") == F.col("src")).select("doc_id", "pos", F.col("dst").alias("word"), "has_space")


def resample_tokens(tokens: DataFrame, vocab: DataFrame, seed: int = 42) -> DataFrame:
    """Each token occurrence by a random vocabulary entry of its class (space before, length)."""
    keys = ["has_space", "n_letters"]
    place = Window.partitionBy(*keys).orderBy("surface")
    entries = vocab.select(*keys, F.col("surface").alias("new_surface"), (F.row_number().over(place) - 1).alias("k"))
    sizes = entries.groupBy(*keys).agg(F.count("*").alias("size"))
    drawn = tokens.join(F.broadcast(sizes), keys).withColumn("k", (draw(seed, F.col("doc_id"), F.col("word_pos"), F.col("sub_pos")) % F.col("size")).cast("int"))
    return drawn.join(bounded(entries), [*keys, "k"]).select("doc_id", "word_pos", "sub_pos", F.col("new_surface").alias("surface"), "has_space", "n_letters")


def reassemble(words: DataFrame) -> DataFrame:
    """Documents again from words in order, a space before those that have one."""
    spelled = F.concat(F.when(F.col("has_space"), " ").otherwise(""), "word")
    rows = F.array_sort(F.collect_list(F.struct("pos", spelled.alias("s"))))
    return words.groupBy("doc_id").agg(F.array_join(F.transform(rows, lambda x: x["s"]), "").alias("text"))


#: Suffix rules of the lemmatizer: (ending, what takes its place), first that yields a known word wins (fixed values).
DETACH = (("ies", "y"), ("sses", "ss"), ("xes", "x"), ("ches", "ch"), ("shes", "sh"), ("s", ""), ("ied", "y"), ("ed", "e"), ("ed", ""), ("iest", "y"), ("est", "e"), ("est", ""), ("ier", "y"), ("er", "e"), ("er", ""))


def lemmatize(counts: DataFrame, lexicon: DataFrame | None = None, exceptions: dict[str, str] | None = None) -> DataFrame:
    """word, lemma of each distinct word: inflection is detached where the base is itself a word of the lexicon (the corpus by default)."""
    words = counts.select("word").distinct()
    known = (lexicon if lexicon is not None else words).select(F.col("word").alias("base")).distinct()
    tries = F.filter(F.array(*[F.when(F.col("word").endswith(end) & (F.length("word") >= len(end) + 2), F.struct(F.lit(k).alias("k"), F.concat(F.expr(f"left(word, length(word) - {len(end)})"), F.lit(put)).alias("base"))) for k, (end, put) in enumerate(DETACH)]), lambda x: x.isNotNull())
    found = words.select("word", F.explode(tries).alias("t")).select("word", "t.k", "t.base").join(known, "base").groupBy("word").agg(F.min_by("base", "k").alias("lemma"))
    out = words.join(found, "word", "left").select("word", F.when(F.length("word") <= 2, F.col("word")).otherwise(F.coalesce("lemma", "word")).alias("lemma"))
    if exceptions:
        table = F.create_map(*[F.lit(x) for kv in exceptions.items() for x in kv])
        out = out.withColumn("lemma", F.coalesce(table[F.col("word")], "lemma"))
    return out


class Stemmer:
    """The published five-step suffix stemmer, from its description in words."""

    STEP2 = (("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble"))
    STEP3 = (("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", ""))
    STEP4 = ("al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize")

    @staticmethod
    def kinds(stem: str) -> str:
        """v or c for each letter; y is a vowel behind a consonant."""
        out = ""
        for ch in stem:
            out += "v" if ch in "aeiou" or ch == "y" and out[-1:] == "c" else "c"
        return out

    @classmethod
    def measure(cls, stem: str) -> int:
        return len(re.findall("v+c+", cls.kinds(stem)))

    @classmethod
    def has_vowel(cls, stem: str) -> bool:
        return "v" in cls.kinds(stem)

    @classmethod
    def double(cls, w: str) -> bool:
        return len(w) > 1 and w[-1] == w[-2] and cls.kinds(w)[-1] == "c"

    @classmethod
    def short_end(cls, w: str) -> bool:
        return cls.kinds(w)[-3:] == "cvc" and w[-1] not in "wxy"

    @classmethod
    def stem(cls, w: str) -> str:
        if len(w) <= 2:
            return w
        w = cls.step1a(w)
        w = cls.step1b(w)
        if w.endswith("y") and cls.has_vowel(w[:-1]):
            w = w[:-1] + "i"
        for rules in (cls.STEP2, cls.STEP3):
            for end, put in sorted(rules, key=lambda r: -len(r[0])):
                if w.endswith(end):
                    if cls.measure(w[: -len(end)]) > 0:
                        w = w[: -len(end)] + put
                    break
        for end in sorted(cls.STEP4, key=len, reverse=True):
            if w.endswith(end):
                base = w[: -len(end)]
                if cls.measure(base) > 1 and (end != "ion" or base[-1:] in ("s", "t")):
                    w = base
                break
        if w.endswith("e"):
            m = cls.measure(w[:-1])
            if m > 1 or m == 1 and not cls.short_end(w[:-1]):
                w = w[:-1]
        if w.endswith("ll") and cls.measure(w) > 1:
            w = w[:-1]
        return w

    @staticmethod
    def step1a(w: str) -> str:
        for end, put in (("sses", "ss"), ("ies", "i"), ("ss", "ss"), ("s", "")):
            if w.endswith(end):
                return w[: -len(end)] + put
        return w

    @classmethod
    def step1b(cls, w: str) -> str:
        if w.endswith("eed"):
            return w[:-1] if cls.measure(w[:-3]) > 0 else w
        for end in ("ed", "ing"):
            base = w[: -len(end)]
            if w.endswith(end) and cls.has_vowel(base):
                if base.endswith(("at", "bl", "iz")):
                    return base + "e"
                if cls.double(base) and base[-1] not in "lsz":
                    return base[:-1]
                return base + "e" if cls.measure(base) == 1 and cls.short_end(base) else base
        return w


def stem(counts: DataFrame) -> DataFrame:
    """word, stem of each distinct word."""

    @F.pandas_udf("string")
    def stems(w):
        return w.map(Stemmer.stem)

    return counts.select("word").distinct().withColumn("stem", stems("word"))


def stem_step1a(word: F.Column) -> F.Column:
    """The stemmer's first step as a column: plural endings."""
    cut = lambda n: F.expr(f"left(word, length(word) - {n})")
    short = F.length(word) <= 2
    return F.when(short, word).when(word.endswith("sses"), cut(2)).when(word.endswith("ies"), cut(2)).when(word.endswith("ss"), word).when(word.endswith("s"), cut(1)).otherwise(word)
