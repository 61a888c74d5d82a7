"""Column functions: stateless draws, letters of a token, length classes."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: Greatest length with a class of its own; longer tokens share the class 7 (fixed values: at most 3, 4, 5, 6, 7 or more).
SHORTEST_CLASS, LONGEST_CLASS = 3, 7


def order_key(seed: int, *keys: Column) -> Column:
    """A hash of the seed and the keys: a random but repeatable order, whatever the partitioning."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[k.cast("string") for k in keys]).cast("binary"))


def draw(seed: int, *keys: Column) -> Column:
    """The order key's first 32 bits as a long: a repeatable uniform draw without state."""
    return F.conv(F.substring(order_key(seed, *keys), 1, 8), 16, 10).cast("long")


def fast_draw(seed: int, *keys: Column) -> Column:
    """As draw, by xxhash64: no SQL twin, several times cheaper."""
    return F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(1 << 32))


def letter_mask(surface: Column, case_sensitive: bool = False) -> Column:
    """One bit for each of the 26 letters that the token has; computed once a token, tested 26 times."""
    chars = F.split(surface if case_sensitive else F.lower(surface), "")
    bits = F.transform(F.filter(chars, lambda c: (c >= "a") & (c <= "z")), lambda c: F.ascii(c) - 97)
    return F.aggregate(F.array_distinct(bits), F.lit(0), lambda m, b: m + F.pow(F.lit(2), b).cast("int"))


def length_class(n_letters: Column) -> Column:
    return F.least(F.greatest(n_letters, F.lit(SHORTEST_CLASS)), F.lit(LONGEST_CLASS)).cast("int")


def fixed_width(word: Column, width: int = 3) -> Column:
    return F.regexp_extract_all(word, F.lit(f".{{1,{width}}}"), F.lit(0))


def register_sql(spark: SparkSession) -> list[str]:
    """Temporary SQL functions with SQL bodies, which the analyzer inlines."""
    bodies = {
        "length_class(n INT) RETURNS INT": f"least(greatest(n, {SHORTEST_CLASS}), {LONGEST_CLASS})",
        "fixed_width(word STRING) RETURNS ARRAY<STRING>": "regexp_extract_all(word, '.{1,3}', 0)",
        "has_letter(word STRING, letter STRING) RETURNS INT": "int(instr(lower(word), letter) > 0)",
        "draw32(x STRING) RETURNS BIGINT": "bigint(conv(substring(md5(x), 1, 8), 16, 10))",
    }
    for head, body in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [h.split("(")[0] for h in bodies]
