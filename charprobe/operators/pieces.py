"""Documents as lists of pieces, one row each: (doc_id, pieces), where a piece begins with a space if the text has white space there.

What is done to words is done once to each distinct word of an Arrow batch, and tokens are numbered where they lie, so
neither needs a row for each word nor a shuffle of the text.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import in_runs
from .merging import Rules
from .rewrite import Stemmer
from .training import ONE_TASK, trained

LETTER, WHITE = np.zeros(256, bool), np.zeros(256, bool)
LETTER[65:91] = LETTER[97:123] = True
WHITE[[9, 10, 13, 32]] = True
ROWS = "doc_id long, pieces array<string>"
#: Pieces that a task holds before it counts them.
HELD = 1 << 20
#: Pieces, or bytes of text, that are worked on at once: a batch of long documents has many more.
PIECES, BYTES = 1 << 18, 1 << 21
#: Words of a table that every worker holds; larger ones are joined.
TABLE = 500_000


def listed(ids: pa.Array, name: str, starts: np.ndarray, flat: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(pa.array(starts, pa.int32()), flat)], names=["doc_id", name])


def starts_of(lists: pa.ListArray) -> np.ndarray:
    return np.concatenate(([0], np.cumsum(lists.value_lengths().fill_null(0).to_numpy(), dtype=np.int64)))


def words_in(texts: pa.StringArray) -> tuple[np.ndarray, pa.Array]:
    """Where each text's words begin and end in the list of all, and that list: runs of letters in lower case, with the white space before them as a space."""
    _, n, data = texts.buffers()
    at = np.frombuffer(n, np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    x = np.frombuffer(data, np.uint8)[at[0] : at[-1]].copy() if data is not None else np.zeros(0, np.uint8)
    at -= at[0]
    inside = np.ones(len(x) + 1, bool)  # behind another byte of the same text
    inside[at] = False
    letter, white = LETTER[x], WHITE[x]
    first = letter.copy()
    first[1:] &= ~(letter[:-1] & inside[1:-1])
    lead = np.zeros(len(x), bool)
    lead[:-1] = white[:-1] & letter[1:] & inside[1:-1]
    first[1:] &= ~lead[:-1]
    x |= 0x20
    x[lead] = 32
    begins = first | lead
    kept = letter | lead
    ends = np.concatenate(([0], np.cumsum(kept)))
    flat = pa.StringArray.from_buffers(int(begins.sum()), pa.py_buffer(np.append(ends[:-1][begins], ends[-1]).astype(np.int32)), pa.py_buffer(x[kept]))
    return np.concatenate(([0], np.cumsum(begins)))[at], flat


def of_documents(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Words of every document in lower case, as ``corpus.words``; null and empty texts have none."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in in_runs(source, BYTES):
            yield listed(batch.column(0), "pieces", *words_in(batch.column(1).cast(pa.string())))

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(run, ROWS)


def recut(rows: DataFrame, splitter: Callable[[], Callable[[list[str]], pa.Array]]) -> DataFrame:
    """Each piece by a list of pieces: ``splitter`` gives, in a task, what splits a list of distinct ones."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = splitter()
        for batch in in_runs(source, PIECES):
            words = batch.column(1).flatten().dictionary_encode()
            cut = split(words.dictionary.to_pylist()).take(words.indices)
            yield listed(batch.column(0), "pieces", starts_of(cut)[starts_of(batch.column(1))], cut.flatten())

    return rows.mapInArrow(run, ROWS)


def each(f: Callable[[str], str]) -> Callable[[list[str]], pa.Array]:
    """A splitter's function from one on words without their space: one piece for each, the space kept."""

    def split(words: list[str]) -> pa.Array:
        new = [" " + f(w[1:]) if w[:1] == " " else f(w) for w in words]
        return pa.ListArray.from_arrays(pa.array(range(len(new) + 1), pa.int32()), pa.array(new, pa.string()))

    return split


def counted(rows: DataFrame) -> DataFrame:
    """word (with its space), n: occurrences of each distinct piece."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def told() -> pa.RecordBatch:
            found = pa.concat_arrays(held).value_counts()
            return pa.RecordBatch.from_arrays([found.field(0), found.field(1)], names=["word", "n"])

        for batch in in_runs(source, PIECES):
            held.append(batch.column(1).flatten())
            size += len(held[-1])
            if size >= HELD:
                yield told()
                held, size = [], 0
        if size:
            yield told()

    return rows.select("doc_id", "pieces").mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def surfaces(counts: DataFrame) -> DataFrame:
    """surface, has_space, freq from the counts of pieces."""
    return counts.select(F.ltrim("word").alias("surface"), F.col("word").startswith(" ").alias("has_space"), F.col("n").alias("freq"))


def numbered(rows: DataFrame, vocab: DataFrame) -> DataFrame:
    """doc_id, ids: as ``encode.sequences``; pieces outside the vocabulary (held by the driver) leave no gap."""
    entries = vocab.select("surface", "has_space", "token_id").collect()  # a vocabulary
    names, number = [" " * r["has_space"] + r["surface"] for r in entries], np.array([r["token_id"] for r in entries], np.int32)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pa.array(names, pa.string())
        for batch in in_runs(source, PIECES):
            place = pc.index_in(batch.column(1).flatten(), value_set=known)
            there = place.is_valid().to_numpy(zero_copy_only=False)
            starts = np.concatenate(([0], np.cumsum(there)))[starts_of(batch.column(1))]
            yield listed(batch.column(0), "ids", starts, pa.array(number[place.drop_null().to_numpy()], pa.int32()))

    return rows.select("doc_id", "pieces").mapInArrow(run, "doc_id long, ids array<int>").where(F.size("ids") > 0)


def learnt(rows: DataFrame, n_merges: int, one_task: int = ONE_TASK) -> list[tuple[str, str]]:
    """Merge rules from the counts of all pieces, as ``tokenize.bpe_merges``."""
    return trained(counted(rows), n_merges, one_task=one_task)


def merged(rows: DataFrame, rules: Sequence[tuple[str, str]]) -> DataFrame:
    """Each word by its pieces under merge rules, the space before it being part of the first."""
    held = rows.sparkSession.sparkContext.broadcast(list(rules))
    return recut(rows, lambda: Rules(held.value).pieces)


def fixed_width(rows: DataFrame, width: int = 3) -> DataFrame:
    """Chunks of ``width`` letters, a shorter rest; the space stays with the first."""

    return recut(rows, lambda: lambda words: pa.array([chunks(w, width) for w in words], pa.list_(pa.string())))


def chunks(word: str, width: int) -> list[str]:
    lead = word[:1] == " "
    return [word[: lead + width], *(word[k : k + width] for k in range(lead + width, len(word), width))]


def substituted(rows: DataFrame, rules: Sequence[tuple[str, str]], table: DataFrame) -> DataFrame:
    """Each word put together again from the substitutes (src, dst: as many as pieces under the rules) of its pieces."""
    held = rows.sparkSession.sparkContext.broadcast((list(rules), {r["src"]: r["dst"] for r in table.collect()}))

    def splitter() -> Callable[[list[str]], pa.Array]:
        rules, other = held.value
        cut = Rules(rules)

        def split(words: list[str]) -> pa.Array:
            parts = cut.pieces(words)
            flat = parts.flatten().dictionary_encode()
            new = pa.array([other[p] for p in flat.dictionary.to_pylist()], pa.string()).take(flat.indices)
            spelled = pc.binary_join(pa.ListArray.from_arrays(pa.array(starts_of(parts), pa.int32()), new), "").to_pylist()
            return each(lambda w: w)([" " * (w[:1] == " ") + x.lstrip(" ") for w, x in zip(words, spelled)])

        return split

    return recut(rows, splitter)


def resampled(rows: DataFrame, counts: DataFrame, seed: int = 42) -> DataFrame:
    """Each piece by a random one of its class (space before, letters) among those counted, as ``rewrite.resample_tokens``; drawn
    by a 64-bit mixer of (seed, document, place) instead of a digest for each token."""
    classes: dict[tuple[bool, int], list[str]] = {}
    for r in sorted(counts.select("word").collect()):  # a vocabulary
        classes.setdefault((r["word"][:1] == " ", len(r["word"])), []).append(r["word"])
    held = rows.sparkSession.sparkContext.broadcast(classes)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classes = held.value
        names, kinds = pa.array([w for ws in classes.values() for w in ws], pa.string()), {k: i for i, k in enumerate(classes)}
        size = np.array([len(ws) for ws in classes.values()], np.uint64)
        first = np.cumsum(size) - size
        for batch in in_runs(source, PIECES):
            words, start = batch.column(1).flatten().dictionary_encode(), starts_of(batch.column(1))
            kind = np.array([kinds[w[:1] == " ", len(w)] for w in words.dictionary.to_pylist()], np.int64)[words.indices.to_numpy()]
            n = np.diff(start)
            x = (np.arange(start[-1]) - np.repeat(start[:-1], n)).astype(np.uint64)
            x += np.repeat(batch.column(0).fill_null(0).to_numpy().astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ np.uint64(seed << 40), n)
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            x = ((x ^ (x >> np.uint64(31))) >> np.uint64(11)) % size[kind] + first[kind]
            yield listed(batch.column(0), "pieces", start, names.take(pa.array(x)))

    return rows.mapInArrow(run, ROWS)


def stemmed(rows: DataFrame) -> DataFrame:
    return recut(rows, lambda: each(Stemmer.stem))


def replaced(rows: DataFrame, table: DataFrame, most: int = TABLE) -> DataFrame:
    """Words by those of a table (word, other: a row for each word that changes); one of more than ``most`` rows is joined."""
    few = table.limit(most + 1).collect()
    if len(few) <= most:
        held = rows.sparkSession.sparkContext.broadcast({r[0]: r[1] for r in few})

        def splitter() -> Callable[[list[str]], pa.Array]:
            other = held.value
            return each(lambda w: other.get(w, w))

        return recut(rows, splitter)
    word, other = table.columns
    long = rows.select("doc_id", F.posexplode("pieces").alias("pos", "piece"))
    met = long.join(table, F.ltrim("piece") == F.col(word), "left")
    new = F.concat(F.when(F.col("piece").startswith(" "), " ").otherwise(""), F.coalesce(F.col(other), F.ltrim("piece")))
    row = F.array_sort(F.collect_list(F.struct("pos", new.alias("piece"))))
    return met.groupBy("doc_id").agg(F.transform(row, lambda x: x["piece"]).alias("pieces"))
