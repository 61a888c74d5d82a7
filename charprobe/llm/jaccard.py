"""Operator 2: exact Jaccard join on word n-grams, answered as connected components.

Two documents link when 100 * |intersection| >= percent * |union| of their n-gram sets. Copies of one set are one
node from the start. The join goes through inverted index lists:

1. Each task turns its sets into blobs of (n-gram, set), dealt by n-gram. Whoever holds an n-gram's list knows how
   many sets have it; n-grams of one set alone end there, as they can be in no intersection.
2. What is shared goes back, dealt by set, with its count. A set orders its n-grams rarest first (ties by hash).
   Two sets can only link if they share one of their first |set| - ceil(percent% of |set|) + 1 n-grams, so a set
   whose prefix has only n-grams of its own has no partner. Few sets remain.
3. Sets that share a prefix n-gram form coarse groups; within a group (large ones in pairs of blocks) sets are taken
   by ascending size. Index lists are skipped block by block where size or position rules out a link, and a set's
   answers are derived from those of the most similar set before it: a set of the same component needs no check,
   and for others the known overlap of the similar set bounds the set's own.

An n-gram that many sets of one task have (HOT of them) is not listed: its sets report it themselves and it is ordered last. Sets
that consist of little else meet in step 3, whose blocks bound the memory of a task, however large the group.

A document with fewer words than n has its whole word sequence as its only n-gram; without words its set is empty and
it links with nothing. Null texts count as empty. Rows with equal ids are one document id with several texts: each
row is answered for its own text. Sets and n-grams go by 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U64, WordHasher, as_input, batches, buckets_for, connected_components, packed, staged, text_key, texts_of, unpacked, window_hashes

#: N-grams that a task holds before it writes its blobs, and sets (their numbers take 16 bits; the last is a mark).
HELD, SETS, MARK = 3_000_000, 65_000, 65_535
#: Sets of one task's run that make an n-gram hot.
HOT = 64
#: Counts are kept in a byte; hot n-grams have the largest.
COMMON, HOTTEST = 254, 255
#: Sets of a block in step 3.
BLOCK = 2048
#: Entries of a block of an index list.
SKIP = 64


def ngram_set(text: bytes, n: int, hasher: WordHasher) -> np.ndarray:
    """Ascending distinct hashes of the n-grams of a lower-cased text."""
    h = hasher(text.lower().split())
    return np.unique(window_hashes(h, min(n, len(h)))) if len(h) else np.zeros(0, U64)


def set_id(hashes: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(hashes.tobytes()) - (1 << 63)


def least_overlap(size: int | np.ndarray, percent: int):
    """Fewest common n-grams that a set of this size needs with any partner."""
    return -(-percent * size // 100)


def needed(a: int | np.ndarray, b: int | np.ndarray, percent: int):
    """Fewest common n-grams that link sets of sizes a and b."""
    return -(-percent * (a + b) // (100 + percent))


def prefix_length(size: int | np.ndarray, percent: int):
    return size - least_overlap(size, percent) + 1


# -- step 1 ------------------------------------------------------------------------------------------------------


LISTED = pa.schema([("bucket", pa.int32()), ("short", pa.bool_()), ("tokens", pa.binary()), ("numbers", pa.binary()), ("ids", pa.binary()), ("sizes", pa.binary())])
LISTED_SQL = "bucket int, short boolean, tokens binary, numbers binary, ids binary, sizes binary"
SHARED = pa.schema([("bucket", pa.int32()), ("ids", pa.binary()), ("sizes", pa.binary()), ("lengths", pa.binary()), ("tokens", pa.binary()), ("counts", pa.binary())])
SHARED_SQL = "bucket int, ids binary, sizes binary, lengths binary, tokens binary, counts binary"


def bucket_starts(buckets: int) -> np.ndarray:
    """First token of each bucket of equal width."""
    return np.array([(k << 64) // buckets for k in range(buckets)], dtype=U64)


def index_blobs(sets: list[np.ndarray], ids: list[int], buckets: int) -> Iterator[tuple]:
    tokens = np.concatenate(sets)
    number = np.repeat(np.arange(len(sets), dtype=np.uint16), [len(s) for s in sets])
    order = np.argsort(tokens, kind="stable")
    tokens, number = tokens[order], number[order]
    del order
    size = np.array([len(s) for s in sets], np.uint32)
    ident = np.array(ids, np.int64)
    first = np.flatnonzero(np.concatenate(([True], tokens[1:] != tokens[:-1])))
    run = np.diff(np.append(first, len(tokens)))
    hot = run >= HOT
    if hot.any():
        where = np.repeat(hot, run)
        # A hot n-gram goes straight to its sets' buckets, as (n-gram, set) with no list; one mark goes to its own bucket.
        hot_tokens, hot_numbers = tokens[where], number[where]
        at = (ident[hot_numbers] % buckets).astype(np.int64)
        o = np.lexsort((hot_tokens, at))
        at, hot_tokens, hot_numbers = at[o], hot_tokens[o], hot_numbers[o]
        ends = np.searchsorted(at, np.arange(buckets + 1))
        for b in range(buckets):
            lo, hi = ends[b], ends[b + 1]
            if hi > lo:
                yield -1 - b, False, hot_tokens[lo:hi].tobytes(), None, ident[hot_numbers[lo:hi]].tobytes(), size[hot_numbers[lo:hi]].tobytes()
        keep = ~where
        keep[first[hot]] = True
        number = number.copy()
        number[first[hot]] = MARK
        tokens, number = tokens[keep], number[keep]
    ends = np.append(np.searchsorted(tokens, bucket_starts(buckets)), len(tokens))
    for b in range(buckets):
        lo, hi = ends[b], ends[b + 1]
        if hi > lo:
            own = number[lo:hi]
            used, again = np.unique(own, return_inverse=True)
            known = used[used != MARK]
            again = again.astype(np.uint16)
            again[own == MARK] = MARK
            short, data = packed(tokens[lo:hi])
            yield b, short, data, again.tobytes(), ident[known].tobytes(), size[known].tobytes()


def build_index(source: Iterator[pa.RecordBatch], n: int, buckets: int) -> Iterator[tuple]:
    hasher, seen = WordHasher(), set()
    sets, ids, held = [], [], 0
    for batch in source:
        for text in texts_of(batch, 0):
            s = ngram_set(text, n, hasher)
            if not len(s):
                continue
            i = set_id(s)
            if i in seen:
                continue
            seen.add(i)
            sets.append(s)
            ids.append(i)
            held += len(s)
            if held >= HELD or len(sets) >= SETS:
                yield from index_blobs(sets, ids, buckets)
                sets, ids, held = [], [], 0
    if sets:
        yield from index_blobs(sets, ids, buckets)


def share_lists(source: Iterator[pa.RecordBatch], buckets: int) -> Iterator[tuple]:
    """Lists of one bucket after another: n-grams that two sets or more have, dealt by set."""
    held: dict[int, list[tuple]] = {}
    for batch in source:
        for b, *rest in zip(*(batch.column(c).to_pylist() for c in LISTED.names)):
            held.setdefault(b, []).append(rest)
    while held:
        b, blobs = held.popitem()
        if b < 0:  # hot n-grams on their way to their sets
            t = np.concatenate([np.frombuffer(x[1], U64) for x in blobs])
            i = np.concatenate([np.frombuffer(x[3], np.int64) for x in blobs])
            z = np.concatenate([np.frombuffer(x[4], np.uint32) for x in blobs])
            yield from dealt(t, i, z, np.full(len(t), HOTTEST, np.uint8), buckets)
            continue
        tokens, owner, size = [], [], []
        for short, data, numbers, ids, sizes in blobs:
            k = np.frombuffer(numbers, np.uint16)
            mark = k == MARK
            ident, weight = np.append(np.frombuffer(ids, np.int64), 0), np.append(np.frombuffer(sizes, np.uint32), np.uint32(0))
            k = np.where(mark, len(ident) - 1, k)
            tokens.append(unpacked(short, data))
            owner.append(ident[k])
            size.append(weight[k])
        t, i, z = np.concatenate(tokens), np.concatenate(owner), np.concatenate(size)
        del blobs, tokens, owner, size  # what is held twice counts in each worker's memory
        order = np.lexsort((i, t))
        t, i, z = t[order], i[order], z[order]
        del order
        new = np.concatenate(([True], (t[1:] != t[:-1]) | (i[1:] != i[:-1])))  # the same set may come from several tasks
        t, i, z = t[new], i[new], z[new]
        first = np.flatnonzero(np.concatenate(([True], t[1:] != t[:-1])))
        run = np.diff(np.append(first, len(t)))
        marked = np.add.reduceat((z == 0).astype(np.int64), first) > 0
        count = np.where(marked, HOTTEST, np.minimum(run, COMMON)).astype(np.uint8)
        keep = np.repeat(marked | (run > 1), run) & (z > 0)
        count = np.repeat(count, run)[keep]
        t, i, z = t[keep], i[keep], z[keep]
        del new, first, run, marked, keep
        yield from dealt(t, i, z, count, buckets)


def dealt(t: np.ndarray, i: np.ndarray, z: np.ndarray, count: np.ndarray, buckets: int) -> Iterator[tuple]:
    at = (i % buckets).astype(np.int64)
    order = np.lexsort((t, i, at))
    t, i, z, count, at = t[order], i[order], z[order], count[order], at[order]
    ends = np.searchsorted(at, np.arange(buckets + 1))
    for b in range(buckets):
        lo, hi = ends[b], ends[b + 1]
        if hi > lo:
            first = np.flatnonzero(np.concatenate(([True], i[lo + 1 : hi] != i[lo : hi - 1])))
            lengths = np.diff(np.append(first, hi - lo)).astype(np.uint32)
            yield b, i[lo:hi][first].tobytes(), z[lo:hi][first].tobytes(), lengths.tobytes(), t[lo:hi].tobytes(), count[lo:hi].tobytes()


# -- step 2 ------------------------------------------------------------------------------------------------------

INVOLVED = pa.schema([("id", pa.int64()), ("size", pa.int32()), ("prefix", pa.list_(pa.int64())), ("tokens", pa.binary())])
INVOLVED_SQL = "id long, size int, prefix array<long>, tokens binary"


def involved(source: Iterator[pa.RecordBatch], percent: int) -> Iterator[tuple]:
    """Sets whose prefix reaches into n-grams that other sets have: with those, in order, and all that they share."""
    held: dict[int, list[tuple]] = {}
    for batch in source:
        for b, *rest in zip(*(batch.column(c).to_pylist() for c in SHARED.names)):
            held.setdefault(b, []).append(rest)
    while held:
        blobs = held.popitem()[1]
        ids, sizes, tokens, counts = [], [], [], []
        for i, z, lengths, t, c in blobs:
            n = np.frombuffer(lengths, np.uint32)
            ids.append(np.repeat(np.frombuffer(i, np.int64), n))
            sizes.append(np.repeat(np.frombuffer(z, np.uint32), n))
            tokens.append(np.frombuffer(t, U64))
            counts.append(np.frombuffer(c, np.uint8))
        i, z, t, c = np.concatenate(ids), np.concatenate(sizes), np.concatenate(tokens), np.concatenate(counts)
        del blobs, ids, sizes, tokens, counts
        order = np.lexsort((t, c, i))
        i, z, t = i[order], z[order], t[order]
        del order, c
        # A hot n-gram comes from every task that has the set.
        new = np.concatenate(([True], (t[1:] != t[:-1]) | (i[1:] != i[:-1])))
        i, z, t = i[new], z[new], t[new]
        first = np.flatnonzero(np.concatenate(([True], i[1:] != i[:-1])))
        ends = np.append(first[1:], len(i))
        size = z[first].astype(np.int64)
        reach = prefix_length(size, percent) - (size - (ends - first))  # prefix n-grams that are shared
        for k in np.flatnonzero(reach > 0):
            lo, hi = first[k], ends[k]
            yield int(i[lo]), int(size[k]), t[lo : min(hi, lo + reach[k])].view(np.int64), t[lo:hi].tobytes()


# -- step 3 ------------------------------------------------------------------------------------------------------


class SkipList:
    """One n-gram's list, by ascending set size, in blocks of SKIP that know their greatest size and greatest rest."""

    __slots__ = ("n", "sets", "sizes", "rests", "most")

    def __init__(self) -> None:
        self.n = 0
        self.sets, self.sizes, self.rests = (np.zeros(4, np.int64) for _ in range(3))
        self.most: list[int] = []

    def add(self, k: int, size: int, rest: int) -> None:
        if self.n == len(self.sets):
            self.sets, self.sizes, self.rests = (np.concatenate([x, np.zeros_like(x)]) for x in (self.sets, self.sizes, self.rests))
        self.sets[self.n], self.sizes[self.n], self.rests[self.n] = k, size, rest
        if self.n % SKIP:
            self.most[-1] = max(self.most[-1], rest)
        else:
            self.most.append(rest)
        self.n += 1

    def near(self, size: int, rest: int, percent: int) -> np.ndarray:
        """Sets that may link with one of this size, of which ``rest`` n-grams stand from here on."""
        smallest = least_overlap(size, percent)
        first = int(np.searchsorted(self.sizes[: self.n], smallest))
        fewest = needed(size, smallest, percent)
        parts = []
        for b in range(first // SKIP, len(self.most)):
            if min(rest, self.most[b]) < fewest:
                continue
            lo, hi = max(first, b * SKIP), min(self.n, (b + 1) * SKIP)
            parts.append(self.sets[lo:hi][np.minimum(rest, self.rests[lo:hi]) >= needed(size, self.sizes[lo:hi], percent)])
        return np.concatenate(parts) if parts else np.zeros(0, np.int64)


def link_group(sizes: np.ndarray, tokens: list[np.ndarray], percent: int, side: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links (by place) that connect all sets of the group which belong together.

    sizes: whole sizes; tokens: the n-grams that each shares with any set. With ``side`` (0 and 1) only sets of
    different sides need meet. Links within a component already connected are not looked for.
    """
    m = len(sizes)
    flat = np.concatenate(tokens) if m else np.zeros(0, U64)
    lengths = np.array([len(t) for t in tokens], np.int64)
    _, inverse, count = np.unique(flat, return_inverse=True, return_counts=True)
    rank = np.empty(len(count), np.int64)
    rank[np.argsort(count, kind="stable")] = np.arange(len(count))
    dense, keep = rank[inverse], count[inverse] > 1
    owner = np.repeat(np.arange(m), lengths)[keep]
    dense = dense[keep]
    o = np.lexsort((dense, owner))
    dense, owner = dense[o], owner[o]
    starts = np.searchsorted(owner, np.arange(m + 1))
    mark = np.zeros(len(count), bool)
    of = np.arange(m)  # component of each set; the smaller one is renamed when two meet
    members: dict[int, list[int]] = {k: [k] for k in range(m)}
    lists: dict[int, SkipList] = {}
    answers: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64))] * m
    bound = np.full(m, 1 << 40)  # greatest possible overlap of the set at hand with each other one
    links = []
    for x in np.argsort(sizes, kind="stable").tolist():
        own = dense[starts[x] : starts[x + 1]]
        size, shared = int(sizes[x]), len(own)
        reach = int(prefix_length(size, percent)) - (size - shared)
        if reach <= 0:
            continue
        prefix = own[:reach].tolist()
        hits = [lists[t].near(size, shared - p, percent) for p, t in enumerate(prefix) if t in lists]
        for p, t in enumerate(prefix):
            lists.setdefault(t, SkipList()).add(x, size, shared - p)
        hits = [h for h in hits if len(h)]
        if not hits:
            continue
        found, times = np.unique(np.concatenate(hits), return_counts=True)
        found = found[np.argsort(-times, kind="stable")]  # the set that shares most of the prefix comes first
        if side is not None:
            found = found[side[found] != side[x]]
        if not len(found):
            continue
        mark[own] = True
        looked, step = [], 1
        while len(found):
            ahead, found = found[:step], found[step:]
            step = 128
            lo, n = starts[ahead], starts[ahead + 1] - starts[ahead]
            ends = np.cumsum(n)
            places = np.arange(ends[-1]) + np.repeat(lo - ends + n, n)
            overlap = np.add.reduceat(mark[dense[places]].astype(np.int64), ends - n)
            bound[ahead] = overlap
            looked.append(ahead)
            for k, v in zip(ahead[overlap >= needed(size, sizes[ahead], percent)].tolist(), overlap[overlap >= needed(size, sizes[ahead], percent)].tolist()):
                if of[k] != of[x]:
                    links.append((x, k))
                    a, b = sorted((int(of[k]), int(of[x])), key=lambda c: len(members[c]))
                    of[members[a]] = b
                    members[b] += members.pop(a)
                    # What the similar set knows bounds what this one can share: it has size - v n-grams besides.
                    others, most = answers[k]
                    bound[others] = np.minimum(bound[others], most + (size - v))
                    looked.append(others)
            found = found[(of[found] != of[x]) & (bound[found] >= needed(size, sizes[found], percent))]
        mark[own] = False
        looked = np.unique(np.concatenate(looked))
        answers[x] = (looked, bound[looked].copy())
        bound[looked] = 1 << 40
    return links


def link_sets(sets: DataFrame, percent: int) -> DataFrame:
    """(u, v): links among sets(id, size, prefix, tokens) that connect each component."""
    posted = sets.select("id", F.explode("prefix").alias("token"))
    pivot = posted.groupBy("token").agg(F.min("id").alias("pivot"), F.count("*").alias("n")).where("n > 1").select(F.col("token").alias("key"), "pivot")
    star = posted.join(pivot, F.col("token") == F.col("key")).where("id <> pivot").select(F.col("id").alias("u"), F.col("pivot").alias("v"))
    group = connected_components(star)
    many = group.groupBy("root").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    placed = sets.join(group, sets["id"] == group["node"]).join(many, "root").withColumn("block", F.expr("int(pmod(xxhash64(id), blocks))"))
    met = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = met.select("root", F.least("block", "other").alias("a"), F.greatest("block", "other").alias("b"), "block", "id", "size", "tokens")

    def pairs(key, table):
        sizes = table.column("size").to_numpy().astype(np.int64)
        tokens = [np.frombuffer(x, U64) for x in table.column("tokens").to_pylist()]
        ids = table.column("id").to_numpy()
        side = None if key[1].as_py() == key[2].as_py() else (table.column("block").to_numpy() == key[1].as_py()).astype(np.int8)
        links = link_group(sizes, tokens, percent, side)
        return pa.table({"u": pa.array([int(ids[x]) for x, _ in links], pa.int64()), "v": pa.array([int(ids[k]) for _, k in links], pa.int64())})

    return met.groupBy("root", "a", "b").applyInArrow(pairs, "u long, v long")


def jaccard_components(docs: DataFrame, n: int = 3, percent: int = 90, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles and component_id (the smallest id reachable by links, its own included) of each row.

    Besides, as ids can be null or repeated: text_key, which with the id names the row, and component_key, the
    component's smallest set (null without n-grams).
    """
    rows = as_input(docs, id_col, text_col).withColumn("text_key", text_key(F.col("text")))
    buckets = buckets_for(docs, mb=10)
    own = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("id", pa.int64()), ("text_key", pa.int64())])

    def sized(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = WordHasher()

        def out() -> Iterator[tuple]:
            for batch in source:
                for doc_id, text, key in zip(batch.column(0).to_pylist(), texts_of(batch), batch.column(2).to_pylist()):
                    s = ngram_set(text, n, hasher)
                    yield doc_id, len(s), set_id(s) if len(s) else None, key

        yield from batches(out(), own)

    ids = staged(rows.mapInArrow(sized, "doc_id long, n_shingles long, id long, text_key long"), "sets")
    listed = rows.select("text").mapInArrow(lambda s: batches(build_index(s, n, buckets), LISTED, size=64), LISTED_SQL)
    # One bucket to a task: a hash of the buckets would put several into some tasks. Hot n-grams go by their sets' bucket.
    shared = listed.repartitionById(buckets, F.when(F.col("bucket") < 0, -1 - F.col("bucket")).otherwise(F.col("bucket")).cast("int")).mapInArrow(lambda s: batches(share_lists(s, buckets), SHARED, size=64), SHARED_SQL)
    sets = staged(shared.repartitionById(buckets, F.col("bucket")).mapInArrow(lambda s: batches(involved(s, percent), INVOLVED, size=256), INVOLVED_SQL), "involved")
    linked = connected_components(link_sets(sets, percent))
    least = ids.where("id is not null").groupBy("id").agg(F.min("doc_id").alias("least"))
    joined = least.join(linked, least["id"] == linked["node"], "left")
    of_root = joined.where("root is not null").groupBy("root").agg(F.min("least").alias("least_linked")).withColumnRenamed("root", "of")
    named = joined.join(of_root, joined["root"] == of_root["of"], "left").select(F.col("id").alias("of_set"), F.coalesce("least_linked", "least").alias("least_id"), F.coalesce("root", "id").alias("component_key"))
    return ids.join(named, ids["id"] == named["of_set"], "left").select("doc_id", "n_shingles", F.coalesce("least_id", "doc_id").alias("component_id"), "text_key", "component_key")


def representatives(docs: DataFrame, components: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of docs for each component: that of the smallest id (null ids last), ties by the text's hash.

    Rows without n-grams are components of their own. Rows alike in id and text count once.
    """
    order = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "text_key")
    chosen = components.where("component_key is not null").groupBy("component_key").agg(F.min(order).alias("row")).select("row.doc_id", "row.text_key")
    own = chosen.unionByName(components.where("component_key is null").select("doc_id", "text_key")).distinct()
    own = own.select(F.col("doc_id").alias("kept_id"), F.col("text_key").alias("kept_key"))
    # The rows' own columns go by place meanwhile, so that no name of theirs meets one of ours.
    places = [f"c{k}" for k in range(len(docs.columns))]
    held, key, text = docs.toDF(*places), places[docs.columns.index(id_col)], places[docs.columns.index(text_col)]
    met = held.join(own, F.col(key).cast("long").eqNullSafe(F.col("kept_id")) & (text_key(F.col(text)) == F.col("kept_key")))
    return met.dropDuplicates(["kept_id", "kept_key"]).select(*places).toDF(*docs.columns)
