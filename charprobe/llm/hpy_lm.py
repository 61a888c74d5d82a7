"""Operator 9: a hierarchical Pitman-Yor language model over all words.

Each word (and the start of a text) is a context with a restaurant of its own, whose dishes are the words and ends that
follow it; all these share one parent restaurant, and that one's base spells a word byte by byte (letter_logs). No word is
left out: contexts, dishes and their counts are tables that grow with the corpus, dealt by context.

Seating is sampled by Gibbs (see pitman_yor): given the parent's probabilities the restaurants draw their tables apart
from each other, each in the task that has its context; their tables are then the parent's customers, dealt by word,
which draws its own tables in turn. Discounts and concentrations are drawn between the sweeps. Predictive probabilities
are averaged over the last sweeps:

    P(w | u) = (c_uw - d t_uw + (a + d T_u) P(w)) / (a + c_u),   P(w) = (c_w - d' t_w + (a' + d' T) base(w)) / (a' + C)

with c_w the tables of all contexts that serve w. Summed over all words of all lengths and the end, each is 1, for contexts
never seen too (these have P(w)). Scores go the other way: each task asks, for the pairs of its documents, the task of
the context, which knows the restaurant and adds up what it has for each document.

Null texts count as empty; an empty text is its end alone. Repeated rows, and rows with null ids, get rows of their
own. With no training document every word has its base probability. Words are held as 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U64, as_input, batches, buckets_for, crc_remainder, dropped, from_bytes, in_bytes, packed, rows_of, staged, unpacked
from .pitman_yor import draw_parameters, draw_tables, histogram, stirling_table, sweep
from .scan import SPACE, Words, slices

FOLDS, HELD_OUT = 7, 2
#: The start of a text as a context, and its end as a dish.
START, END = U64(1), U64(2)
#: The base's parameters: an end's share, a letter's share among bytes, and that a byte is a word's last (fixed values).
ENDS, LETTERS, LAST = 0.02, 0.9, 0.15
#: Bytes that a lower-cased word can have besides a to z: no white space, no capitals.
OTHERS = 256 - int(SPACE.sum()) - 52
#: Pairs that a task holds before it writes them out.
HELD = 2_000_000
NO_ID = -(1 << 63)

LETTER = np.zeros(256, bool)
LETTER[[*range(65, 91), *range(97, 123)]] = True
ASK, TELL, STATE, TABLES, STATS, DOCS, PAIRS, PART, HISTOGRAM = "ask", "1 tell", "0 state", "1 tables", "stats", "0 docs", "2 pairs", "1 part", "histogram"
ROW = pa.schema([("kind", pa.string()), ("bucket", pa.int32()), ("part", pa.int64()), ("numbers", pa.list_(pa.float64())), ("short", pa.bool_()), ("contexts", pa.binary()), ("runs", pa.binary()), ("words_short", pa.bool_()), ("words", pa.binary()), ("places", pa.binary()), ("counts", pa.binary()), ("large", pa.binary()), ("extra", pa.binary()), ("more", pa.binary())])
ROW_SQL = "kind string, bucket int, part long, numbers array<double>, short boolean, contexts binary, runs binary, words_short boolean, words binary, places binary, counts binary, large binary, extra binary, more binary"
EMPTY = dict.fromkeys(ROW.names)
OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])


def row(**values) -> tuple:
    return tuple((EMPTY | values).values())


def letter_logs(letters: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Natural log of the base probability of words with so many letters among so many bytes: (1 - ENDS) times the
    chance of the length times that of each byte. A size of 0 is the end."""
    word = np.log(1 - ENDS) + np.log(LAST) + (size - 1) * np.log1p(-LAST) + letters * np.log(LETTERS / 26) + (size - letters) * np.log((1 - LETTERS) / OTHERS)
    return np.where(size == 0, np.log(ENDS), word)


class Spelled:
    """Dishes of a column of texts: of each text its words and the end; the contexts before them; and their spelling's base."""

    def __init__(self, column: pa.Array) -> None:
        w = Words(column, True)
        letters = np.zeros(len(w.data) + 1, np.int64)
        np.cumsum(LETTER[w.data], out=letters[1:])
        base = letter_logs(letters[w.end] - letters[w.start], w.end - w.start)
        self.dish = np.insert(w.hash, w.first[1:], END)
        self.base = np.insert(base, w.first[1:], np.log(ENDS)).astype(np.float32)
        self.context = np.insert(w.hash, w.first[:-1], START)
        self.n_tokens = np.diff(w.first) + 1


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    """Ends of the buckets' runs in ascending hashes: a bucket is a range of hashes."""
    return np.append(np.searchsorted(h, np.array([(k << 64) // buckets for k in range(buckets)], dtype=U64)), len(h))


def as_places(x: np.ndarray, most: int) -> bytes:
    return x.astype(np.uint16 if most <= 1 << 16 else np.uint32).tobytes()


def places_of(data, most: int, kind: type = np.int64) -> np.ndarray:
    return np.frombuffer(data, np.uint16 if most <= 1 << 16 else np.uint32).astype(kind)


def pair_blobs(held: list[tuple], buckets: int, scoring: bool) -> Iterator[dict]:
    """Distinct (context, dish) pairs for each bucket. In training with their counts, and the base of each dish; in
    scoring with the documents (numbers within the run) that have them, one entry for each time. ``held`` is emptied."""
    opens, dish, base, doc = (np.concatenate(x) for x in zip(*held))
    held.clear()  # what is held twice, or longer than needed, counts in each worker's memory
    dish = np.append(dish, START)
    order = np.argsort(dish, kind="stable")
    dish = dish[order]
    new = np.concatenate(([True], dish[1:] != dish[:-1]))
    names, first = dish[new], order[new]
    place = np.empty(len(dish), np.uint32)
    place[order] = np.cumsum(new, dtype=np.uint32) - np.uint32(1)
    del dish, order, new
    key = np.empty(len(place) - 1, U64)
    key[0], key[1:] = place[-1], place[:-2]  # a context is the dish before, or the start
    key[opens] = place[-1]
    key <<= U64(32)
    key |= place[:-1]
    order = np.argsort(key, kind="stable")
    key, doc = key[order], doc[order]  # in training doc is 1 for a training row and 0 for others
    del order, place
    start = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    pair, size = key[start], np.diff(np.append(start, len(key)))
    ends = np.searchsorted(pair, bucket_of(names, buckets).astype(U64) << U64(32))
    known_base = np.append(base, np.float32(0))[np.minimum(first, len(base))]
    counts = size if scoring else np.add.reduceat(doc.astype(np.int64), start)
    edge = np.append(start, len(key))
    for b in range(buckets):
        lo, hi = int(ends[b]), int(ends[b + 1])
        if hi > lo:
            u, runs = np.unique(pair[lo:hi] >> U64(32), return_counts=True)
            w, at = np.unique(pair[lo:hi] & U64(0xFFFFFFFF), return_inverse=True)
            short, contexts = packed(names[u.astype(np.int64)])
            words_short, words = packed(names[w.astype(np.int64)])
            small, large = in_bytes(counts[lo:hi])
            out = {"bucket": b, "short": short, "contexts": contexts, "runs": runs.astype(np.uint32).tobytes(), "words_short": words_short, "words": words, "places": as_places(at, len(w)), "counts": small, "large": large}
            if scoring:
                out["extra"] = as_places(doc[edge[lo] : edge[hi]], int(doc.max()) + 1)
            else:
                out["extra"] = known_base[w.astype(np.int64)].astype(np.float32).tobytes()
            yield out


def read_pairs(r: dict, kind: type = np.int64) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct contexts and words of a blob, and of each pair the places in these and its count."""
    contexts, words = unpacked(r["short"], r["contexts"]), unpacked(r["words_short"], r["words"])
    return contexts, words, np.repeat(np.arange(len(contexts), dtype=kind), np.frombuffer(r["runs"], np.uint32)), places_of(r["places"], len(words), kind), from_bytes(r["counts"], r["large"])


def training_pairs(source: Iterator[pa.RecordBatch], buckets: int) -> Iterator[tuple]:
    """Pairs of all documents with their counts in the training ones, so that each bucket knows all words it is asked for."""
    held, amount = [], 0
    for batch in slices(source):
        s = Spelled(batch.column(1))
        train = np.repeat(~np.array(batch.column(2).to_pylist(), bool), s.n_tokens).astype(np.uint8) if len(s.n_tokens) else np.zeros(0, np.uint8)
        held.append((s.context == START, s.dish, s.base, train))
        amount += len(s.dish)
        if amount >= HELD:
            for blob in pair_blobs(held, buckets, False):
                yield row(kind=PAIRS, **blob)
            held, amount = [], 0
    if amount:
        for blob in pair_blobs(held, buckets, False):
            yield row(kind=PAIRS, **blob)


def by_word(words: np.ndarray, parts: int, bucket: int, kind: str, **columns: np.ndarray) -> Iterator[tuple]:
    """Columns of a bucket's words, dealt by word; ``words`` ascend, so they need not be told again afterwards."""
    ends = bucket_of(words, parts)
    for p in range(parts):
        lo, hi = ends[p], ends[p + 1]
        if hi > lo:
            short, data = packed(words[lo:hi]) if kind == ASK else (None, None)
            yield row(kind=kind, bucket=bucket, part=p, words_short=short, words=data, **{k: v[lo:hi].tobytes() for k, v in columns.items()})


def gathered(source: Iterator[pa.RecordBatch], buckets: int) -> Iterator[tuple]:
    """Of each bucket (its rows come one after another): its restaurants, and what it asks of the parent."""
    bucket, held = None, []

    def told() -> Iterator[tuple]:
        if not held:
            return
        contexts, words = np.unique(np.concatenate([h[0] for h in held])), np.unique(np.concatenate([h[1] for h in held]))
        base = np.zeros(len(words), np.float32)
        keys, counts = [], []
        while held:
            u, w, cu, cw, n, b = held.pop()
            at = np.searchsorted(words, w)
            base[at] = b
            keys.append(np.searchsorted(contexts, u)[cu] << 32 | at[cw])
            counts.append(n)
        keys, counts = np.concatenate(keys), np.concatenate(counts).astype(np.int64)
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
        del order
        start = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        keys, counts = keys[start], np.add.reduceat(counts, start)
        seen = counts > 0  # pairs of documents that are held out only told their words
        keys, counts = keys[seen], counts[seen]
        cu, cw = keys >> 32, keys & 0xFFFFFFFF
        runs = np.bincount(cu, minlength=len(contexts))
        short, data = packed(contexts)
        words_short, names = packed(words)
        small, large = in_bytes(counts)
        yield row(kind=STATE, bucket=bucket, short=short, contexts=data, runs=runs.astype(np.uint32).tobytes(), words_short=words_short, words=names, places=as_places(cw, len(words)), counts=small, large=large, extra=base.tobytes())
        yield row(kind=STATS, bucket=bucket, numbers=[float((counts == 1).sum()), float((counts == 2).sum())])
        n = np.bincount(cw, weights=counts, minlength=len(words)).astype(np.int64)
        yield from by_word(words, buckets, bucket, ASK, counts=n, runs=np.bincount(cw, minlength=len(words)).astype(np.uint32), extra=base)

    for batch in source:
        for r in rows_of(batch):
            if r["bucket"] != bucket:
                yield from told()
                bucket, held = r["bucket"], []
            held.append((*read_pairs(r, np.int32), np.frombuffer(r["extra"], np.float32).copy()))  # not a view, which would hold the batch
    yield from told()


def parent_rows(source: Iterator[pa.RecordBatch], d: float, a: float, tables: float, draw: bool, last: bool, seed: int) -> Iterator[tuple]:
    """For each bucket, of its words: the parent's weight of them (a draw, or ``last`` its mean: customers less discounted tables), and counts in the corpus.

    The rows of a part come one after another: first what all buckets ask, then, from the second sweep on, their tables.
    """
    part, asked, later = None, [], {}

    def told() -> Iterator[tuple]:
        if not asked:
            return
        words, place = np.unique(np.concatenate([x[1] for x in asked]), return_inverse=True)
        n = np.bincount(place, weights=np.concatenate([x[2] for x in asked]), minlength=len(words)).astype(np.int64)
        own = np.concatenate([later.get(x[0], x[3]) for x in asked])
        c = np.bincount(place, weights=own, minlength=len(words)).astype(np.int64)
        base = np.zeros(len(words), np.float32)
        base[place] = np.concatenate([x[4] for x in asked])
        t = (c > 0).astype(np.int64)
        rng = np.random.default_rng([seed, part])
        if draw and c.any():
            # The parent's own step: one restaurant whose parent is the base.
            x = np.log(d) + np.log(rng.gamma(a / d + tables))
            held = np.flatnonzero(c)
            t[held] = draw_tables(c[held], x + base[held].astype(np.float64), d, stirling_table(d), rng, t[held])
        mass = c - d * t
        if not last:  # the contexts' step is exact given a draw of the parent's probabilities; scores take their mean
            mass = rng.gamma(mass)
        lo = 0
        for bucket, w, *_ in asked:
            at = place[lo : lo + len(w)]
            lo += len(w)
            yield row(kind=TELL, bucket=bucket, part=part, runs=mass[at].astype(np.float64).tobytes(), counts=n[at].astype(np.int64).tobytes())
        yield row(kind=STATS, part=part, numbers=[float(n.sum()), float((n > 0).sum()), float(c.sum()), float(t.sum()), float(mass.sum())])
        for kind, x, y, m in histogram(c[c > 0], t[c > 0], np.zeros(0), np.zeros(0)):
            yield row(kind=HISTOGRAM, part=part, numbers=[kind, x, y, m])

    for batch in source:
        for r in rows_of(batch):
            if r["part"] != part:
                yield from told()
                part, asked, later = r["part"], [], {}
            if r["kind"] == ASK:
                asked.append((r["bucket"], unpacked(r["words_short"], r["words"]), np.frombuffer(r["counts"], np.int64), np.frombuffer(r["runs"], np.uint32).astype(np.int64), np.frombuffer(r["extra"], np.float32)))
            else:
                later[r["bucket"]] = np.frombuffer(r["runs"], np.uint32).astype(np.int64)
    yield from told()


class Room:
    """The restaurants of one bucket, and their Gibbs steps; ``p`` holds the parameters of both levels and the parent's totals."""

    def __init__(self, state: dict, p: dict) -> None:
        self.contexts, self.words, self.u, self.w, self.c = read_pairs(state, np.int32)
        self.p = p
        self.base = np.exp(np.frombuffer(state["extra"], np.float32).astype(np.float64))
        self.customers = np.bincount(self.u, weights=self.c, minlength=len(self.contexts))
        self.dishes = np.bincount(self.u, minlength=len(self.contexts)).astype(np.float64)
        self.tables = self.dishes
        self.t = np.ones(len(self.c), np.int32)
        self.mass, self.n, self.many = [], [], None

    def hear(self, r: dict) -> None:
        self.mass.append(np.frombuffer(r["runs"], np.float64).copy())  # not views, which would hold the batch
        self.n.append(np.frombuffer(r["counts"], np.int64).copy())

    def parent(self) -> np.ndarray:
        """P(w) of all words of the bucket."""
        p = self.p
        mass = np.concatenate(self.mass) if self.mass else np.zeros(len(self.words))
        return (mass + p["rest"] * self.base) / (p["weight"] + p["rest"])

    def sweeps(self, steps: int, keep: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        """Over the last ``keep`` of the steps, the mean of what a pair's own customers and what its parent weigh."""
        d, a = self.p["d"], self.p["a"]
        table, rest = stirling_table(d), np.zeros(len(self.contexts))
        some = np.flatnonzero(self.c > 1)  # a lone customer has a table of its own
        u, c, t = self.u[some], self.c[some].astype(np.int64), self.t[some].astype(np.int64)
        log_parent, mean = np.log(self.parent())[self.w[some]], np.zeros(len(some))
        for k in range(steps):
            t = sweep(u, c, t, self.tables, log_parent, d, a, table, rng)
            self.tables = self.dishes + np.bincount(u, weights=t - 1, minlength=len(self.contexts))
            if k >= steps - keep:
                mean += t / keep
                rest += (a + d * self.tables) / (a + self.customers) / keep
        self.t[some] = t
        del u, c, log_parent
        own = np.ones(len(self.c))
        own[some] = mean
        own *= -d
        own += self.c
        own /= (a + self.customers)[self.u]
        return own, rest


def seated(source: Iterator[pa.RecordBatch], buckets: int, p: dict, steps: int, seed: int) -> Iterator[tuple]:
    """A few Gibbs steps of each bucket: its words' tables for the parent, and the histograms that the parameters' draw needs."""
    room, bucket = None, None

    def told() -> Iterator[tuple]:
        if room is None:
            return
        room.sweeps(steps, 1, np.random.default_rng([seed, 1, bucket]))
        yield from by_word(room.words, buckets, bucket, TABLES, runs=np.bincount(room.w, weights=room.t, minlength=len(room.words)).astype(np.uint32))
        full = room.customers > 0
        for kind, x, y, m in histogram(room.c, room.t, room.customers[full], room.tables[full]):
            yield row(kind=HISTOGRAM, bucket=bucket, numbers=[kind, x, y, m])

    for batch in source:
        for r in rows_of(batch):
            if r["kind"] == STATE:
                yield from told()
                room, bucket = Room(r, p), r["bucket"]
            else:
                room.hear(r)
    yield from told()


def asked_scores(source: Iterator[pa.RecordBatch], buckets: int) -> Iterator[tuple]:
    """Runs of documents, and for each bucket the pairs that they have there. A run's number is its task's and its own."""
    from pyspark import TaskContext

    run = TaskContext.get().partitionId() << 24
    held, docs, amount = [], [], 0

    def out() -> Iterator[tuple]:
        ids, out_of, sizes = (np.concatenate(x) for x in zip(*docs))
        yield row(kind=DOCS, bucket=run % buckets, part=run, contexts=ids.tobytes(), counts=out_of.tobytes(), runs=sizes.tobytes())
        for blob in pair_blobs(held, buckets, True):
            yield row(kind=PAIRS, part=run, **blob)

    for batch in slices(source):
        s = Spelled(batch.column(1))
        before = sum(len(d[0]) for d in docs)
        held.append((s.context == START, s.dish, s.base, np.repeat(np.arange(before, before + batch.num_rows, dtype=np.uint32), s.n_tokens)))
        ids = np.array([NO_ID if x is None else x for x in batch.column(0).to_pylist()], np.int64)
        docs.append((ids, np.array(batch.column(2).to_pylist(), np.uint8), s.n_tokens.astype(np.int64)))
        amount += len(s.dish)
        if amount >= HELD:
            yield from out()
            held, docs, amount, run = [], [], 0, run + 1
    if docs:
        yield from out()


def partial_scores(source: Iterator[pa.RecordBatch], p: dict, steps: int, keep: int, seed: int) -> Iterator[tuple]:
    """For each run of documents, what this bucket's pairs add to their scores."""
    room, bucket, own, rest, parent, n, key = None, None, None, None, None, None, None
    for batch in source:
        for r in rows_of(batch):
            if r["kind"] == STATE:
                room, bucket, own = Room(r, p), r["bucket"], None
            elif r["kind"] == TELL:
                room.hear(r)
            elif r["kind"] == DOCS:
                yield row(**{k: (v.to_pybytes() if isinstance(v, pa.Buffer) else v) for k, v in r.items()})
            else:
                if own is None:
                    own, rest = room.sweeps(steps, keep, np.random.default_rng([seed, 2, bucket]))
                    parent, n, key = room.parent(), np.concatenate(room.n) if room.n else np.zeros(len(room.words), np.int64), room.u.astype(np.int64)
                    key <<= 32
                    key |= room.w
                    room.u = room.w = room.c = room.t = room.mass = room.n = None  # the answers need them no more
                contexts, words, cu, cw, times = read_pairs(r)
                u = np.minimum(np.searchsorted(room.contexts, contexts), len(room.contexts) - 1)  # every context and word asked for is told
                w = np.searchsorted(room.words, words)
                pair = u[cu] << 32 | w[cw]
                at = np.minimum(np.searchsorted(key, pair), max(0, len(key) - 1))
                seen = key[at] == pair if len(key) else np.zeros(len(pair), bool)
                back = np.where(room.customers[u] > 0, rest[u], 1.0)
                prob = np.where(seen, own[at] if len(key) else 0.0, 0.0) + back[cu] * parent[w][cw]
                count = n[w][cw]
                base = np.log10((count + 1) / (p["tokens"] + p["types"] + 1))
                raw = r["extra"]
                doc = np.frombuffer(raw, np.uint16 if len(raw) == 2 * int(times.sum()) else np.uint32)
                docs, place = np.unique(doc, return_inverse=True)
                total = lambda x: np.bincount(place, weights=np.repeat(x, times), minlength=len(docs))
                yield row(kind=PART, bucket=bucket, part=r["part"], contexts=docs.tobytes(), short=docs.dtype == np.uint16, runs=total(np.log10(prob)).tobytes(), counts=total(base).tobytes(), extra=total(count > 0).astype(np.uint32).tobytes())


def summed(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of each run of documents, from its list and all parts (which come one after another, the list first)."""
    ids = None

    def whole() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64(), mask=ids == NO_ID), pa.array(out_of, pa.bool_()), pa.array(sizes, pa.int64()), pa.array(known, pa.int64()), pa.array(base), pa.array(score)], schema=OUT)

    for batch in source:
        for r in rows_of(batch):
            if r["kind"] == DOCS:
                if ids is not None:
                    yield whole()
                ids, out_of, sizes = np.frombuffer(r["contexts"], np.int64), np.frombuffer(r["counts"], np.uint8).astype(bool), np.frombuffer(r["runs"], np.int64)
                known, base, score = np.zeros(len(ids), np.int64), np.zeros(len(ids)), np.zeros(len(ids))
            else:
                at = np.frombuffer(r["contexts"], np.uint16 if r["short"] else np.uint32)
                score[at] += np.frombuffer(r["runs"], np.float64)
                base[at] += np.frombuffer(r["counts"], np.float64)
                known[at] += np.frombuffer(r["extra"], np.uint32)
    if ids is not None:
        yield whole()


def score_documents(docs: DataFrame, sweeps: int = 2, steps: int = 2, keep: int = 3, seed: int = 42, megabytes: int = 24) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row.

    ``sweeps`` times the contexts make ``steps`` Gibbs steps each and the parent one; then the contexts make two more and
    ``keep`` over which probabilities are averaged. A bucket has the contexts of about so many megabytes of input.
    """
    rows = as_input(docs).withColumn("held_out", crc_remainder("doc_id", FOLDS) == HELD_OUT)
    buckets, rng = buckets_for(docs, mb=megabytes, least=6), np.random.default_rng(seed)
    run = lambda df, f, *args: df.mapInArrow(lambda s: batches(f(s, *args), ROW, size=64), ROW_SQL)
    dealt = lambda df, key, *order: df.repartitionById(buckets, F.col(key).cast("int")).sortWithinPartitions(key, *order)
    kind = lambda df, *names: df.where(F.col("kind").isin(*names)).select(*ROW.names)
    numbers = lambda df, name: [r["numbers"] for r in kind(df, name).select("numbers").collect()]  # noqa: E731  one row a task, or a bounded histogram

    held = staged(run(dealt(run(rows, training_pairs, buckets), "bucket"), gathered, buckets), "restaurants", "kind")
    found = numbers(held, STATS)
    once, twice = (sum(x) for x in zip(*found)) if found else (0, 0)
    d = float(np.clip(once / (once + 2 * twice), 0.05, 0.95)) if once else 0.5
    p = {"d": d, "a": 1.0, "d0": 0.5, "a0": 1.0, "tables": 0.0}
    told, tables = None, None
    for k in range(sweeps + 1):
        asked = kind(held, ASK) if tables is None else kind(held, ASK).unionByName(kind(tables, TABLES))
        if tables is not None:  # the parent's tables of the sweep before are where its draw sets out from
            p["d0"], p["a0"] = draw_parameters([tuple(x) for x in numbers(told, HISTOGRAM)] + [(1, p["customers"], p["tables"], 1)], rng)
            p["d"], p["a"] = draw_parameters(merged_histogram(kind(tables, HISTOGRAM)), rng)
        before, told = told, staged(run(dealt(asked, "part", F.col("kind") != ASK), parent_rows, p["d0"], p["a0"], p["tables"], k > 0, k == sweeps, seed + k), "parent", "kind")
        sums = numbers(told, STATS)
        p["tokens"], p["types"], p["customers"], p["tables"], p["weight"] = (sum(x) for x in zip(*sums)) if sums else (0.0,) * 5
        p["rest"] = p["a0"] + p["d0"] * p["tables"]  # of what the base keeps
        if k < sweeps:
            p["rest"] = float(rng.gamma(p["rest"]))
        for old in (before, tables):
            if old is not None:
                dropped(old)
        if k < sweeps:
            both = kind(held, STATE).unionByName(kind(told, TELL))
            tables = staged(run(dealt(both, "bucket", "kind", "part"), seated, buckets, dict(p), steps, seed + k), "tables", "kind")
    dropped(held, f"kind={ASK}")
    parts = kind(held, STATE).unionByName(kind(told, TELL)).unionByName(run(rows, asked_scores, buckets))
    scored = run(dealt(parts, "bucket", "kind", "part"), partial_scores, dict(p), 2 + keep, keep, seed)
    summed_up = scored.repartition(buckets, "part").sortWithinPartitions("part", "kind").mapInArrow(summed, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return summed_up.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(int(p["tokens"])).cast("long").alias("train_tokens"), "base_score", "score")


def merged_histogram(rows: DataFrame) -> list[tuple]:
    """The tasks' histograms summed: as many rows as there are steps of 2 % in customers and tables."""
    x = [F.col("numbers")[k].alias(f"x{k}") for k in range(4)]
    return [tuple(r) for r in rows.select(*x).groupBy("x0", "x1", "x2").agg(F.sum("x3").alias("n")).collect()]


def perplexity(scored: DataFrame) -> DataFrame:
    """Perplexity of the model and of the base, by held_out: 10 to the mean negative log10 per token."""
    ten = lambda x: F.pow(F.lit(10.0), -F.sum(x) / F.sum("n_tokens"))
    return scored.groupBy("held_out").agg(F.sum("n_tokens").alias("n_tokens"), ten("score").alias("perplexity"), ten("base_score").alias("base_perplexity"))
