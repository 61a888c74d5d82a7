"""Tokenizers: whitespace words, fixed width, staged merges, byte-pair merges, WordPiece, unigram.

Words never merge across white space, so trained tokenizers learn from word counts and encode distinct words;
the staged tokenizer also encodes occurrences, as scrambled words hardly repeat.
"""

from __future__ import annotations

import heapq
import math
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import LETTERS, fixed_width, order_key
from ..sources import checkpointed
from .merging import Rules
from .training import ONE_TASK, trained
from .vocab import bounded

SPACE = " "  # how a leading space is written as a symbol inside the trainers
UNKNOWN = "<unk>"
#: What a WordPiece unit inside a word starts with (a fixed value).
INNER = "##"


# -- words and fixed chunks --------------------------------------------------------------------------------------


def whitespace_tokens(words: DataFrame, vocab: DataFrame) -> DataFrame:
    """Words as tokens; those outside the vocabulary become <unk>."""
    known = bounded(vocab.select(F.col("surface").alias("known"), F.col("has_space").alias("known_space"), "token_id"))
    met = words.join(known, (F.col("word") == F.col("known")) & (F.col("has_space") == F.col("known_space")), "left")
    return met.select("doc_id", "pos", F.when(F.col("token_id").isNull(), UNKNOWN).otherwise(F.col("word")).alias("surface"), "has_space", F.coalesce("token_id", F.lit(-1)).alias("token_id"))


def fixed_width_tokens(words: DataFrame, width: int = 3) -> DataFrame:
    """Chunks of ``width`` letters, a shorter rest; only the first chunk carries the space. Words of up to two letters stay whole."""
    return words.select("doc_id", F.col("pos").alias("word_pos"), "has_space", F.posexplode(fixed_width(F.col("word"), width)).alias("sub_pos", "surface")).select(
        "doc_id", "word_pos", "sub_pos", "surface", (F.col("has_space") & (F.col("sub_pos") == 0)).alias("has_space"), F.length("surface").alias("n_letters")
    )


def decode(tokens: DataFrame) -> DataFrame:
    """Words again from tokens: the pieces of each word in order."""
    pieces = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("sub_pos", "surface"))), lambda x: x["surface"]), "")
    return tokens.groupBy("doc_id", "word_pos").agg(pieces.alias("word"))


def tokenizer_stats(tokens: DataFrame) -> DataFrame:
    per_word = tokens.groupBy("doc_id", "word_pos").agg(F.count("*").alias("pieces"))
    return per_word.agg(F.count("*").alias("words"), F.sum("pieces").alias("tokens"), F.round(F.sum("pieces") / F.count("*"), 6).alias("tokens_per_word"))


# -- the staged tokenizer ----------------------------------------------------------------------------------------


def staged_vocab(spark: SparkSession, letters: str = LETTERS, longest: int = 3) -> DataFrame:
    """All strings of 1 to ``longest`` letters, with and without a space before them."""
    one = spark.createDataFrame([(c,) for c in letters], "c string").coalesce(1)
    level, out = one.select(F.col("c").alias("surface")), None
    for n in range(1, longest + 1):
        rows = level.withColumn("n_letters", F.lit(n))
        out = rows if out is None else out.unionByName(rows)
        level = level.crossJoin(one).select(F.concat("surface", "c").alias("surface"))  # 26 times a vocabulary of fixed size
    return out.withColumn("has_space", F.explode(F.array(F.lit(True), F.lit(False)))).select("surface", "has_space", "n_letters")


def staged_merges(spark: SparkSession, seed: int = 42, letters: str = LETTERS) -> DataFrame:
    """rank, stage, left, right, merged: strings of odd length (the space counts) split behind the longer part, even ones in the middle.

    Stages go space+1, 2, space+2, 3, space+3 letters; inside a stage the order is a hash of the seed.
    """
    vocab = staged_vocab(spark, letters, 3)
    spelled = F.concat(F.when(F.col("has_space"), SPACE).otherwise(""), "surface")
    size = F.length(spelled)
    stage = F.when(F.col("has_space"), 2 * F.col("n_letters") - 1).otherwise(2 * F.col("n_letters") - 2)
    rows = vocab.where(size >= 2).select(stage.cast("int").alias("stage"), F.substring(spelled, F.lit(1), F.ceil(size / 2).cast("int")).alias("left"), F.substring(spelled, F.ceil(size / 2).cast("int") + 1, size).alias("right"), spelled.alias("merged"))
    order = Window.orderBy("stage", order_key(seed, F.col("stage"), F.col("left"), F.col("right")), "left", "right")  # 36,530 rules whatever the corpus
    return rows.select((F.row_number().over(order) - 1).alias("rank"), "stage", "left", "right", "merged")


# -- merging -----------------------------------------------------------------------------------------------------


def merge_word(symbols: Sequence[str], rank: dict[tuple[str, str], int], trace: list | None = None) -> list[str]:
    """The applicable rule of best rank, all its places from the left, again and again until none applies."""
    out = list(symbols)
    while len(out) > 1:
        best = min((rank.get(p, math.inf) for p in zip(out, out[1:])), default=math.inf)
        if best is math.inf:
            break
        merged, k = [], 0
        while k < len(out):
            if k + 1 < len(out) and rank.get((out[k], out[k + 1])) == best:
                merged.append(out[k] + out[k + 1])
                k += 2
            else:
                merged.append(out[k])
                k += 1
        out = merged
        if trace is not None:
            trace.append((best, list(out)))
    return out


def spelled_symbols(word: str, has_space: bool) -> list[str]:
    return ([SPACE] if has_space else []) + list(word)


def _ordered_rules(merges: DataFrame) -> list[tuple[str, str]]:
    """Rules on the driver: their number is the vocabulary's size and does not grow with the corpus."""
    return [(r["left"], r["right"]) for r in sorted(merges.select("left", "right", "rank").collect(), key=lambda r: r["rank"])]


def with_pieces(words: DataFrame, merges: DataFrame) -> DataFrame:
    """words (with word and has_space) and their pieces in the row, the space before a word being part of its first piece."""
    rules = words.sparkSession.sparkContext.broadcast(_ordered_rules(merges))
    at, space = words.columns.index("word"), words.columns.index("has_space")

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = Rules(rules.value)
        for batch in source:
            spelled = [SPACE + w if g else w for w, g in zip(batch.column(at).to_pylist(), batch.column(space).to_pylist())]
            distinct: dict[str, int] = {}
            number = [distinct.setdefault(w, len(distinct)) for w in spelled]
            yield pa.RecordBatch.from_arrays([*batch.columns, held.pieces(list(distinct)).take(pa.array(number, pa.int64()))], names=[*batch.schema.names, "pieces"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in words.schema)
    return words.mapInArrow(run, f"{fields}, pieces array<string>")


def bpe_encode(words: DataFrame, merges: DataFrame, level: str = "occurrence") -> DataFrame:
    """doc_id, word_pos, sub_pos, surface, has_space, n_letters. ``distinct`` encodes each word once and joins back."""
    if level == "distinct":
        rows = words.join(with_pieces(words.select("word", "has_space").distinct(), merges), ["word", "has_space"])
    else:
        rows = with_pieces(words, merges)
    return exploded(rows.select("doc_id", "pos", "pieces"))


def exploded(rows: DataFrame) -> DataFrame:
    """Tokens of rows (doc_id, pos, pieces)."""
    long = rows.select("doc_id", F.col("pos").alias("word_pos"), F.posexplode("pieces").alias("sub_pos", "piece"))
    spaced = F.col("piece").startswith(SPACE)
    return long.select("doc_id", "word_pos", "sub_pos", F.ltrim("piece").alias("surface"), spaced.alias("has_space"), F.length(F.ltrim("piece")).alias("n_letters"))


def trace_function(rules: Sequence[tuple[str, str]]):
    """A table function: the steps by which one word's symbols merge, (step, rank, symbols). For LATERAL joins on few words."""
    from pyspark.sql.functions import udtf

    rank = {p: k for k, p in reversed(list(enumerate(rules)))}

    class MergeTrace:
        def eval(self, word: str, has_space: bool):
            steps: list = []
            if word:
                merge_word(spelled_symbols(word, has_space), rank, steps)
            for k, (r, symbols) in enumerate(steps):
                yield k + 1, int(r), symbols

    return udtf(MergeTrace, returnType="step int, rank int, symbols array<string>")


class WordCounts:
    """Distinct words as symbols with an index of pairs, for the trainers that run in one task.

    Its memory is that of the distinct words given, so the caller bounds them (min_freq or a top list).
    """

    def __init__(self, counts: Iterable[tuple[Sequence[str], int]], join=lambda a, b: a + b) -> None:
        self.join = join
        self.words = [(list(s), n) for s, n in counts]
        self.pairs: Counter = Counter()
        self.symbols: Counter = Counter()
        self.where: dict[tuple[str, str], set[int]] = defaultdict(set)
        for k, (s, n) in enumerate(self.words):
            for x in s:
                self.symbols[x] += n
            for p in zip(s, s[1:]):
                self.pairs[p] += n
                self.where[p].add(k)

    def fuse(self, pair: tuple[str, str]) -> set[tuple[str, str]]:
        """Fuses a pair in all words from the left; returns the pairs whose counts changed."""
        a, b = pair
        changed: set[tuple[str, str]] = set()
        for k in self.where.pop(pair, set()):
            s, n = self.words[k]
            for p in zip(s, s[1:]):
                self.pairs[p] -= n
                changed.add(p)
            out, i = [], 0
            while i < len(s):
                if i + 1 < len(s) and s[i] == a and s[i + 1] == b:
                    out.append(self.join(a, b))
                    self.symbols[a] -= n
                    self.symbols[b] -= n
                    self.symbols[out[-1]] += n
                    i += 2
                else:
                    out.append(s[i])
                    i += 1
            self.words[k] = (out, n)
            for p in zip(out, out[1:]):
                self.pairs[p] += n
                self.where[p].add(k)
                changed.add(p)
        return changed


def train_bpe(counts: Iterable[tuple[Sequence[str], int]], n_merges: int) -> list[tuple[str, str]]:
    """The most frequent pair, ties by (left, right), fused again and again; a heap hands out the next one."""
    held = WordCounts(counts)
    heap = [(-n, p) for p, n in held.pairs.items()]
    heapq.heapify(heap)
    out: list[tuple[str, str]] = []
    while heap and len(out) < n_merges:
        n, p = heapq.heappop(heap)
        if held.pairs.get(p, 0) != -n or n >= 0:
            continue
        out.append(p)
        for q in held.fuse(p):
            if held.pairs[q] > 0:
                heapq.heappush(heap, (-held.pairs[q], q))
    return out


def train_bpe_naive(counts: Iterable[tuple[Sequence[str], int]], n_merges: int) -> list[tuple[str, str]]:
    """The same by recounting everything each time; for tests."""
    words, out = [(list(s), n) for s, n in counts], []
    for _ in range(n_merges):
        pairs: Counter = Counter()
        for s, n in words:
            for p in zip(s, s[1:]):
                pairs[p] += n
        if not pairs:
            break
        best = min(pairs, key=lambda p: (-pairs[p], p))
        out.append(best)
        words = [(merge_word(s, {best: 0}), n) for s, n in words]
    return out


def joined_piece(a: str, b: str) -> str:
    return a + b.removeprefix(INNER)


def piece_score(n: int, a: int, b: int) -> float:
    """How much more likely a corpus gets by fusing a pair: its count over the product of its units' counts."""
    return n / (a * b)


def inner_units(word: str) -> list[str]:
    return [word[0], *(INNER + c for c in word[1:])]


def train_wordpiece(counts: Iterable[tuple[str, int]], size: int) -> list[str]:
    """Grows by the pair of the greatest score, ties by count and by the pair; inner units start with INNER."""
    held = WordCounts(((inner_units(w), n) for w, n in counts if w), joined_piece)
    vocab = sorted(held.symbols)
    known = set(vocab)
    while len(vocab) < size:
        best, top = None, None
        for p, n in held.pairs.items():
            if n > 0:
                key = (-piece_score(n, held.symbols[p[0]], held.symbols[p[1]]), -n, p)
                if top is None or key < top:
                    best, top = p, key
        if best is None:
            break
        new = joined_piece(*best)
        if new not in known:
            known.add(new)
            vocab.append(new)
        held.fuse(best)
    return vocab


def train_wordpiece_naive(counts: Iterable[tuple[str, int]], size: int) -> list[str]:
    """The same by recounting everything each time; for tests."""
    words = [(inner_units(w), n) for w, n in counts if w]
    vocab = sorted({x for s, _ in words for x in s})
    while len(vocab) < size:
        pairs, units = Counter(), Counter()
        for s, n in words:
            for x in s:
                units[x] += n
            for p in zip(s, s[1:]):
                pairs[p] += n
        if not pairs:
            break
        best = min(pairs, key=lambda p: (-piece_score(pairs[p], units[p[0]], units[p[1]]), -pairs[p], p))
        if joined_piece(*best) not in vocab:
            vocab.append(joined_piece(*best))
        fused = []
        for s, n in words:
            out, k = [], 0
            while k < len(s):
                both = k + 1 < len(s) and (s[k], s[k + 1]) == best
                out.append(joined_piece(*best) if both else s[k])
                k += 2 if both else 1
            fused.append((out, n))
        words = fused
    return vocab


def wordpiece(word: str, vocab: set[str]) -> list[str]:
    """Longest known prefix first; a word that cannot be spelled out is <unk>."""
    out, at = [], 0
    while at < len(word):
        lead = INNER if at else ""
        end = next((e for e in range(len(word), at, -1) if lead + word[at:e] in vocab), None)
        if end is None:
            return [UNKNOWN]
        out.append(lead + word[at:end])
        at = end
    return out


class Unigram:
    """A unigram language model of pieces: EM over all segmentations, pruning, best and sampled segmentations."""

    def __init__(self, pieces: dict[str, float]) -> None:
        self.logp = dict(pieces)
        self.longest = max(map(len, pieces), default=1)

    def _edges(self, word: str, end: int) -> Iterator[tuple[int, float]]:
        for start in range(max(0, end - self.longest), end):
            p = self.logp.get(word[start:end])
            if p is not None:
                yield start, p

    def forward(self, word: str, alpha: float = 1.0) -> list[float]:
        f = [0.0] + [-math.inf] * len(word)
        for e in range(1, len(word) + 1):
            terms = [f[s] + alpha * p for s, p in self._edges(word, e)]
            top = max(terms, default=-math.inf)
            f[e] = top if top == -math.inf else top + math.log(sum(math.exp(t - top) for t in terms))
        return f

    def expected(self, word: str) -> tuple[dict[str, float], float]:
        """Expected count of each piece over all segmentations, and the word's log-likelihood."""
        n, f = len(word), self.forward(word)
        b = [-math.inf] * n + [0.0]
        for s in range(n - 1, -1, -1):
            terms = [self.logp[word[s:e]] + b[e] for e in range(s + 1, min(n, s + self.longest) + 1) if word[s:e] in self.logp]
            top = max(terms, default=-math.inf)
            b[s] = top if top == -math.inf else top + math.log(sum(math.exp(t - top) for t in terms))
        out: dict[str, float] = defaultdict(float)
        if f[n] > -math.inf:
            for e in range(1, n + 1):
                for s, p in self._edges(word, e):
                    if f[s] > -math.inf and b[e] > -math.inf:
                        out[word[s:e]] += math.exp(f[s] + p + b[e] - f[n])
        return out, f[n]

    def best(self, word: str) -> list[str]:
        score, back = [0.0] + [-math.inf] * len(word), [0] * (len(word) + 1)
        for e in range(1, len(word) + 1):
            for s, p in self._edges(word, e):
                if score[s] + p > score[e]:
                    score[e], back[e] = score[s] + p, s
        if score[-1] == -math.inf and word:
            return [UNKNOWN]
        out, e = [], len(word)
        while e:
            out.append(word[back[e] : e])
            e = back[e]
        return out[::-1]

    def sample(self, word: str, alpha: float, draws: Iterator[float]) -> list[str]:
        """A segmentation with probability proportional to its own to the power alpha, from the end backwards."""
        f, out, e = self.forward(word, alpha), [], len(word)
        if word and f[-1] == -math.inf:
            return [UNKNOWN]
        while e:
            u, total, start = next(draws), 0.0, None
            for s, p in self._edges(word, e):
                if f[s] > -math.inf:
                    total += math.exp(f[s] + alpha * p - f[e])
                    start = s
                    if total >= u:
                        break
            out.append(word[start:e])
            e = start
        return out[::-1]


def train_unigram(counts: Sequence[tuple[str, int]], size: int, n_iter: int = 2, shrink: float = 0.75, longest: int = 6) -> tuple[Unigram, list[float]]:
    """Seeds with frequent substrings, then rounds of EM and pruning of what costs the likelihood least; single letters stay."""
    subs: Counter = Counter()
    for w, n in counts:
        for s in range(len(w)):
            for e in range(s + 1, min(len(w), s + longest) + 1):
                subs[w[s:e]] += n
    seed = {x: n for x, n in subs.items() if len(x) == 1} | dict(sorted(((x, n) for x, n in subs.items() if len(x) > 1), key=lambda r: (-r[1] * len(r[0]), r[0]))[: 8 * size])
    total = sum(seed.values())
    model, trail = Unigram({x: math.log(n / total) for x, n in seed.items()}), []
    while True:
        for _ in range(n_iter):
            held: dict[str, float] = defaultdict(float)
            likelihood = 0.0
            for w, n in counts:
                e, ll = model.expected(w)
                likelihood += n * ll if ll > -math.inf else 0.0
                for x, v in e.items():
                    held[x] += n * v
            trail.append(likelihood)
            total = sum(held.values()) or 1.0
            model = Unigram({x: math.log(max(held.get(x, 0.0), 1e-9) / total) for x in model.logp if len(x) == 1 or held.get(x, 0.0) > 1e-9})
        if len(model.logp) <= size:
            return model, trail
        loss = {}
        for x, lp in model.logp.items():
            if len(x) > 1:
                rest = Unigram({k: v for k, v in model.logp.items() if k != x and len(k) <= len(x)} if len(model.logp) <= 64 else {k: model.logp[k] for s in range(len(x)) for k in {x[s:e] for e in range(s + 1, len(x) + 1)} if k != x and k in model.logp})
                loss[x] = held.get(x, 0.0) * (lp - rest.forward(x)[-1])
        keep = max(size, int(shrink * len(model.logp)))
        gone = sorted(loss, key=lambda x: (loss[x], x))[: len(model.logp) - keep]
        if not gone:
            return model, trail
        model = Unigram({x: p for x, p in model.logp.items() if x not in set(gone)})


def top_words(words: DataFrame, most: int) -> list[tuple[str, bool, int]]:
    """The most frequent words with counts, bounded by ``most``."""
    counted = words.groupBy("word", "has_space").agg(F.count("*").alias("n"))
    return [tuple(r) for r in counted.orderBy(F.desc("n"), "word", "has_space").limit(most).collect()]


def bpe_merges(words: DataFrame, n_merges: int, most_words: int = ONE_TASK) -> DataFrame:
    """rank, left, right, merged, learnt from the counts of all distinct words: up to ``most_words`` of them in one task, more in several."""
    spelled = F.concat(F.when(F.col("has_space"), SPACE).otherwise(""), "word")
    rules = trained(words.groupBy("word", "has_space").agg(F.count("*").alias("n")).select(spelled.alias("word"), "n"), n_merges, one_task=most_words)
    return words.sparkSession.createDataFrame([(k, a, b, a + b) for k, (a, b) in enumerate(rules)], "rank int, left string, right string, merged string")


def pair_counts(counts: DataFrame) -> DataFrame:
    """Weighted counts of adjacent symbols from (symbols array, freq): one distributed round of merge training."""
    near = F.zip_with(F.slice("symbols", F.lit(1), F.size("symbols") - 1), F.slice("symbols", F.lit(2), F.size("symbols")), lambda a, b: F.struct(a.alias("left"), b.alias("right")))
    return counts.where(F.size("symbols") > 1).select(F.explode(near).alias("p"), "freq").groupBy("p.left", "p.right").agg(F.sum("freq").alias("n"))


def fuse_symbols(counts: DataFrame, left: str, right: str, new: str | None = None) -> DataFrame:
    """(symbols, freq) with a pair fused from the left, inside the row."""
    empty = F.array().cast("array<string>")
    last = lambda a: F.element_at(a, -1)
    # The last symbol waits under a mark until it is known whether the next one fuses with it.
    fused = F.aggregate(
        "symbols",
        F.struct(empty.alias("done"), F.lit(False).alias("open")),
        lambda acc, x: F.when(
            acc["open"] & (x == right),
            F.struct(F.concat(F.slice(acc["done"], F.lit(1), F.size(acc["done"]) - 1), F.array(F.lit(left + right if new is None else new))).alias("done"), F.lit(False).alias("open")),
        ).otherwise(F.struct(F.concat(acc["done"], F.array(x)).alias("done"), (x == left).alias("open"))),
        lambda acc: acc["done"],
    )
    return counts.withColumn("symbols", fused)


def bpe_train_distributed(counts: DataFrame, n_merges: int, every: int = 10) -> list[tuple[str, str, int]]:
    """Merge training by DataFrame rounds, for word tables that no single task should hold."""
    rules, held = [], counts
    for k in range(n_merges):
        best = pair_counts(held).orderBy(F.desc("n"), "left", "right").first()
        if best is None:
            break
        rules.append((best["left"], best["right"], best["n"]))
        held = fuse_symbols(held, best["left"], best["right"])
        if (k + 1) % every == 0:
            held = checkpointed(held)
    return rules


# -- WordPiece and unigram over DataFrames -----------------------------------------------------------------------


def plain_counts(words: DataFrame) -> DataFrame:
    """word, n: occurrences of each distinct word, spaced or not."""
    return words.groupBy("word").agg(F.count("*").alias("n"))


def wordpiece_vocab(words: DataFrame, size: int, most_words: int = ONE_TASK) -> list[str]:
    """A WordPiece vocabulary from all distinct words: up to ``most_words`` of them in one task, more in several."""
    return [x for x, _ in trained(plain_counts(words), size, True, most_words)]


def encoded_distinct(words: DataFrame, split, kind: str = "pieces") -> DataFrame:
    """word and pieces of every distinct word; ``split`` is a picklable function of a word."""
    held = words.sparkSession.sparkContext.broadcast(split)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in source:
            pieces = [held.value(w) for w in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(pieces, pa.list_(pa.string()))], names=["word", kind])

    return words.select("word").distinct().mapInArrow(run, f"word string, {kind} array<string>")


def encoded_words(words: DataFrame, split, kind: str = "pieces") -> DataFrame:
    """doc_id, pos, has_space and pieces of every word; ``split`` runs once for each distinct word."""
    return words.join(encoded_distinct(words, split, kind), "word").select("doc_id", "pos", "has_space", kind)


class WordPieceSplit:
    def __init__(self, vocab: Iterable[str]) -> None:
        self.vocab = set(vocab)

    def __call__(self, word: str) -> list[str]:
        return wordpiece(word, self.vocab)


class UnigramSplit:
    """The best segmentation, or with ``alpha`` a sampled one whose draws hang on the seed and the word."""

    def __init__(self, logp: dict[str, float], alpha: float | None = None, seed: int = 42) -> None:
        self.model, self.alpha, self.seed = Unigram(logp), alpha, seed

    def __call__(self, word: str) -> list[str]:
        if self.alpha is None:
            return self.model.best(word)
        import random

        draw = random.Random(f"{self.seed}|{word}")
        return self.model.sample(word, self.alpha, iter(draw.random, None))


def wordpiece_encode(words: DataFrame, vocab: Iterable[str]) -> DataFrame:
    return encoded_words(words, WordPieceSplit(vocab))


def unigram_encode(words: DataFrame, logp: dict[str, float], alpha: float | None = None, seed: int = 42) -> DataFrame:
    return encoded_words(words, UnigramSplit(logp, alpha, seed))


def unigram_model(words: DataFrame, size: int, n_iter: int = 2, shrink: float = 0.75, longest: int = 8, seeds: int = 8) -> tuple[dict[str, float], list[float]]:
    """Pieces with log-probabilities, and the likelihood after each pass: EM over all segmentations of all distinct words.

    The expected counts are summed where the words are; the driver holds the pieces alone, ``seeds`` times ``size`` at first.
    """
    spark = words.sparkSession
    counts = plain_counts(words).persist()
    try:
        at = F.sequence(F.lit(1), F.length("word"))
        spans = F.flatten(F.transform(at, lambda i: F.transform(F.sequence(i, F.least(i + longest - 1, F.length("word"))), lambda j: F.substring("word", i, j - i + 1))))
        subs = counts.where(F.length("word") > 0).select(F.explode(spans).alias("x"), "n").groupBy("x").agg(F.sum("n").alias("n"))
        single = {r["x"]: r["n"] for r in subs.where(F.length("x") == 1).collect()}
        more = {r["x"]: r["n"] for r in subs.where(F.length("x") > 1).orderBy(F.desc(F.col("n") * F.length("x")), "x").limit(seeds * size).collect()}
        total = sum(single.values()) + sum(more.values())
        logp, trail = {x: math.log(n / total) for x, n in (single | more).items()}, []
        while logp:
            for _ in range(n_iter):
                shared = spark.sparkContext.broadcast(logp)

                def expect(source: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
                    model, held, likelihood = Unigram(shared.value), defaultdict(float), 0.0
                    for batch in source:
                        for w, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                            e, ll = model.expected(w)
                            if ll > -math.inf:
                                likelihood += n * ll
                                for x, v in e.items():
                                    held[x] += n * v
                    yield pa.RecordBatch.from_arrays([pa.array(["", *held], pa.string()), pa.array([likelihood, *held.values()], pa.float64())], names=["x", "v"])

                got = {r["x"]: r["v"] for r in counts.mapInArrow(expect, "x string, v double").groupBy("x").agg(F.sum("v").alias("v")).collect()}  # as many as there are pieces
                shared.unpersist()
                trail.append(got.pop("", 0.0))
                total = sum(got.values()) or 1.0
                logp = {x: math.log(max(got.get(x, 0.0), 1e-9) / total) for x in logp if len(x) == 1 or got.get(x, 0.0) > 1e-9}
            if len(logp) <= size:
                break
            loss = {x: got.get(x, 0.0) * (p - Unigram({x[a:b]: logp[x[a:b]] for a in range(len(x)) for b in range(a + 1, len(x) + 1) if x[a:b] != x and x[a:b] in logp}).forward(x)[-1]) for x, p in logp.items() if len(x) > 1}
            gone = sorted(loss, key=lambda x: (loss[x], x))[: len(logp) - max(size, int(shrink * len(logp)))]
            if not gone:
                break
            logp = {x: p for x, p in logp.items() if x not in set(gone)}
        return logp, trail
    finally:
        counts.unpersist()


def piece_stats(encoded: DataFrame, times: str | None = None) -> DataFrame:
    """Of encoded words: words, tokens, tokens a word, share of unknown words, and distinct tokens. ``times``: the column that
    says how many words a row stands for."""
    rows = encoded.select("pieces", (F.lit(1) if times is None else F.col(times)).cast("long").alias("n"))
    per = rows.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("words"), F.sum(F.col("n") * F.size("pieces")).alias("tokens"), F.sum(F.when(F.element_at("pieces", 1) == UNKNOWN, F.col("n")).otherwise(0)).alias("unknown"))
    types = rows.select(F.explode("pieces").alias("piece")).agg(F.count_distinct("piece").alias("types"))
    return per.crossJoin(types).select("words", "tokens", F.round(F.col("tokens") / F.col("words"), 6).alias("tokens_per_word"), F.round(F.col("unknown") / F.col("words"), 6).alias("unknown_rate"), "types")  # one row each
