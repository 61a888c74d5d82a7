"""Training of merge rules on all distinct words in arrays: in one task, or in several that hold a share of the words each.

Words lie one behind another as symbol numbers, 0 between them. Fusing a pair (a, b) changes the counts of the pairs that
end in a, begin with b, or hold the new symbol, so what a task tells the others about a fusion is two counts by symbol.
Every task keeps the same table of pair counts and makes the same choices. Several tasks are one barrier stage, and an
exchange takes about a second whatever its size; so a run of rules is fused between two exchanges wherever it is certain
that taking them one at a time would have chosen the same.
"""

from __future__ import annotations

import base64
import heapq
import zlib
from collections import defaultdict
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Distinct words that one task works on alone (some 20 bytes each); more are dealt to all cores.
ONE_TASK = 4_000_000
#: Letters of words that lie in one array: a scan stays in the cache.
CHUNK = 1 << 20
#: Added to the code of a letter that is not the first of its word, where these are symbols of their own.
INNER_BIT = 1 << 21


class Chunk:
    """Some words, sorted by how often they occur, so that weights are runs of places."""

    def __init__(self, words: list[str], n: np.ndarray, marked: bool) -> None:
        order = np.argsort(n, kind="stable")
        size = np.fromiter(map(len, words), np.int64, len(words))[order]
        codes = np.frombuffer("".join([words[k] for k in order.tolist()]).encode("utf-32-le"), np.uint32).copy()
        first = np.cumsum(size) - size
        if marked:
            inner = np.ones(len(codes), bool)
            inner[first[size > 0]] = False
            codes[inner] += INNER_BIT
        self.symbols = np.zeros(len(codes) + len(words) + 1, np.uint32)
        self.symbols[np.arange(len(codes)) + np.repeat(np.arange(len(words)), size) + 1] = codes
        self.weight, at = np.unique(n[order], return_index=True)
        self.bound = np.append((first + np.arange(len(words)))[at], len(self.symbols))

    def number(self, alphabet: np.ndarray, kind: type) -> None:
        """Codes become numbers from 1 in the order of the alphabet."""
        letters = self.symbols > 0
        out = np.zeros(len(self.symbols), kind)
        out[letters] = np.searchsorted(alphabet, self.symbols[letters]) + 1
        self.symbols = out

    def weights(self, places: np.ndarray) -> np.ndarray:
        return np.repeat(self.weight, np.diff(np.searchsorted(places, self.bound)))

    def fuse(self, a: int, b: int, new: int, left: np.ndarray, right: np.ndarray) -> tuple[int, int]:
        """Fuses a pair everywhere from the left. Adds how often each symbol stood before a (not inside a run of the pair) and
        behind b; returns how often the pair followed itself, and how often it was fused."""
        s = self.symbols
        hit = np.flatnonzero((s[:-1] == a) & (s[1:] == b))
        if not len(hit):
            return 0, 0
        if a == b:  # in a run of equal symbols the places overlap: every other one counts
            follows = np.concatenate(([False], np.diff(hit) == 1))
            start = np.maximum.accumulate(np.where(follows, 0, np.arange(len(hit))))
            hit = hit[(np.arange(len(hit)) - start) % 2 == 0]
        w = self.weights(hit)
        joined = hit[1:] == hit[:-1] + 2
        alone = np.concatenate(([True], ~joined))
        right += np.bincount(s[hit + 2], weights=w, minlength=len(right)).astype(np.int64)
        left += np.bincount(s[hit[alone] - 1], weights=w[alone], minlength=len(left)).astype(np.int64)
        s[hit] = new
        self.symbols = np.delete(s, hit + 1)
        self.bound = self.bound - np.searchsorted(hit + 1, self.bound)
        return int(w[:-1][joined].sum()), int(w.sum())


class Trainer:
    """The table of pair counts, the same in every task, and this task's words. ``told`` adds up arrays over all tasks."""

    def __init__(self, chunks: list[Chunk], named: Callable[[int], str], union: Callable[[np.ndarray], np.ndarray], told: Callable[[np.ndarray], np.ndarray], new_symbols: int) -> None:
        self.chunks, self.told = chunks, told
        codes = [np.unique(c.symbols) for c in chunks]
        alphabet = union(np.unique(np.concatenate(codes)) if codes else np.zeros(0, np.uint32))
        alphabet = alphabet[alphabet > 0]
        self.names = [""] + [named(c) for c in alphabet.tolist()]
        self.of = {x: k for k, x in enumerate(self.names) if k}
        for c in chunks:
            c.number(alphabet, np.int16 if len(self.names) + new_symbols < 1 << 15 else np.int32)
        k = len(self.names)
        singles, pairs = np.zeros(k, np.int64), np.zeros(k * k, np.int64) if k <= 500 else None
        apart: dict[int, int] = defaultdict(int)
        for c in chunks:
            s = c.symbols.astype(np.int64)
            w = c.weights(np.arange(len(s)))
            singles += np.bincount(s, weights=w, minlength=k).astype(np.int64)
            code = s[:-1] * k + s[1:]
            if pairs is not None:
                pairs += np.bincount(code, weights=w[:-1], minlength=k * k).astype(np.int64)
            else:
                found, place = np.unique(code, return_inverse=True)
                for p, n in zip(found.tolist(), np.bincount(place, weights=w[:-1]).astype(np.int64).tolist()):
                    apart[p] += n
        if pairs is None:
            known = union(np.array(sorted(apart), np.int64))
            pairs = told(np.array([apart.get(p, 0) for p in known.tolist()], np.int64))
        else:
            pairs = told(pairs)
            known = np.flatnonzero(pairs)
            pairs = pairs[known]
        self.single = told(singles).tolist()
        self.pairs: dict[tuple[int, int], int] = {(p // k, p % k): n for p, n in zip(known.tolist(), pairs.tolist()) if n and p // k and p % k}
        self.heap = [(-n, (self.names[a], self.names[b]), (a, b)) for (a, b), n in self.pairs.items()]
        heapq.heapify(self.heap)

    def fused(self, batch: list[tuple[int, int]]) -> None:
        """Fuses pairs one after another, in the words and in the table."""
        parts, made = [], []
        for a, b in batch:
            joined = self.joined(self.names[a], self.names[b])
            new = self.of.setdefault(joined, len(self.names))
            if new == len(self.names):
                self.names.append(joined)
                self.single.append(0)
            left, right, ends = np.zeros(len(self.names), np.int64), np.zeros(len(self.names), np.int64), np.zeros(2, np.int64)
            for c in self.chunks:
                ends += c.fuse(a, b, new, left, right)
            parts += [left, right, ends]
            made.append((a, b, new))
        whole, changed = self.told(np.concatenate(parts)), set()

        def add(p: tuple[int, int], n: int) -> None:
            if n:
                self.pairs[p] = self.pairs.get(p, 0) + n
                changed.add(p)

        lo = 0
        for k, (a, b, new) in enumerate(made):
            size = len(parts[3 * k])
            left, right, (runs, times) = whole[lo : lo + size], whole[lo + size : lo + 2 * size], whole[lo + 2 * size : lo + 2 * size + 2].tolist()
            lo += 2 * size + 2
            for x in (np.flatnonzero(left[1:]) + 1).tolist():
                add((x, a), -int(left[x]))
                add((x, new), int(left[x]))
            for y in (np.flatnonzero(right[1:]) + 1).tolist():
                add((b, y), -int(right[y]))
                add((new, y), int(right[y]) - (runs if y == a else 0))
            add((new, new), runs)
            add((a, b), -times)
            self.single[a] -= times
            self.single[b] -= times
            self.single[new] += times
        for p in changed:
            n = self.pairs[p]
            if n > 0:
                heapq.heappush(self.heap, (-n, (self.names[p[0]], self.names[p[1]]), p))
            else:
                del self.pairs[p]

    @staticmethod
    def joined(a: str, b: str) -> str:
        return a + b

    def tied(self) -> list[tuple[int, int]]:
        """Takes the pairs of the greatest count from the heap, in order."""
        out: list[tuple[int, int]] = []
        count = None
        while self.heap and (count is None or self.heap[0][0] == count):
            n, _, p = heapq.heappop(self.heap)
            if self.pairs.get(p, 0) == -n and p not in out[-1:]:
                count = n
                out.append(p)
        return out

    def batch(self, most: int) -> list[tuple[int, int]]:
        """The next rules that can be fused before counts are exchanged.

        A rule neither changes the count of a pair that does not begin with its right or end in its left symbol, nor makes a
        pair more frequent than one of those was. So the most frequent pairs in order are the next rules as long as no two
        meet that way, none meets itself, none makes a symbol that is there, and equal counts are taken together or not at all.
        """
        out: list[tuple[int, int]] = []
        first, last, made = set(), set(), set()
        while len(out) < most:
            group = self.tied()
            good = 0
            for a, b in group:
                new = self.joined(self.names[a], self.names[b])
                if a == b or a in last or b in first or new in self.of or new in made:
                    break
                first.add(a)
                last.add(b)
                made.add(new)
                good += 1
            whole = good == len(group) and len(group) > 0
            take = group[: most - len(out)] if whole else [] if out else group[:1]
            out += take
            for p in group[len(take) :]:
                heapq.heappush(self.heap, (-self.pairs[p], (self.names[p[0]], self.names[p[1]]), p))
            if not whole:
                break
        return out

    def rules(self, n_merges: int) -> Iterator[tuple[str, str]]:
        """The most frequent pair, ties by (left, right), again and again."""
        done = 0
        while done < n_merges and (batch := self.batch(n_merges - done)):
            yield from [(self.names[a], self.names[b]) for a, b in batch]
            done += len(batch)
            if done < n_merges:
                self.fused(batch)


class PieceTrainer(Trainer):
    """Grows by the pair of the greatest score, one at a time."""

    @staticmethod
    def joined(a: str, b: str) -> str:
        from .tokenize import joined_piece

        return joined_piece(a, b)

    def best(self) -> tuple[int, int] | None:
        from .tokenize import piece_score

        if not self.pairs:
            return None
        held = list(self.pairs.items())
        a, b = np.array([p for p, _ in held], np.int64).T
        total = np.array(self.single, np.float64)
        score = np.array([n for _, n in held], np.float64) / (total[a] * total[b])
        near = np.flatnonzero(score >= score.max() * (1 - 1e-9))  # these are compared exactly
        return min((held[k] for k in near.tolist()), key=lambda x: (-piece_score(x[1], self.single[x[0][0]], self.single[x[0][1]]), -x[1], (self.names[x[0][0]], self.names[x[0][1]])))[0]

    def vocabulary(self, size: int) -> list[str]:
        out = sorted(self.names[1:])
        known = set(out)
        while len(out) < size and (best := self.best()):
            new = self.joined(self.names[best[0]], self.names[best[1]])
            if new not in known:
                known.add(new)
                out.append(new)
            self.fused([best])
        return out


def slots(df: DataFrame) -> int:
    """Tasks that can run at the same time."""
    sc = df.sparkSession.sparkContext._jsc.sc()
    return max(1, sc.maxNumConcurrentTasks(sc.resourceProfileManager().defaultResourceProfile()))


def trained(counts: DataFrame, size: int, pieces: bool = False, one_task: int = ONE_TASK) -> list[tuple[str, str]]:
    """Rules (left, right), or with ``pieces`` units (unit, ''), from distinct words and their counts (word string, n long).

    Up to ``one_task`` words go to one task, more to as many as can run at a time. The driver gets what was learnt alone.
    """
    from .tokenize import INNER

    held = counts.select("word", F.col("n").cast("long").alias("n")).persist()
    try:
        tasks = 1 if held.count() <= one_task else slots(held)

        def learn(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            chunks, words, weights, letters = [], [], [], 0
            for batch in source:
                more = batch.column(0).to_pylist()
                words += more
                weights.append(batch.column(1).to_numpy())
                letters += sum(map(len, more))
                if letters >= CHUNK:
                    chunks.append(Chunk(words, np.concatenate(weights), pieces))
                    words, weights, letters = [], [], 0
            if words:
                chunks.append(Chunk(words, np.concatenate(weights), pieces))
            union, told, part = lambda x: x, lambda x: x, 0
            if tasks > 1:
                from pyspark import BarrierTaskContext

                context = BarrierTaskContext.get()
                part = context.partitionId()

                def gathered(x: np.ndarray) -> list[np.ndarray]:
                    got = context.allGather(base64.b64encode(zlib.compress(x.astype(np.int64).tobytes(), 1)).decode())
                    return [np.frombuffer(zlib.decompress(base64.b64decode(g)), np.int64) for g in got]

                union = lambda x: np.unique(np.concatenate(gathered(x))).astype(x.dtype)
                told = lambda x: np.sum(gathered(x), axis=0, dtype=np.int64)
            if pieces:
                name = lambda c: INNER + chr(c - INNER_BIT) if c >= INNER_BIT else chr(c)
                learnt = [(x, "") for x in PieceTrainer(chunks, name, union, told, size).vocabulary(size)]
            else:
                learnt = list(Trainer(chunks, chr, union, told, size).rules(size))
            if part == 0:
                yield pa.RecordBatch.from_arrays([pa.array(range(len(learnt)), pa.int32()), pa.array([a for a, _ in learnt], pa.string()), pa.array([b for _, b in learnt], pa.string())], names=["k", "a", "b"])

        rows = held.repartition(tasks).mapInArrow(learn, "k int, a string, b string", barrier=tasks > 1).collect()  # as many as were asked for
        return [(r["a"], r["b"]) for r in sorted(rows, key=lambda r: r["k"])]
    finally:
        held.unpersist()
