"""Training in arrays against training one word at a time."""

import random

import numpy as np

from charprobe.operators import corpus
from charprobe.operators import tokenize as T
from charprobe.operators import training


def some(rng: random.Random, letters: str) -> list[tuple[str, int]]:
    words = {"".join(rng.choice(letters) for _ in range(rng.randint(1, 9))): rng.randint(1, 5) for _ in range(rng.choice((3, 12, 60)))}
    return sorted(words.items())


def chunks(counts: list[tuple[str, int]], parts: int, marked: bool) -> list[training.Chunk]:
    return [training.Chunk([w for w, _ in c], np.array([n for _, n in c]), marked) for c in (counts[k::parts] for k in range(parts)) if c]


def test_arrays_learn_what_words_one_at_a_time_teach():
    rng = random.Random(3)
    for _ in range(300):
        counts = some(rng, rng.choice(("ab", "aab", "abcdefgh", "aé ß")))
        same = lambda x: x
        got = training.Trainer(chunks(counts, rng.randint(1, 3), False), chr, same, same, 25).rules(25)
        assert list(got) == T.train_bpe_naive([(list(w), n) for w, n in counts], 25)
        name = lambda c: T.INNER + chr(c - training.INNER_BIT) if c >= training.INNER_BIT else chr(c)
        size = rng.randint(1, 30)
        assert training.PieceTrainer(chunks(counts, 2, True), name, same, same, size).vocabulary(size) == T.train_wordpiece_naive(counts, size)


def test_many_rules_go_between_two_exchanges():
    rng, told = random.Random(4), []
    counts = [("".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(6)), 1) for _ in range(4000)]
    trainer = training.Trainer(chunks(counts, 2, False), chr, lambda x: x, lambda x: told.append(1) or x, 100)
    assert list(trainer.rules(100)) == T.train_bpe([(list(w), n) for w, n in counts], 100)
    assert len(told) < 60


def test_several_tasks_learn_the_same(spark):
    rng = random.Random(5)
    text = " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 7))) for _ in range(400))
    w = corpus.words(spark.createDataFrame([(1, text), (2, None)], "doc_id long, text string"))
    jobs = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("several", "several")
    rules = lambda most: [(r["left"], r["right"]) for r in sorted(T.bpe_merges(w, 6, most).collect(), key=lambda r: r["rank"])]
    assert rules(10) == rules(10_000) == T.train_bpe([(T.spelled_symbols(a, g), n) for a, g, n in T.top_words(w, 10_000)], 6)
    assert len(jobs.getJobIdsForGroup("several")) < 40  # the rounds of 6 rules alone were so many
    assert T.wordpiece_vocab(w, 18, 10) == T.wordpiece_vocab(w, 18)
