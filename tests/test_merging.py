"""Merging in arrays, trained tokenizers over DataFrames, and the small language models."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from charprobe.operators import corpus, lm, measure, mlp, rewrite
from charprobe.operators import tokenize as T
from charprobe.operators.merging import Rules


def test_array_merging_equals_one_word_at_a_time():
    rng = random.Random(1)
    for _ in range(150):
        words = {"".join(rng.choice("abc") for _ in range(rng.randint(1, 9))): rng.randint(1, 5) for _ in range(8)}
        rules = T.train_bpe([(list(w), n) for w, n in sorted(words.items())], 12)
        if rng.random() < 0.5:
            rng.shuffle(rules)
        each = ["".join(rng.choice("aabcdé") for _ in range(rng.randint(0, 12))) for _ in range(30)]
        rank = {p: k for k, p in reversed(list(enumerate(rules)))}
        assert Rules(rules).pieces(each).to_pylist() == [T.merge_word(list(w), rank) for w in each]
        counts = sorted(words.items())
        assert T.train_wordpiece(counts, 14) == T.train_wordpiece_naive(counts, 14)


def some_words(spark):
    return corpus.words(spark.createDataFrame([(1, "low lower lowest new newer newest wide wider widest low low"), (2, None), (3, "slow slower")], "doc_id long, text string"))


def test_unigram_over_a_dataframe(spark):
    w = some_words(spark)
    logp, trail = T.unigram_model(w, 1000, 4)
    assert all(b >= a - 1e-6 for a, b in zip(trail, trail[1:]))
    pruned, _ = T.unigram_model(w, 16, 1, 0.5)
    assert len(pruned) <= 16 and {x for x in pruned if len(x) == 1} == set("lowernstid")
    best = {r["pos"]: r["pieces"] for r in T.unigram_encode(w, pruned).where("doc_id = 1").collect()}
    words = {r["pos"]: r["word"] for r in w.where("doc_id = 1").collect()}
    assert all("".join(best[k]) == x and best[k] == T.Unigram(pruned).best(x) for k, x in words.items())
    sampled = T.unigram_encode(w, pruned, 0.2, 7).collect()
    assert sorted(map(str, sampled)) == sorted(map(str, T.unigram_encode(w, pruned, 0.2, 7).collect())) and all("".join(r["pieces"]) in set(words.values()) | {"slow", "slower"} for r in sampled)


def test_sampled_segmentations_have_their_probabilities():
    model, count, n = T.Unigram({"a": np.log(0.5), "b": np.log(0.3), "ab": np.log(0.2)}), 0, 20_000
    rng = random.Random(0)
    for _ in range(n):
        count += model.sample("ab", 0.5, iter(rng.random, None)) == ["ab"]
    want = 0.2**0.5 / (0.2**0.5 + 0.15**0.5)
    assert abs(count / n - want) < 0.02


def test_wordpiece_over_a_dataframe(spark):
    w = some_words(spark)
    vocab = T.wordpiece_vocab(w, 24)
    assert vocab == T.wordpiece_vocab(w, 24, most_words=2)  # the distributed rounds
    for r in T.wordpiece_encode(w, vocab).join(w, ["doc_id", "pos"]).collect():
        assert r["pieces"] == T.wordpiece(r["word"], set(vocab))
    s = T.piece_stats(T.wordpiece_encode(w, vocab)).first()
    assert s["words"] == 13 and s["unknown_rate"] == 0


def test_trace_as_a_table_function(spark):
    rules = [("b", "c"), (" ", "a"), ("bc", "d")]
    spark.udtf.register("trace_here", T.trace_function(rules))
    got = spark.sql("SELECT step, rank, array_join(symbols, '|') AS s FROM VALUES ('abcd', true) w(word, g), LATERAL trace_here(word, g) ORDER BY step").collect()
    assert [(r["step"], r["rank"], r["s"]) for r in got] == [(1, 0, " |a|bc|d"), (2, 1, " a|bc|d"), (3, 2, " a|bcd")]


@pytest.mark.parametrize("causal", [True, False])
def test_transformer_gradients_by_finite_differences(causal):
    c, rng = lm.LmConfig(causal, 2, 2, 8, 6), np.random.default_rng(0)
    p = {k: x + rng.normal(0, 0.3, x.shape) for k, x in lm.initial(7, c).items()}
    a, b = lm.examples(rng.integers(0, 7, (3, 6)), c, rng, 7)
    _, g = lm.loss_and_gradients(p, a, b, c)
    for k in p:
        flat = p[k].reshape(-1)
        for i in range(0, flat.size, max(1, flat.size // 5)):
            old = flat[i]
            flat[i] = old + 1e-5
            up = lm.loss_and_gradients(p, a, b, c)[0]
            flat[i] = old - 1e-5
            down = lm.loss_and_gradients(p, a, b, c)[0]
            flat[i] = old
            assert abs((up - down) / 2e-5 - g[k].reshape(-1)[i]) < 1e-7, k


def test_causal_model_learns_a_cycle(spark):
    seqs = spark.createDataFrame([(d, [(d + k) % 5 for k in range(200)]) for d in range(8)], "doc_id long, ids array<int>")
    out = lm.train(seqs, 5, lm.LmConfig(width=16, length=16, rate=1e-2, warm_up=5), 3, 30, 2)
    assert [s for s, *_ in out] == [0, 30, 60, 90] and out[-1][1] < 0.5 * out[0][1] and out[-1][2].shape == (5, 16)


def test_ridge_finds_a_line(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(60, 3))
    rows = spark.createDataFrame([(i, int(i % 4 == 0), float(2 * a[0] - a[2] + 1)) for i, a in enumerate(x)], "token_id long, is_test int, t double")
    vectors = spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(x)], "token_id long, vector array<double>")
    got = mlp.ridge(rows, vectors, "t", 1e-6)
    assert got.agg(F.max(F.abs(F.col("target") - F.col("predicted")))).first()[0] < 1e-4


def test_contribution_refuses_what_differs_twice(spark):
    r = spark.createDataFrame([("a", "bpe", "en", "all", 100, 70.0), ("b", "bpe", "other", "all", 100, 60.0), ("c", "word", "other", "all", 100, 55.0)], "experiment string, tokenizer string, corpus string, restriction string, n long, accuracy double")
    pairs = spark.createDataFrame([("x", "corpus", "a", "b"), ("y", "corpus", "a", "c")], "factor string, varies string, control string, treatment string")
    got = {g["factor"]: (g["refused"], g["points"]) for g in measure.contribution(r, pairs).collect()}
    assert got == {"x": (0, 10.0), "y": (1, None)}


def test_fast_scramble_and_subword_substitution(spark):
    src = "She dreams, she is dreaming ß 42 é!"
    docs = spark.createDataFrame([(1, src), (2, None), (3, "")], "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in rewrite.scrambled_documents(docs).collect()}
    assert got[2] == got[3] == "" and len(got[1]) == len(src)
    for a, b in zip(src, got[1]):
        assert (a.isascii() and a.isalpha() and b.isascii() and b.isalpha() and a.isupper() == b.isupper()) or a == b
    seen = "".join(r["text"] for r in rewrite.scrambled_documents(spark.createDataFrame([(i, "a" * 500) for i in range(20)], "doc_id long, text string")).collect())
    assert set(seen) == set("abcdefghijklmnopqrstuvwxyz") and max(map(seen.count, set(seen))) < 2 * min(map(seen.count, set(seen)))
    w = some_words(spark)
    rows = T.with_pieces(w, T.bpe_merges(w, 12))
    table = {r["src"]: r["dst"] for r in rewrite.subword_substitution(rows).collect()}
    assert len(table) == len(set(table.values())) and all(len(a) == len(b) and a.startswith(" ") == b.startswith(" ") for a, b in table.items())
    new = {(r["doc_id"], r["pos"]): r["word"] for r in rewrite.substitute_subwords(rows, rewrite.subword_substitution(rows)).collect()}
    for r in rows.collect():
        assert new[r["doc_id"], r["pos"]] == "".join(table[p] for p in r["pieces"]).strip()


def test_subword_substitution_works_pieces_out_once(spark):
    """Words that come often are cut into pieces once, not at every use of the table."""
    from charprobe.plans import experiments

    w = some_words(spark)
    coded = experiments.coded_words(w, 12)
    table = rewrite.subword_substitution(coded)
    got = rewrite.substitute_subwords(w, table, coded)
    rows = T.with_pieces(w, T.bpe_merges(w, 12))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, rewrite.substitute_subwords(rows, table).collect()))
    assert coded.count() == w.select("word", "has_space").distinct().count()


def test_benchmark_runs_take_time_in_proportion_to_the_text(spark):
    """A text of 40,000 words: its words were cut out anew for every run before."""
    import time

    docs = spark.createDataFrame([(1, " ".join(f"w{k}" for k in range(40_000))), (2, "short"), (3, None)], "doc_id long, text string")
    item = spark.createDataFrame([(7, " ".join(f"w{k}" for k in range(39_980, 40_000)))], "item_id long, text string")
    began = time.time()
    assert sorted(r["doc_id"] for r in corpus.without_benchmark(docs, item).collect()) == [2, 3]
    assert time.time() - began < 40


def test_statistics_of_distinct_words_are_those_of_all(spark):
    w = some_words(spark)
    vocab = T.wordpiece_vocab(w, 12)
    counts = corpus.word_counts(w)
    once = counts.join(T.encoded_distinct(counts, T.WordPieceSplit(vocab)), "word")
    assert T.piece_stats(once, "freq").collect() == T.piece_stats(T.wordpiece_encode(w, vocab)).collect()
