import random

from charprobe.operators import tokenize as T
from charprobe.operators.rewrite import Stemmer


def test_rule_order_decides_the_cut():
    first = {(" ", "a"): 0, ("b", "c"): 1, ("c", "d"): 2, (" a", "b"): 3, ("bc", "d"): 4, (" a", "bc"): 5}
    assert T.merge_word(T.spelled_symbols("abcd", True), first) == [" a", "bcd"]
    swapped = first | {("b", "c"): 2, ("c", "d"): 1}
    assert T.merge_word(T.spelled_symbols("abcd", True), swapped) == [" ab", "cd"]


def test_bpe_training_equals_recounting():
    rng = random.Random(3)
    for _ in range(60):
        words = {"".join(rng.choice("abc") for _ in range(rng.randint(1, 7))): rng.randint(1, 5) for _ in range(rng.randint(1, 8))}
        counts = [(list(w), n) for w, n in sorted(words.items())]
        assert T.train_bpe(counts, 12) == T.train_bpe_naive(counts, 12)


def test_wordpiece_takes_the_longest_prefix():
    v = {"a", "ab", "##c", "##cd", "##d"}
    assert T.wordpiece("abcd", v) == ["ab", "##cd"]
    assert T.wordpiece("abx", v) == [T.UNKNOWN]


def test_unigram_matches_enumeration_and_likelihood_rises():
    import math

    m = T.Unigram({"a": math.log(0.4), "b": math.log(0.3), "ab": math.log(0.2), "ba": math.log(0.1)})

    def cuts(w):
        if not w:
            yield []
        for k in range(1, len(w) + 1):
            if w[:k] in m.logp:
                yield from ([w[:k], *r] for r in cuts(w[k:]))

    for w in ("abab", "ba", "aabb"):
        each = [(sum(m.logp[x] for x in c), c) for c in cuts(w)]
        total = math.log(sum(math.exp(p) for p, _ in each))
        e, ll = m.expected(w)
        assert abs(ll - total) < 1e-9
        for piece in m.logp:
            assert abs(e.get(piece, 0) - sum(math.exp(p - total) * c.count(piece) for p, c in each)) < 1e-9
        assert abs(sum(m.logp[x] for x in m.best(w)) - max(p for p, _ in each)) < 1e-12
    _, trail = T.train_unigram([("abab", 5), ("abc", 3), ("cab", 2)], 100, 6)
    assert all(b >= a - 1e-6 for a, b in zip(trail, trail[1:]))


def test_stemmer_on_published_pairs():
    pairs = {"caresses": "caress", "ponies": "poni", "cats": "cat", "feed": "feed", "agreed": "agre", "plastered": "plaster", "motoring": "motor", "sing": "sing", "conflated": "conflat", "troubled": "troubl", "hopping": "hop", "falling": "fall", "filing": "file", "happy": "happi", "sky": "sky", "relational": "relat", "conditional": "condit", "rational": "ration", "triplicate": "triplic", "hopefulness": "hope", "goodness": "good", "revival": "reviv", "adoption": "adopt", "probate": "probat", "rate": "rate", "cease": "ceas", "controll": "control", "roll": "roll"}
    assert {w: Stemmer.stem(w) for w in pairs} == pairs


def test_staged_tables(spark):
    v = T.staged_vocab(spark)
    assert {(r["n_letters"], r["count"]) for r in v.groupBy("n_letters").count().collect()} == {(1, 52), (2, 1352), (3, 35152)}
    assert v.count() == 36556
    m = T.staged_merges(spark)
    assert m.count() == 36530
    got = {r["merged"]: (r["left"], r["right"]) for r in m.where("merged in ('abc', ' def', 'ab', ' ab')").collect()}
    assert got["abc"] == ("ab", "c") and got[" def"] == (" d", "ef") and got[" ab"] == (" a", "b")
    m2 = T.staged_merges(spark.newSession(), 42).repartition(7)
    assert m.exceptAll(m2).count() == 0


def test_round_trips(spark):
    from charprobe.operators import corpus

    docs = spark.createDataFrame([(1, "Hello there  wide world"), (2, None), (3, ""), (4, "a bb\tccc\ndddd")], "doc_id long, text string")
    w = corpus.words(docs)
    for tokens in (T.fixed_width_tokens(w), T.bpe_encode(w, T.bpe_merges(w, 5)), T.bpe_encode(w, T.staged_merges(spark), "distinct")):
        back = {(r["doc_id"], r["word_pos"]): r["word"] for r in T.decode(tokens).collect()}
        assert back == {(r["doc_id"], r["pos"]): r["word"] for r in w.collect()}
    assert [len(r["surface"]) for r in T.fixed_width_tokens(corpus.words(spark.createDataFrame([(1, "abcdefghij")], "doc_id long, text string"))).orderBy("sub_pos").collect()] == [3, 3, 3, 1]


def test_distributed_rounds_equal_local(spark):
    words = [("abab", 4), ("abc", 3), ("bcab", 2)]
    counts = spark.createDataFrame([(list(w), n) for w, n in words], "symbols array<string>, freq long")
    assert [(a, b) for a, b, _ in T.bpe_train_distributed(counts, 4)] == T.train_bpe([(list(w), n) for w, n in words], 4)


def test_merges_learn_from_all_words_beyond_the_driver_s_share(spark):
    from charprobe.operators import corpus

    w = corpus.words(spark.createDataFrame([(1, "ab ab ab ab cd ce cdx cdy cdz cdq ab")], "doc_id long, text string"))
    rules = lambda most: [(r["left"], r["right"]) for r in T.bpe_merges(w, 3, most).orderBy("rank").collect()]
    whole = T.train_bpe([(T.spelled_symbols(a, g), n) for a, g, n in T.top_words(w, 1000)], 3)
    assert rules(1000) == rules(2) == whole != T.train_bpe([(T.spelled_symbols(a, g), n) for a, g, n in T.top_words(w, 2)], 3)
