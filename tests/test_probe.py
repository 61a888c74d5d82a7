import numpy as np
from pyspark.sql import functions as F

from charprobe.operators import encode, measure, mlp, probe, rewrite, vocab


def some_vocab(spark, n=600):
    rng = np.random.default_rng(1)
    words = sorted({"".join(rng.choice(list("abcdefgh"), rng.integers(2, 6))) for _ in range(n)})
    return spark.createDataFrame([(i, w, bool(i % 2), len(w), 1) for i, w in enumerate(words)], "token_id long, surface string, has_space boolean, n_letters int, freq long")


def test_gradients_by_finite_differences():
    rng = np.random.default_rng(0)
    p = mlp.Probe(5, mlp.ProbeConfig(hidden=(4, 3)))
    x, y = rng.normal(size=(7, 5)), rng.integers(0, 2, 7).astype(float)
    masks = ((rng.random((7, 4)) < 0.8) / 0.8, (rng.random((7, 3)) < 0.8) / 0.8)
    for k, g in enumerate(p.gradients(x, y, masks)):
        flat = p.p[k].reshape(-1)
        for i in range(0, flat.size, 3):
            old, h = flat[i], 1e-6
            flat[i] = old + h
            up = p.loss(x, y, masks)
            flat[i] = old - h
            down = p.loss(x, y, masks)
            flat[i] = old
            assert abs((up - down) / (2 * h) - g.reshape(-1)[i]) < 1e-6


def test_matched_sample_is_balanced_and_length_says_nothing(spark):
    labels = probe.label(some_vocab(spark))
    m = probe.sample_matched(labels)
    assert m.groupBy("letter", "n_letters").agg(F.sum("y").alias("p"), F.count("*").alias("n")).where("2 * p <> n").count() == 0
    assert {r["length_accuracy"] for r in measure.length_only_accuracy(m).collect()} == {50.0}
    s = probe.split_pairs(m)
    assert s.groupBy("letter", "n_letters", "is_test").agg(F.sum("y").alias("p"), F.count("*").alias("n")).where("2 * p <> n").count() == 0


def test_controls(spark):
    v = some_vocab(spark, 900)
    s = probe.split_pairs(probe.sample_matched(probe.label(v, "abcdefgh")))
    cfg = mlp.ProbeConfig(epochs=25)
    spelled = measure.accuracy(mlp.fit_predict(s, encode.letter_bag(v), cfg)).first()
    noise = measure.accuracy(mlp.fit_predict(s, encode.random_vectors(v, 16), cfg)).first()
    assert spelled["accuracy"] >= 95
    assert abs(noise["accuracy"] - 50) <= 100 * 2.576 * 0.5 / noise["n"] ** 0.5 + 1


def test_folds_keep_groups_whole_and_even(spark):
    labels = probe.label(some_vocab(spark), "abc")
    for method in ("serpentine", "greedy"):
        f = probe.group_folds(labels, 5, "next", method)
        assert f.groupBy("letter", "grp").count().where("count > 1").count() == 0
        assert f.select("fold").distinct().count() == 5
    g = probe.grouped_sample(labels, 5, "prev")
    assert g.groupBy("letter", "fold", "n_letters").agg(F.sum("y").alias("p"), F.count("*").alias("n")).where("2 * p <> n").count() == 0


def test_svd_against_numpy(spark):
    rng = np.random.default_rng(2)
    a = rng.random((12, 12)) * (rng.random((12, 12)) < 0.5)
    rows = [(i, j, float(a[i, j])) for i in range(12) for j in range(12) if a[i, j]]
    got = encode.svd_vectors(spark.createDataFrame(rows, "t long, c long, value double"), 3, 12).orderBy("token_id").collect()
    x = np.array([r["vector"] for r in got])
    u, s, _ = np.linalg.svd(a)
    keep = [i for i in range(12) if a[i].any()]
    want = (u[:, :3] * np.sqrt(s[:3]))[keep]
    assert np.allclose(np.abs(x), np.abs(want), atol=1e-4)


def test_interventions_keep_what_they_should(spark):
    docs = spark.createDataFrame([(1, "She dreams, she is dreaming ß 42!"), (2, "")], "doc_id long, text string")
    got = {r["doc_id"]: r["t"] for r in docs.select("doc_id", rewrite.scramble_letters(F.col("text"), 42, F.col("doc_id")).alias("t")).collect()}
    src = "She dreams, she is dreaming ß 42!"
    assert len(got[1]) == len(src) and got[2] == ""
    for a, b in zip(src, got[1]):
        assert (a.isascii() and a.isalpha() and b.isascii() and b.isalpha() and a.isupper() == b.isupper()) or a == b
    units = spark.createDataFrame([("word%s" % "abcdefghij"[i],) for i in range(10)], "surface string")
    d = rewrite.substitution_dict(units).collect()
    assert len(d) == 10 == len({r["dst"] for r in d}) and all(len(r["src"]) == len(r["dst"]) for r in d)
    short = rewrite.substitution_short(spark.createDataFrame([(c,) for c in ("a", "b", "ab", "zz")], "surface string")).collect()
    assert len(short) == 4 == len({r["dst"] for r in short})


def test_vocab_share_and_budget(spark):
    v = some_vocab(spark)
    assert abs(sum(r["share"] for r in measure.vocab_share(v).collect()) - 100) < 1e-4
    assert vocab.max_letters(v, 3).where("n_letters > 3").count() == 0
    b = measure.token_budget(spark).first()
    assert (b["tokens"], b["repeated"]) == (13_107_200_000, 3_107_200_000)


def test_substitution_keeps_every_word(spark):
    import __spark_entry__ as entry
    from charprobe.plans import registry

    small = "/root/testdata/sf0.001"
    before = {(r["doc_id"], r["pos"]): r["word"] for r in registry.words(spark, small).collect()}
    after = {(r["doc_id"], r["pos"]): r["word"] for r in entry.queries()["substitute_words"](spark, small).collect()}
    assert before.keys() == after.keys() and min(map(len, before.values())) < 4
    table = {(w, after[k]) for k, w in before.items()}
    assert len(table) == len({a for a, _ in table}) == len({b for _, b in table}) and all(len(a) == len(b) for a, b in table)


def test_substitution_of_short_units_with_other_letters(spark):
    from charprobe.operators import rewrite

    units = spark.createDataFrame([(x,) for x in ("a", "ab", "abc", "\u00e9", "\u00e8", "\u00e9a", "word", "w\u00e9rd")], "surface string")
    got = {r["src"]: r["dst"] for r in rewrite.substitution_all(units).collect()}
    assert len(got) == len(set(got.values())) == 8 and all(len(a) == len(b) for a, b in got.items())
