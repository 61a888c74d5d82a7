import numpy as np
import pytest
from pyspark.sql import functions as F

from charprobe.operators import corpus, encode, pieces, rewrite, tokenize, vocab


@pytest.fixture(scope="module")
def docs(spark):
    texts = ["The cats sat\ton the  mats, the\ncat", None, "", " \n", "a", "zz zz zzz", "flies fly ß éa 1x2", "word " * 300, "Abcdefgh ijklmnop"]
    return spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)


def tokens(rows):
    """(document, place, piece) of documents as lists."""
    return sorted((r["doc_id"], k, p) for r in rows.collect() for k, p in enumerate(r["pieces"]))


def spelled(df, *order):
    rows = df.select("doc_id", *order, F.concat(F.when(F.col("has_space"), " ").otherwise(""), df["surface"] if "surface" in df.columns else df["word"]).alias("p")).orderBy("doc_id", *order).collect()
    out, place = [], {}
    for r in rows:
        out.append((r["doc_id"], place.setdefault(r["doc_id"], 0), r["p"]))
        place[r["doc_id"]] += 1
    return out


def test_lists_hold_the_tokens_of_rows(docs):
    words, rows = corpus.words(docs), pieces.of_documents(docs)
    assert tokens(rows) == spelled(words, "pos")
    assert tokens(pieces.fixed_width(rows)) == spelled(tokenize.fixed_width_tokens(words), "word_pos", "sub_pos")
    merges = tokenize.bpe_merges(words, 9)
    rules = pieces.learnt(rows, 9)
    assert rules == [(r["left"], r["right"]) for r in merges.orderBy("rank").collect()]
    coded = tokenize.with_pieces(words, merges)
    merged, long = pieces.merged(rows, rules), tokenize.exploded(coded)
    assert tokens(merged) == spelled(long, "word_pos", "sub_pos")
    v, w = (vocab.target_vocab(x) for x in (vocab.build(long, 12), vocab.ranked(pieces.surfaces(pieces.counted(merged)), 12)))
    assert sorted(map(tuple, v.collect())) == sorted(map(tuple, w.collect()))
    assert sorted(map(tuple, pieces.numbered(merged, w).collect())) == sorted(map(tuple, encode.sequences(long, v).collect()))
    table = rewrite.subword_substitution(coded, 1)
    assert tokens(pieces.substituted(rows, rules, table)) == spelled(rewrite.substitute_subwords(coded, table), "pos")


def test_words_of_random_texts():
    import re

    import pyarrow as pa

    rng = np.random.default_rng(2)
    texts = ["".join(rng.choice(list("aBz  \t\n\r\x0b1.é漢"), n)) for n in rng.integers(0, 30, 400)]
    want = [[" " * (m[0] in " \t\n\r") + m.strip().lower() for m in re.findall("[ \t\n\r]?[A-Za-z]+", t)] for t in texts]
    for part in (slice(0, 400), slice(7, 311), slice(5, 5)):
        starts, flat = pieces.words_in(pa.array(texts, pa.string())[part])
        assert pa.ListArray.from_arrays(pa.array(starts, pa.int32()), flat).to_pylist() == want[part]


def test_words_by_others(spark, docs):
    words, rows = corpus.words(docs), pieces.of_documents(docs)
    table = spark.createDataFrame([("cats", "cat"), ("flies", "fly")], "word string, other string")
    want = [(d, k, p.replace("cats", "cat").replace("flies", "fly")) for d, k, p in spelled(words, "pos")]
    assert tokens(pieces.replaced(rows, table)) == tokens(pieces.replaced(rows, table, 1)) == want
    stems = {r["word"]: r["stem"] for r in rewrite.stem(corpus.word_counts(words)).collect()}
    assert tokens(pieces.stemmed(rows)) == [(d, k, " " * p.startswith(" ") + stems[p.strip()]) for d, k, p in spelled(words, "pos")]


def test_vectors_of_a_small_vocabulary_take_few_jobs(spark):
    rng = np.random.default_rng(5)
    seqs = spark.createDataFrame([(k, [int(x) for x in rng.integers(0, 60, n)]) for k, n in enumerate(rng.integers(0, 50, 80))], "doc_id long, ids array<int>")
    sc = spark.sparkContext
    sc.setJobGroup("few", "vectors")
    try:
        for direction in ("concat", "both", "forward"):
            got = {r["token_id"]: r["vector"] for r in encode.distributional(seqs, 2, 8, direction).collect()}
        jobs = len(sc.statusTracker().getJobIdsForGroup("few"))
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    assert jobs <= 18
    want = {r["token_id"]: r["vector"] for r in encode.distributional(seqs, 2, 8, "forward", square=0).collect()}
    assert set(got) == set(want) and all(np.allclose(got[k], want[k], atol=1e-9) for k in got)


def test_resampled_pieces_stay_in_their_class(spark):
    texts = [" ".join("abcdefgh"[(i * k + j) % 8] * (1 + (k + j) % 3) for j in range(40)) for k, i in enumerate(range(60))]
    rows = pieces.of_documents(spark.createDataFrame([*enumerate(texts), (90, None), (91, "")], "doc_id long, text string").repartition(3)).persist()
    kind = lambda p: (p[:1] == " ", len(p))
    before, after, other = tokens(rows), tokens(pieces.resampled(rows, pieces.counted(rows), 1)), tokens(pieces.resampled(rows, pieces.counted(rows), 2))
    assert [(d, k, kind(p)) for d, k, p in before] == [(d, k, kind(p)) for d, k, p in after]
    assert after != before and after != other
    assert after == tokens(pieces.resampled(rows.repartition(7), pieces.counted(rows), 1))
    for c in {kind(p) for *_, p in before if p[:1] == " "}:  # every entry of a class about as often, however often it stood before
        n = {}
        for *_, p in after:
            if kind(p) == c:
                n[p] = n.get(p, 0) + 1
        assert set(n) == {p for *_, p in before if kind(p) == c} and max(n.values()) < 2 * sum(n.values()) / len(n)
    rows.unpersist()
