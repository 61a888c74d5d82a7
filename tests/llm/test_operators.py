import collections
import random
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from charprobe.llm import bm25, common, hpy_lm, jaccard, mixing, packing, pu_quality, quality_rules, sharding, token_store, url_filter
from charprobe.llm.common import text_key
from charprobe.llm.token_ids import default_vocabulary, encoder

SMALL = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, n_chars long, size long, id long, place long"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, ties, repeated rows, columns with clashing names."""
    base = "The quick brown fox jumps over the lazy dog. And then it sleeps,  well!\nNext line here. "
    texts = [(1, base), (2, base), (2, base), (3, None), (4, ""), (None, "only one two"), (5, " \t\n"), (6, "word"), (20, base * 400), (40, base + "tail"), (7, "x" * 5000), (8, "é ß 😀 漢字\r\nword  ")]
    rows = [(i, t, "en" if i != 3 else None, "s" if i != 4 else None, 0, 1, 2, 3) for i, t in texts]
    return spark.createDataFrame(rows, DOC)


def words(t):
    return (t or "").encode().lower().split()


def test_encoder_equals_library():
    e = encoder(default_vocabulary())
    rng = random.Random(5)
    texts = ["".join(rng.choice("ab'  \n\t.,!?é1　😀\x85\x1c") for _ in range(rng.randint(0, 40))) for _ in range(3000)] + ["<|endoftext|> a", "a  b", " ", ""]
    for t, want in zip(texts, e.tokenizer.encode_batch(texts, add_special_tokens=False)):
        assert list(e.ids(t)) == want.ids, repr(t)


def test_shards(spark, odd):
    rows = sharding.assign_shards(odd, 7).collect()
    assert len(rows) == odd.count()
    for r in rows:
        assert r["grown_shard"] in (r["shard"], 7)
    by = collections.defaultdict(list)
    for r in rows:
        by[r["shard"]].append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    k = sharding.mixed(np.arange(20000))
    moved = (sharding.jump(k, 40) != sharding.jump(k, 41)).mean()
    assert abs(moved - 1 / 41) < 0.01
    assert sharding.assign_shards(odd.limit(0), 3).count() == 0


def components(texts, n, percent):
    sets = [{tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set() for w in map(words, texts)]
    root = list(range(len(texts)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for i in range(len(sets)):
        for j in range(i):
            c = len(sets[i] & sets[j])
            if c and 100 * c >= percent * len(sets[i] | sets[j]):
                root[max(find(i), find(j))] = min(find(i), find(j))
    return [len(s) for s in sets], [find(i) for i in range(len(sets))]


def test_jaccard_against_all_pairs(spark, monkeypatch):
    rng = random.Random(1)
    for hot in (64, 3):
        monkeypatch.setattr(jaccard, "HOT", hot)
        monkeypatch.setattr(jaccard, "BLOCK", 6)
        seed = [rng.choice("abcdefghij") * 2 for _ in range(60)]
        texts = []
        for _ in range(70):
            w = list(seed)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 5])):
                w[rng.randrange(len(w))] = "z%d" % rng.randrange(50)
            texts.append(" ".join(w[: rng.choice([60, 60, 58, 30])]))
        texts += ["one", "One", "", "one two", "p q r s"]
        sizes, root = components(texts, 3, 90)
        got = {r["doc_id"]: r for r in jaccard.jaccard_components(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), 3, 90).collect()}
        assert [got[i]["n_shingles"] for i in range(len(texts))] == sizes
        assert [got[i]["component_id"] for i in range(len(texts))] == root


def test_jaccard_odd_rows(odd):
    rows = jaccard.jaccard_components(odd, 3, 90).collect()
    assert len(rows) == odd.count()
    by = {r["doc_id"]: r["component_id"] for r in rows}
    assert by[2] == 1 and by[3] == 3 and by[4] == 4 and by[5] == 5
    assert jaccard.jaccard_components(odd.limit(0)).count() == 0
    kept = jaccard.representatives(odd, jaccard.jaccard_components(odd, 5, 80))
    assert sorted(str(r["doc_id"]) for r in kept.select("doc_id").collect()).count("2") == 0


def test_packed_tokens_round_trip():
    rng = np.random.default_rng(0)
    for n in (1, 2, 50, 100_000):
        t = np.unique(rng.integers(0, 1 << 63, n, dtype=np.int64).astype(np.uint64))
        assert (common.unpacked(*common.packed(t)) == t).all()


def test_quality_base_counts():
    h = quality_rules.WordHasher()
    t = "a b c d e f g h x a b c d e f g h".encode()
    assert quality_rules.base_counts(t, t.split(), h(t.split()))[4] == 16
    t = b"a a a a a a a a a"
    assert quality_rules.base_counts(t, t.split(), h(t.split()))[4] == 9
    t = "é #x\n\n é #x\nq\né #x\n".encode()
    assert quality_rules.base_counts(t, t.split(), h(t.split()))[:4] == (7, 10, 3, 1)


def test_learnt_quality(spark, odd):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    scored = pu_quality.score_quality(docs, labels).where("held_out").join(labels, "doc_id").select("score", "predicted", "quality").collect()
    good, bad = [r["score"] for r in scored if r["quality"] == 1], [r["score"] for r in scored if r["quality"] == 0]
    assert np.mean([[g > b for b in bad] for g in good]) > 0.9
    judged = quality_rules.judge_quality(docs, labels).where("not base_failed").join(labels, "doc_id").collect()
    assert np.mean([r["kept"] == (r["quality"] == 1) for r in judged]) > 0.9
    for f in (pu_quality.score_quality, quality_rules.judge_quality):
        assert f(odd, labels).count() == odd.count()
        assert f(odd.limit(0), labels.limit(0)).count() == 0


def test_prior_estimate():
    rng = np.random.default_rng(0)
    p, n = rng.normal(2, 1, 4000), rng.normal(-2, 1, 4000)
    for prior in (0.3, 0.85):
        u = np.concatenate([rng.normal(2, 1, int(4000 * prior)), n[: int(4000 * (1 - prior))]])
        assert abs(pu_quality.estimate_prior(p, u) - prior) < 0.06


def test_unlabelled_risk_of_all_rows(spark, odd, monkeypatch):
    """Sums on the executors against dense features of every row; few rows in a task, several levels of adding."""
    from charprobe.llm.text_features import SIZE, sparse

    monkeypatch.setattr(pu_quality, "FAN", 3)
    rng = np.random.default_rng(3)
    words = [f"w{k}" for k in range(300)] + ["é", "##", "A!"]
    texts = [(k, " ".join(rng.choice(words, rng.integers(0, 60)))) for k in range(200)] + [(5, None), (6, ""), (None, "x y")]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(11)
    first, at = rng.normal(0, 0.3, SIZE + 1), rng.normal(0, 0.3, SIZE + 1)
    learnt = frozenset(range(0, 200, 2))
    whole, scores = pu_quality.whole_risk(docs, first, at, learnt)
    hasher, slope, losses, seen = common.WordHasher(), np.zeros(SIZE + 1), [], []
    for i, text in texts:
        if zlib.crc32(str("" if i is None else i).encode()) % 5 == 0:
            continue
        index, value = sparse((text or "").encode(), hasher)
        x = np.zeros(SIZE + 1)
        x[index], x[-1] = value, 1.0
        losses.append(np.logaddexp(0, x @ at))
        slope += x / (1 + np.exp(-(x @ at)))
        if i not in learnt:
            seen.append(x @ first)
    assert np.isclose(whole.loss, np.mean(losses), rtol=1e-5)
    assert np.allclose(whole.slope, slope / len(losses), rtol=1e-4, atol=1e-5)
    assert scores.sum() == len(seen)
    assert np.allclose(np.repeat(pu_quality.BINS, scores.astype(int)), np.sort(np.clip(seen, -20, 20)), atol=0.011)
    none, scores = pu_quality.whole_risk(docs.limit(0), first, at, learnt)
    assert none.loss == 0 and not scores.any()
    assert pu_quality.whole_risk(odd, first, at, learnt)[1].sum() >= 0


def test_whole_risk_corrects_the_sample():
    """A fit on a lopsided sample, given the value and slope of all rows, comes nearer to the fit on all rows."""
    from charprobe.llm.text_features import SIZE, Examples, sigmoid

    rng = np.random.default_rng(1)
    row = lambda good: (np.sort(rng.choice(np.arange(40) + (0 if good else 20), 12, False)).astype(np.int32), np.full(12, 0.8, np.float32))
    p, everything = Examples([row(True) for _ in range(300)]), [row(k % 3 == 0) for k in range(3000)]
    u, sample = Examples(everything), Examples(everything[0:60:3] + everything[1:60:12])
    want = pu_quality.fit(p, u, 1 / 3)
    start = pu_quality.fit(p, sample, 1 / 3)
    m = u.margins(start[:-1]) + start[-1]
    whole = pu_quality.Whole(start, float(np.logaddexp(0, m).mean()), np.append(u.gradient(sigmoid(m) / u.n), sigmoid(m).mean()))
    got = pu_quality.fit(p, sample, 1 / 3, whole=whole)
    assert start.shape == (SIZE + 1,)
    gap = lambda w: np.abs((u.margins(w[:-1]) + w[-1]) - (u.margins(want[:-1]) + want[-1])).mean()
    assert gap(got) < gap(start)


def test_examples_are_summed_in_little_memory():
    import tracemalloc

    from charprobe.llm.text_features import SIZE, Examples

    rng = np.random.default_rng(3)
    rows = [(np.sort(rng.choice(SIZE, n, replace=False)).astype(np.int32), rng.random(n).astype(np.float32)) for n in rng.integers(900, 1100, 1500)]
    weights, slopes = rng.normal(size=SIZE), rng.normal(size=len(rows))
    tracemalloc.start()
    try:
        e = Examples(rows)
        margins, gradient = e.margins(weights), e.gradient(slopes)
        assert tracemalloc.get_traced_memory()[1] < 16 * sum(len(i) for i, _ in rows)
    finally:
        tracemalloc.stop()
    want = np.zeros(SIZE)
    for (i, v), s in zip(rows, slopes):
        want[i] += v.astype(float) * s
    assert np.allclose(gradient, want) and np.allclose(margins, [weights[i] @ v for i, v in rows])
    assert len(Examples([]).margins(weights)) == 0 and not Examples([]).gradient(np.zeros(0)).any()


def test_cuts_are_cheapest():
    rng = np.random.default_rng(0)
    for _ in range(200):
        w, n = int(rng.choice([4, 8, 16])), int(rng.integers(1, 30))
        pos = np.concatenate(([0], np.cumsum(rng.integers(1, w + 1, n))))
        pen, wc = np.concatenate(([0.0], rng.choice([0.0, 1.0, 3.0], n))), float(rng.choice([0.0, 2.0]))
        got = packing.cost_of(packing.choose_cuts(pos, pen, w, wc), pos, pen, w, wc)
        assert abs(got - packing.brute_cuts(pos.tolist(), pen.tolist(), w, wc)) < 1e-9


def test_packing_covers_every_id(odd):
    rows = packing.pack_documents(odd, default_vocabulary(), 64).collect()
    e, seq, doc = encoder(default_vocabulary()), collections.defaultdict(list), collections.Counter()
    texts = collections.defaultdict(set)
    for r in odd.collect():
        texts[r["doc_id"]].add(r["text"])
    for r in rows:
        seq[r["sequence_id"]].append((r["offset"], r["length"]))
        doc[r["doc_id"]] += r["length"]
        ids = [np.append(e.ids(t or ""), np.uint32(0)) for t in texts[r["doc_id"]]]
        assert any(zlib.crc32(i[r["start"] : r["start"] + r["length"]].astype("<u4").tobytes()) == r["ids_crc32"] and len(i) == r["doc_tokens"] for i in ids)
    for v in seq.values():
        at = 0
        for offset, n in sorted(v):
            assert offset == at
            at += n
        assert at <= 64
    assert doc[2] == 2 * doc[1]
    assert packing.pack_documents(odd.limit(0), default_vocabulary()).count() == 0


def test_url_rules_against_plain_python(spark):
    rules = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]
    urls = ["http://a.Example.COM/en/71?x", "http://example.com/en/81", "https://x.net/de/9#t", "http://www.example.net/de/88", "http://notcom/en/", "com/en/", None, "", "http://", "http://org/es/", "ftp://q.org", "http://example.com?/en/7", "http://example.com/en/71?x", "http://u/a://com/en/", "http://a..com/en/\nx"]
    rows = [(i, u, 1) for i, u in enumerate(urls)] + [(0, urls[0], 1), (None, urls[1], 1)]
    got = url_filter.judge_urls(spark.createDataFrame(rows, "page_id long, url string, host int"), url_filter.rule_table(spark, rules)).collect()

    def judge(u):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        end = min([rest.find(c) for c in "/?#" if c in rest] or [len(rest)])
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:end])
        path = rest[end:]
        path = path[: min([path.find(c) for c in "?#" if c in path] or [len(path)])]
        fit = [(len(h + p), len(h), v == "block", h + p, v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fit, default=(0, 0, 0, None, "allow"))
        return host, path, best[3], best[4]

    assert sorted(map(str, [(i, *judge(u)) for i, u, _ in rows])) == sorted(str((r["page_id"], r["host"], r["path"], r["rule"], r["verdict"])) for r in got)


def test_raking_meets_the_marginals(spark, odd):
    cells = [(a, b) for a in "xyz" for b in "uv"]
    w = mixing.rake(cells, np.arange(1.0, 7.0), [{"x": 0.5, "y": 0.3, "z": 0.2}, {"u": 0.6, "v": 0.4}], 60)
    assert abs(sum(v for c, v in zip(cells, w) if c[0] == "x") - 0.5) < 1e-9 and abs(sum(v for c, v in zip(cells, w) if c[1] == "u") - 0.6) < 1e-9
    p = mixing.calibrated(np.array([0.5, 1.0, 3.0]), np.array([0.5, 0.3, 0.2]), 0.6)
    assert abs((p * [0.5, 0.3, 0.2]).sum() - 0.6) < 1e-9 and p.max() <= 1
    rows = mixing.mix_documents(odd).collect()
    assert len(rows) == odd.count() and mixing.mix_documents(odd.limit(0)).count() == 0
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    out = mixing.mix_documents(docs).selectExpr("sum(if(kept, n_tokens, 0)) / sum(n_tokens) as share").first()
    assert abs(out["share"] - 0.9) < 0.03


def test_tempered_targets_are_shares_of_bounded_raise():
    own = {"a": 0.9, "b": 0.0999, "c": 0.0001, "d": 0.0}
    t = mixing.tempered(own, 0.5, 1.25)
    assert abs(sum(t.values()) - 1) < 1e-12 and set(t) == {"a", "b", "c"}
    assert abs(t["b"] - 1.25 * 0.0999) < 1e-9 and abs(t["c"] - 1.25 * 0.0001) < 1e-12
    free = mixing.tempered(own, 0.9, 1e9)
    assert abs(free["c"] / free["a"] - (0.0001 / 0.9) ** 0.9) < 1e-12


def test_registered_mix_reaches_its_targets(spark):
    """Expected kept shares against the tempered targets, by source, language and topic."""
    from charprobe.llm import queries

    rows = queries.QUERIES["op6_rake_mix"](spark, "/root/testdata/sf0.1").select("source", "lang", "topic", "n_tokens", "prob", "kept").collect()
    everything = sum(r["n_tokens"] for r in rows)
    kept, drawn = sum(r["n_tokens"] * r["prob"] for r in rows), sum(r["n_tokens"] for r in rows if r["kept"])
    assert max(r["prob"] for r in rows) <= 1 and kept > 0.65 * everything and abs(drawn - kept) < 0.03 * everything
    for column in ("source", "lang", "topic"):
        own, got = collections.Counter(), collections.Counter()
        for r in rows:
            own[r[column]] += r["n_tokens"] / everything
            got[r[column]] += r["n_tokens"] * r["prob"] / kept
        for name, target in mixing.tempered(own, 0.9).items():
            assert abs(got[name] / target - 1) < 1e-4, (column, name)


def test_store_round_trip(spark, odd, tmp_path):
    path = str(tmp_path / "store")
    token_store.write_store(odd, path, default_vocabulary())
    e = encoder(default_vocabulary())
    want = sorted((str(r["doc_id"]), list(map(int, np.append(e.ids(r["text"] or ""), 2)))) for r in odd.collect())
    assert sorted((str(r["doc_id"]), list(r["ids"])) for r in token_store.read_documents(spark, path).collect()) == want
    rows = token_store.read_digests(spark, path).orderBy("start").collect()
    at = 0
    for r in rows:
        assert r["start"] == at
        at += r["n_tokens"]
    ids = [r["doc_id"] for r in rows]
    assert ids == sorted(ids, key=lambda x: (x is not None, x))
    assert sorted(r["ids_crc32"] for r in rows) == sorted(zlib.crc32(np.array(i, "<u4").tobytes()) for _, i in want)
    chunks = spark.read.parquet(f"{path}/content").where("kind = 'chunk'")
    assert chunks.count() == chunks.select("digest").distinct().count()
    spark.read.parquet(f"{path}/manifest").selectExpr("range", "range_root", "documents + 1 as documents", "ids", "first_id").write.parquet(str(tmp_path / "m"))
    import shutil

    shutil.rmtree(f"{path}/manifest")
    shutil.move(str(tmp_path / "m"), f"{path}/manifest")
    with pytest.raises(token_store.BrokenStore):
        token_store.read_digests(spark, path)
    assert token_store.store_and_read(odd.limit(0), default_vocabulary()).count() == 0


def test_shared_passages_cut_alike():
    rng = np.random.default_rng(0)
    shared = rng.integers(0, 50000, 6000).astype(np.uint32)
    a, b = np.concatenate([rng.integers(0, 50000, 777).astype(np.uint32), shared]), np.concatenate([rng.integers(0, 50000, 99).astype(np.uint32), shared])

    def parts(x):
        ends = token_store.cut_points(x)
        return {x[s:e].tobytes() for s, e in zip([0, *ends], ends)}

    assert len(parts(a) & parts(b)) >= 4


def test_language_model_base_is_exact_and_model_is_better(spark, odd):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = hpy_lm.score_documents(docs).collect()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    count = collections.Counter()
    for i, t in texts.items():
        if zlib.crc32(str(i).encode()) % 7 != 2:
            count.update([*words(t), None])
    n, v = sum(count.values()), len(count)
    for r in rows:
        w = [*words(texts[r["doc_id"]]), None]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(count[x] > 0 for x in w), n)
        assert abs(r["base_score"] - sum(np.log10((count[x] + 1) / (n + v + 1)) for x in w)) < 1e-6
    ten = {x: 10 ** (-sum(r["score"] for r in rows if r["held_out"] == x) / sum(r["n_tokens"] for r in rows if r["held_out"] == x)) for x in (True, False)}
    assert ten[False] < ten[True]  # texts that the model has learnt from are likelier, word for word
    known = [r for r in rows if r["held_out"] and r["n_known"] == r["n_tokens"]]
    assert known and sum(r["score"] for r in known) > sum(r["base_score"] for r in known)
    got = hpy_lm.score_documents(odd).collect()
    assert sorted((str(r["doc_id"]), r["n_tokens"]) for r in got) == sorted((str(r["doc_id"]), len(words(r["text"])) + 1) for r in odd.collect())
    assert hpy_lm.score_documents(odd.limit(0)).count() == 0
    nothing = hpy_lm.score_documents(odd.where("doc_id = -1").unionByName(odd.where("doc_id = 6").selectExpr("cast(0 as bigint) doc_id", "text", "lang", "source", "n_chars", "size", "id", "place"))).collect()
    assert len(nothing) == 1


def test_search_equals_sql(spark, odd):
    from charprobe.llm import oracles, queries

    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    for name in ("op1_jump_shards", "op2_ngram_jaccard", "op5_url_rules", "op10_bm25_search"):
        got = queries.QUERIES[name](spark, SMALL)
        cols = sorted(got.columns)
        want = con.execute(oracles.SQL[name]).df()[cols]
        assert sorted(map(str, (tuple(r[c] for c in cols) for r in got.collect()))) == sorted(map(str, want.astype(object).itertuples(index=False, name=None))), name
    rows = bm25.search_top_k(odd, 3).collect()
    assert {r["query_id"] for r in rows} == {20, 40} and bm25.search_top_k(odd.limit(0)).count() == 0
    again = bm25.search_top_k(odd.unionByName(odd.where("doc_id = 20")), 4, least_shards=1).where("query_id = 20").orderBy("rank").collect()
    assert [r["rank"] for r in again] == [1, 2, 3, 4] and sum(r["doc_id"] == 20 for r in again) == 2


def test_a_task_of_the_copies_index_has_one_bucket(spark, monkeypatch):
    """Buckets of n-grams are not hashed to tasks again, which put up to four of 48 into one."""
    seen = spark.sparkContext.accumulator(0)
    texts = [(k, " ".join(f"a{(k // 2 * 7 + j) % 99991}" for j in range(60))) for k in range(400)]
    docs = spark.createDataFrame(texts, "doc_id long, text string")

    def told(source, buckets, share=jaccard.share_lists):
        whole = list(source)
        seen.add(max(0, len({b if b >= 0 else -1 - b for x in whole for b in x.column(0).to_pylist()}) - 1))
        return share(iter(whole), buckets)

    monkeypatch.setattr(jaccard, "share_lists", told)
    rows = jaccard.jaccard_components(docs, 3, 90).collect()
    assert seen.value == 0 and all(r["component_id"] == r["doc_id"] // 2 * 2 for r in rows)


def test_search_multiplies_neither_queries_nor_answers_by_shards(spark):
    """Many shards answer like one, and no step of the plan copies a query for each shard or ranks the shards' answers."""
    rng = np.random.default_rng(9)
    texts = [(k, " ".join(f"w{x}" for x in rng.zipf(1.4, int(rng.integers(1, 40))) % 200)) for k in range(600)]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    many, one = bm25.search_top_k(docs, 4, least_shards=7), bm25.search_top_k(docs, 4, least_shards=1)
    plan = many._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "Window" not in plan
    got = sorted(map(tuple, many.collect()))
    assert got == sorted(map(tuple, one.collect())) and len(got) == 4 * 30


def test_pruned_search_equals_scoring_all():
    """One shard of 3,000 documents: most blocks are left unread, and the best ten are those of scoring every document."""
    rng = np.random.default_rng(2)
    texts = []
    for _ in range(3000):
        topic, size = rng.integers(0, 40), int(rng.integers(5, 120))
        word = np.where(rng.random(size) < 0.2, rng.zipf(1.3, size) % 300, 1000 + 60 * topic + rng.integers(0, 60, size))
        texts.append(word.astype(np.uint64))
    texts[7] = np.concatenate([texts[8], np.full(70_000, texts[8][0])])  # one word more often than 16 bits count
    docs = [(i, len(t), *np.unique(t, return_counts=True)) for i, t in enumerate(texts)]
    held = bm25.lists(bm25.inverted(docs))
    df = np.bincount(np.searchsorted(held[2], np.concatenate([d[2] for d in docs])))
    mean = sum(len(t) for t in texts) / 3000
    shard = bm25.Shard(*held, df, 3000, mean)
    for q in range(0, 3000, 30):
        t = docs[q][2]
        score = np.zeros(3000)
        for x, (_, n, terms, counts) in enumerate(docs):
            both, _, at = np.intersect1d(t, terms, return_indices=True)
            f = df[np.searchsorted(held[2], both)]
            score[x] = np.round((np.log(1 + (3000 - f + 0.5) / (f + 0.5)) * counts[at] * 2.2 / (counts[at] + 1.2 * (0.25 + 0.75 * n / mean))).sum(), 6)
        want = np.lexsort((np.arange(3000), -score))[:10]
        ((got, scores),) = shard.top_many(shard.find_terms(t), [len(t)], 10)
        assert shard.ids[got].tolist() == want[score[want] > 0].tolist() and np.allclose(scores, score[want][score[want] > 0], atol=2e-6)
    assert shard.visited < 0.7 * shard.asked


def test_queries_take_their_runs_of_visits_together(monkeypatch):
    """Many queries are answered as one by one, with floors or without, and a run of visits is one reading for all of them."""
    rng = np.random.default_rng(4)
    texts = [(rng.zipf(1.3, int(rng.integers(1, 90))) % 3000).astype(np.uint64) for _ in range(2000)]
    docs = [(i, len(t), *np.unique(t, return_counts=True)) for i, t in enumerate(texts)]
    held = bm25.lists(bm25.inverted(docs))
    shard = bm25.Shard(*held, np.bincount(np.searchsorted(held[2], np.concatenate([d[2] for d in docs]))), 2000, sum(map(len, texts)) / 2000)
    asked = [*(d[2] for d in docs[::20]), np.array([7_000], np.uint64), np.zeros(0, np.uint64)]
    numbers, sizes = shard.find_terms(np.concatenate(asked)), list(map(len, asked))
    alone = [next(shard.top_many(shard.find_terms(t), [len(t)], 10)) for t in asked]
    reads = []
    monkeypatch.setattr(bm25.Shard, "_read", lambda self, *args, read=bm25.Shard._read: reads.append(1) or read(self, *args))
    floors = [float(s[-1]) - bm25.ROUNDING if len(s) else 0.0 for _, s in alone]
    for low in (None, floors):
        got = list(shard.top_many(numbers, sizes, 10, low))
        assert len(got) == len(asked) and all(a.tolist() == c.tolist() and b.tolist() == d.tolist() for (a, b), (c, d) in zip(got, alone))
    assert not len(got[-1][0]) and not len(got[-2][0])
    assert len(reads) <= 2 * 3 * -(-len(asked) // bm25.TOGETHER)


def test_pipeline_keeps_clean_rows_without_or_with_repeated_ids(spark, monkeypatch):
    import corpus_pipeline

    say = lambda tag: " ".join(f"{tag}{k} and" for k in range(60)) + "."
    texts = [(None, say("red")), (None, say("blue")), (7, say("green")), (7, say("black")), (7, say("black")), (9, say("red") + " more"), (None, "bad"), (7, "bad"), (None, None), (11, "")]
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in texts], "doc_id long, text string, lang string, source string")
    kept = lambda df: sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)
    want = sorted(set(texts) - {(None, say("red")), (None, "bad")}, key=str)  # both have a like row with an id
    assert kept(jaccard.representatives(docs, jaccard.jaccard_components(docs, 5, 80))) == want
    labels = spark.createDataFrame([], "doc_id long, quality int")
    monkeypatch.setattr(corpus_pipeline, "_labels", lambda *_: labels)
    ruled = kept(corpus_pipeline.quality_rule_filter(spark, docs, ""))
    assert ruled == sorted(texts[:6], key=str)
    judged = pu_quality.score_quality(docs, labels, keyed=True).withColumn("predicted", F.when(F.col("text_key") == text_key(F.lit("bad")), 0).otherwise(1))
    assert kept(corpus_pipeline._rejected(docs, judged.where("predicted = 0"))) == sorted([x for x in texts if x[1] != "bad"], key=str)


def test_pipeline(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, SMALL)
    ids = {r["doc_id"] for r in out.select("doc_id").distinct().collect()}
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    assert ids and ids <= {r["doc_id"] for r in docs.select("doc_id").collect()}
    step = docs
    for name, f in corpus_pipeline.STAGES[:-1]:
        step = f(spark, step, SMALL)
        assert step.columns == docs.columns, name
        assert 0 < step.count() <= docs.count()


def test_stages_keep_columns_with_clashing_names(spark, monkeypatch):
    """Extra columns named like ours, nulls everywhere, repeated rows and empty tables, through every stage but the last."""
    import corpus_pipeline

    monkeypatch.setattr(corpus_pipeline, "_labels", lambda *_: spark.createDataFrame([], "doc_id long, quality int"))
    say = lambda tag: " ".join(f"{tag}{k} and" for k in range(60)) + "."
    extra = ["bad_id", "bad_key", "kept_id", "kept_key", "text_key", "form_topic", "topic", "row", "mix_kept", "mix_prob", "c0", "component_id"]
    rows = [(1, say("a"), "en", "s"), (1, say("a"), "en", "s"), (2, None, None, None), (None, say("b"), None, "s"), (3, "", "en", None)]
    docs = spark.createDataFrame([(*r, *range(len(extra))) for r in rows], "doc_id long, text string, lang string, source string, " + ", ".join(f"{c} long" for c in extra))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        for table in (docs, docs.limit(0)):
            out = stage(spark, table, "")
            assert out.columns == docs.columns, name
            assert {tuple(r) for r in out.collect()} <= {tuple(r) for r in docs.collect()}, name
    assert corpus_pipeline.pack(spark, docs, "").agg(F.sum("length")).first()[0] > 0
