import duckdb

import __spark_entry__ as entry
from charprobe import streaming
from charprobe.operators import corpus, stats
from charprobe.sources import SCHEMAS, StagedVocabularySource

SMALL = "/root/testdata/sf0.001"
CHECKED = ["benchmark_antijoin", "one_letter_accuracy", "strength_bins", "boundary_mi_shuffled", "word_counts", "fixed_width_tokens", "matched_sample", "boundary_pairs", "scramble_letters", "staged_merges"]


def test_queries_match_sql(spark):
    con = duckdb.connect()
    for t in [*SCHEMAS]:
        con.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries)
    for name in CHECKED:
        got = queries[name](spark, SMALL)
        cols = sorted(got.columns)
        a = sorted(map(str, (tuple(r[c] for c in cols) for r in got.collect())))
        b = con.execute(sql[name]).df()
        assert a == sorted(map(str, b[cols].astype(object).itertuples(index=False, name=None))), name


def test_stream_equals_batch(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    docs.repartition(4).write.parquet(str(tmp_path / "in"))
    q = streaming.running_boundary_counts(streaming.document_stream(spark, str(tmp_path / "in"))).writeStream.outputMode("complete").format("memory").queryName("bounds").start()
    q.processAllAvailable()
    q.stop()
    assert spark.table("bounds").exceptAll(stats.fixed_boundary_pairs(corpus.words(docs))).count() == 0


def test_staged_source(spark):
    spark.dataSource.register(StagedVocabularySource)
    df = spark.read.format("staged_vocab").option("letters", "abc").load()
    assert df.count() == 2 * (3 + 9 + 27) and df.distinct().count() == df.count()


def test_queries_read_a_given_table(spark, tmp_path):
    """These made their data up: now what they return follows the tables."""
    spark.createDataFrame([(1, "ab Abba", "en", "x", 7), (2, "zz", "de", "x", 2)], SCHEMAS["documents"]).coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    spark.sql("SELECT event_id, timestamp_ntz'2024-01-01 00:00:00' AS ts, event_id AS user_id, 'a' AS event_type, 1.0D AS value, '' AS props FROM VALUES (0L), (1000L), (2000L), (12001L) t(event_id)").coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    con = duckdb.connect()
    for t in ("documents", "events"):
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    queries, sql = entry.queries(), entry.oracle_sql()
    rows = {"lr_schedule": 4, "token_budget": 1, "staged_vocab": 2 * (2 + 4 + 8), "staged_merges": 2 * (2 + 4 + 8) - 2, "merge_strength": 4}
    for name, n in rows.items():
        got = queries[name](spark, str(tmp_path))
        a = sorted(map(str, map(tuple, got.collect())))
        assert len(a) == n and a == sorted(map(str, con.execute(sql[name]).df()[got.columns].astype(object).itertuples(index=False, name=None))), name
    assert queries["token_budget"](spark, str(tmp_path)).first()["repeated"] == 13_107_200_000 - 3
