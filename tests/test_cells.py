import threading

import pytest

from charprobe.plans import experiments

SMALL = "/root/testdata/sf0.001"


def met(monkeypatch, spark, n):
    """Every cell waits here for another one; those taken one after another would never meet."""
    gate = threading.Barrier(n, timeout=60)
    pred = spark.createDataFrame([("a", 1, 1, 1, True)], "letter string, y int, correct int, n_letters int, has_space boolean")

    def scored(*_, **__):
        gate.wait()
        return pred

    monkeypatch.setattr(experiments, "scored", scored)
    monkeypatch.setattr(experiments, "_bpe", lambda rows: rows)


def test_cells_of_languages_run_at_the_same_time(spark, monkeypatch):
    met(monkeypatch, spark, 6)
    rows = experiments.languages(spark, SMALL).collect()
    assert sorted((r["experiment"], r["col_label"]) for r in rows) == [(x, k) for x in ("de", "es", "fr") for k in ("original", "scrambled")]


def test_a_failed_cell_is_told(spark):
    def fails():
        raise ValueError("cell")

    assert experiments.at_once(spark, [lambda: 1, lambda: 2, lambda: 3], 2) == [1, 2, 3]
    with pytest.raises(ValueError, match="cell"):
        experiments.at_once(spark, [lambda: 1, fails, lambda: 3], 1)


def test_models_share_one_vocabulary_and_run_at_the_same_time(spark, monkeypatch):
    gate, counts = threading.Barrier(experiments.AT_ONCE, timeout=60), []
    pred = spark.createDataFrame([("a", 1, 1, 1, True)], "letter string, y int, correct int, n_letters int, has_space boolean")
    first = iter(range(experiments.AT_ONCE))  # the others may come when these have gone

    def embedded(v, *_, **__):
        if next(first, None) is not None:
            gate.wait()
        return v.select("token_id")

    monkeypatch.setattr(experiments, "embedded", embedded, raising=False)
    monkeypatch.setattr(experiments, "judged", lambda *_, **__: pred)
    monkeypatch.setattr(experiments.encode, "external_vectors", lambda _, v: embedded(v))
    monkeypatch.setattr(experiments.pieces, "counted", lambda rows, count=experiments.pieces.counted: counts.append(1) or count(rows))
    rows = experiments.table1_models(spark, SMALL).collect()
    assert [(r["experiment"], r["col_label"]) for r in rows][::2] == [(n, "matched") for n in ("skipgram", "causal", "masked", "distributional", "symmetric", "external", "random", "letters")]
    assert len(rows) == 16 and len(counts) == 1
