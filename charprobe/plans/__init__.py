"""Registered queries, their SQL twins and the experiment drivers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import corpus, encode, measure, mlp, probe, tokenize, vocab
from ..sources import table


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed-width tokens of English documents, their vocabulary and vectors, a matched sample, the probe, and its accuracy by letter."""
    words = corpus.words(table(spark, sf_dir, "documents").where("lang = 'en'"))
    tokens = tokenize.fixed_width_tokens(words)
    v = vocab.target_vocab(vocab.build(tokens, 1000))
    vectors = encode.distributional(encode.sequences(tokens, v), 2, 32)
    sample = probe.split_pairs(probe.sample_matched(probe.label(v)))
    return measure.accuracy_by_letter_and_all(mlp.fit_predict(sample, vectors))
