"""The training-data pipeline: quality classifier, quality rules, near duplicates, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes each stage's rows as Parquet to the
shared folder and reads them again for the next. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from charprobe.llm import jaccard, mixing, packing, pu_quality, quality_rules
from charprobe.llm.common import staged, text_key
from charprobe.llm.token_ids import default_vocabulary

#: A learnt stage has no SQL, so the rows of run() have none.
ORACLE_SQL = None


def _labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def _by_place(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with its columns named by place, so that no name of theirs meets one of ours; and the new name of each."""
    names = {c: f"c{k}" for k, c in enumerate(docs.columns)}
    return docs.toDF(*names.values()), names


def _rejected(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """docs without those whose id and text are in rows; null ids compare as equal, and so do null texts."""
    bad = rows.select(F.col("doc_id").alias("bad_id"), F.col("text_key").alias("bad_key")).distinct()
    held, name = _by_place(docs)
    left = held.join(bad, F.col(name["doc_id"]).eqNullSafe(F.col("bad_id")) & (text_key(F.col(name["text"])) == F.col("bad_key")), "left_anti")
    return left.toDF(*docs.columns)


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts; null and empty texts are scored like others; without labels all stay."""
    scored = pu_quality.score_quality(docs, _labels(spark, sf_dir), keyed=True)
    return _rejected(docs, scored.where("predicted = 0"))


def quality_rule_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that keep to the rules; null and empty texts have too few words and go; repeated rows are judged alike."""
    judged = quality_rules.judge_quality(docs, _labels(spark, sf_dir), keyed=True)
    return _rejected(docs, judged.where("not kept"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies; texts without words are groups of their own, rows alike in id and text one row."""
    return jaccard.representatives(docs, jaccard.jaccard_components(docs, 5, 80))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn so that sources, languages and topics reach their target weights; null ones are categories of their own.

    The draw goes by id and text: rows without an id would all stay or go by one draw. Repeated rows stay or go together.
    """
    held, name = _by_place(docs)
    text = F.col(name["text"])
    row = F.concat_ws("|", F.col(name["doc_id"]).cast("string"), text_key(text).cast("string"))
    keyed = held.withColumn("topic", mixing.form_topic(text)).withColumn("row", row)
    mixed = mixing.mix(keyed, [name["source"], name["lang"], "topic"], mixing.word_count(text), keep=None, id_col="row")
    return mixed.where("mix_kept").select(*name.values()).toDF(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences; null texts count as empty, null ids come first."""
    return packing.pack_documents(docs, default_vocabulary())


STAGES = [("quality classifier", quality_classifier), ("quality rules", quality_rule_filter), ("n-gram jaccard join", near_duplicates), ("mixing", mixture), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
