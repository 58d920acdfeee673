"""Corpus pipeline: quality classifier, similarity join, benchmark decontamination, secret scan, packing.

Every stage but the last returns the columns of documents, whatever further columns these have. Null texts count as
empty for every decision and stay null; empty and very long texts are judged like all others; rows that repeat as a whole
are copies, of which the second stage keeps one; rows that share an id but not a text are two documents until packing; an
empty table passes through as one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from benchvary.llm import decontaminate, jaccard_join, packing, quality, secrets
from benchvary.session import forget, materialize

#: Least quality score of a document that stays.
LEAST_QUALITY = 0.5


def _free(docs: DataFrame, name: str) -> str:
    """A column name that docs doesn't have."""
    while name in docs.columns:
        name += "_"
    return name


#: Most rows (of ids and text keys) that are sent to every executor; more are joined.
SENT_ROWS = 1 << 19


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """docs without the rows that gone, a written table, names by all its columns."""
    return docs.join(F.broadcast(gone) if gone.count() <= SENT_ROWS else gone, gone.columns, "left_anti")


def filter_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble doesn't reject; it is fitted on this stage's own labelled documents.

    Without labels of both kinds nothing is rejected. A document without text has statistics like any other.
    """
    slim = docs.select("doc_id", "text")
    stats = materialize(quality.text_statistics(slim), "statistics")
    model = quality.train(stats, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    forget(stats)
    row = _free(docs, "document")
    whole = docs.select(F.struct(*docs.columns).alias(row))
    return quality.text_statistics(whole, keep=(row,), within=row).where(model.score() >= LEAST_QUALITY).select(f"{row}.*")


def keep_one_of_similar(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that with the smallest id, of each group joined by five-word shingles at 0.8; empty ones stay.

    Of rows that repeat id and text, one stays.
    """
    groups = materialize(jaccard_join.similar_groups(docs, n_words=5, threshold=(80, 100)), "groups")
    key = _free(docs, "text_key")
    gone = materialize(groups.where("component_id != doc_id").select("doc_id", F.col("text_key").alias(key)).distinct(), "gone")
    kept = _without(docs.withColumn(key, F.xxhash64("text")), gone)
    again = groups.where("component_id = doc_id").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    if not again.isEmpty():
        kept = kept.join(again, "doc_id", "left_anti").unionByName(kept.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id", key]))
    return kept.select(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark passage; an id with one goes with all its rows."""
    leaks = decontaminate.find_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select("doc_id").distinct()
    return _without(docs, materialize(leaks, "leaks")).select(*docs.columns)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with reported secrets replaced and n_chars, where there is one, brought up to date."""
    clean = secrets.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns) if "n_chars" in docs.columns else clean


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the packed token row, with their ids; an empty document is its separator."""
    return packing.concatenate_and_cut(docs)


STAGES = [
    ("quality", filter_quality),
    ("similar", keep_one_of_similar),
    ("decontamination", drop_leaks),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]

#: Trained scores, components and a tokeniser have no SQL form; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after another, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        done, docs = docs, materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        if name != STAGES[0][0]:
            forget(done)
    return STAGES[-1][1](spark, docs, sf_dir)
