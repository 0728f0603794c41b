"""A corpus pipeline: language ID, line dedup, near-duplicate join, decontamination, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ontospark.llm import decontaminate, jaccard_join, langid, line_dedup, packing
from ontospark.llm._frames import bounded, cut, small_batches, table


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is rejected (no letter, or too little confidence) go."""
    small_batches(spark)
    return langid.drop_rejected(docs, langid.train(docs))


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of runs of lines go; a document of which nothing else was left goes too. n_chars follows the text."""
    out = line_dedup.drop_repeated_lines(docs).where("_removed = 0 OR _removed < _lines")
    chars = F.when(F.col("_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", chars).select(docs.columns)


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the document with the least id stays, once."""
    small_batches(spark)
    found = cut(jaccard_join.similar(docs))
    gone = cut(found.where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct())
    out = docs.join(bounded(gone), F.col("doc_id") == F.col("_gone"), "left_anti")
    twice = cut(found.groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias("_twice")))
    if twice.isEmpty():
        return out
    again = F.col("doc_id").eqNullSafe(F.col("_twice"))
    once = out.join(bounded(twice), again, "left_semi").dropDuplicates(["doc_id", "text"])
    return out.join(bounded(twice), again, "left_anti").unionByName(once)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.drop_leaks(docs, table(spark, sf_dir, "benchmark")).select(docs.columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every remaining document, cut and packed into sequences of 2048 tokens."""
    small_batches(spark)
    return packing.pack(docs)


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup_stage),
    ("ngram_jaccard_join", ngram_jaccard_join),
    ("benchmark_decontamination", benchmark_decontamination),
    ("packing", packing_stage),
]

#: SQL can't express language ID or tokenising; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir))
    return docs
