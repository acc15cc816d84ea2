"""The corpus pipeline: five stages, each over all that the one before has kept.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
documents. Rows whose id is null pass through the joins under a stand-in id. Stages bear null and empty
texts: language identification rejects them, so later stages meet texts with letters only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.llm import common, decontamination, exact_dedup, language_id, near_dedup, packing

COLUMNS, PERCENT = common.DOCUMENT_COLUMNS, 80


def _without(docs: DataFrame, dropped: DataFrame, *keys: str) -> DataFrame:
    """docs without the rows that match dropped on all keys, null ids matching each other."""
    stand_in = {k: F.coalesce(F.col(k).cast("string"), F.lit("none")) for k in keys}
    return docs.join(dropped.select(*(c.alias(f"dropped_{k}") for k, c in stand_in.items())).distinct(), [c == F.col(f"dropped_{k}") for k, c in stand_in.items()], "left_anti")


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts of which no language can be told (null, or without a letter) go; where lang is null, the predicted one stands."""
    model = language_id.train(docs.select("doc_id", "text", "lang"))
    kept = language_id.predict(docs, model, COLUMNS).where(F.col("lang_pred") != language_id.UNKNOWN)
    return kept.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the largest doc_id stays."""
    found = common.written(exact_dedup.duplicates(docs), "copies")
    named = docs.select(*COLUMNS).withColumn("text_sha", F.sha2(F.coalesce("text", F.lit("")), 256))
    dropped = found.where("NOT kept").select("doc_id", F.col("text_sha256").alias("text_sha"))
    rest = _without(named, dropped, "doc_id", "text_sha")
    repeated = found.where("kept").groupBy("doc_id", "text_sha256").count().where("count > 1")
    return (rest if repeated.isEmpty() else rest.dropDuplicates(["doc_id", "text_sha"])).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five words, PERCENT or more) stays, the one with the smallest doc_id."""
    found = near_dedup.near_duplicates(docs, PERCENT).where("NOT kept")
    named = docs.select(*COLUMNS).withColumn("text_hash", F.xxhash64(F.coalesce("text", F.lit(""))))
    return _without(named, found, "doc_id", "text_hash").select(*COLUMNS)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go, and so do rows that share such a document's id."""
    found = decontamination.leaks(docs, common.read_table(spark, sf_dir, "benchmark"))
    return _without(docs.select(*COLUMNS), found, "doc_id")


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of what is left, with the sequence and offset of each."""
    return packing.pack(packing.token_pieces(docs))


STAGES = [
    ("language_id", identify_language),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("decontamination", drop_benchmark_leaks),
    ("packing", pack_sequences),
]

#: SQL can't express the language model, the tokenizer or the packing; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
