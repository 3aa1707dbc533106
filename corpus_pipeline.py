"""Stages of corpus preparation: each is one operator, and each works on all that its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from contrastmine.llm import decontaminate, jaccard, packing, secret_scan, toxicity
from contrastmine.llm.queries import tokenizer_path
from contrastmine.llm.shared import clear_scratch, fresh_path, scratch_mark, table, worker_batches


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that the toxicity model rejects; null and empty texts stay, repeated rows go or stay alike."""
    worker_batches(spark)
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of each group of near copies; texts without words are copies of each other, and each text without an id stays once."""
    worker_batches(spark)
    return jaccard.keep_one(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that hold a benchmark item, edited or not; null and empty texts stay."""
    worker_batches(spark)
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their texts replaced by a mark; null texts stay null."""
    return secret_scan.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece of every document; a null text is its end id only, repeated rows are packed like any other."""
    worker_batches(spark)
    return packing.pack_answers(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("secrets", redact_secrets),
    ("packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order; each result is written as Parquet to the shared folder and read again.

    When a stage is written, its intermediate tables and its input, if an earlier stage wrote it, are deleted."""
    docs = table(spark, sf_dir, "documents")
    begin = scratch_mark()
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        clear_scratch(spark, begin, keep=(path,))
    return docs


ORACLE_SQL = None  # no SQL for tokenisation or fuzzy matching; tested against brute force
