"""Corpus pipeline: identify the language, drop repeated lines, near copies and benchmark leaks, and pack what stays.

Every stage takes what its predecessor kept, written as Parquet and read again; all but the last return the
columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.llm import decontaminate, language_id, line_dedup, ngram_join, packing
from provgraph.llm.common import discard, made, remove, shared_dir, small_batches, table
from provgraph.llm.queries import TOKENIZERS


def identify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents whose language can't be told: null, empty and letterless texts."""
    small_batches(spark)
    return language_id.keep_identified(docs, language_id.fitted(docs))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes later matches of lines from the texts, and documents of which no line is left. n_chars follows."""
    small_batches(spark)
    kept = line_dedup.remove_lines(docs).filter((F.col("n_removed") == 0) | F.col("text").rlike(r"[^\x20\x09-\x0D]")).select(*docs.columns)
    return kept.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else kept


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest identifier of each component of near copies, and all without words. Of rows that repeat one
    identifier and text one stays; a null identifier stays only in a component without any other."""
    small_batches(spark)
    return ngram_join.one_of_each(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item. Null texts, and repeated rows each on its own, are judged as find_items() does; null
    and repeated items change nothing."""
    small_batches(spark)
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places of all remaining documents' pieces in sequences: a null text has the end id alone, a repeated row pieces of its own, and
    pieces of one length go by identifier."""
    small_batches(spark)
    return packing.pack(docs, f"{TOKENIZERS}/word_bpe_49k.json")


STAGES = [("language_id", identify), ("line_dedup", drop_lines), ("near_copies", drop_near_copies), ("decontamination", drop_leaks), ("packing", pack)]

#: SQL cannot express kernel regression or the packing plan.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table of documents; what a stage made is deleted when its successor has been written."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path, mark = f"{shared_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}", made()
        stage(spark, docs, sf_dir).write.parquet(path)
        discard(mark)
        if before:
            remove(spark, before)
        docs, before = spark.read.parquet(path), path
    return docs
