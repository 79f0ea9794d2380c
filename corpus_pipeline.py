"""The corpus pipeline: quality, near-duplicates, benchmark passages, secrets, packing.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return the
columns of documents. Stages are written as Parquet and read again, so a lost executor costs one stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.conf import Table
from vertexalg.llm import common as C
from vertexalg.llm.decontamination import keep_clean
from vertexalg.llm.near_dedup import keep_first
from vertexalg.llm.packing import pack
from vertexalg.llm.quality_classifier import keep_good, learn
from vertexalg.llm.secret_scan import redact


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go. Null and empty texts are scored as empty ones; without labels all stay; an
    empty table stays empty; ids may be null or repeat, each row is judged by its text."""
    return keep_good(docs, learn(docs.select("doc_id", "text"), C.table(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near-duplicates stays: that of the least id (null first), of rows of one id the first. Null
    and empty texts have no duplicates and all stay; an empty table stays empty."""
    return keep_first(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go; null and empty texts hold none; an empty benchmark removes nothing.
    Each row is judged by its text, whatever its id."""
    return keep_clean(docs, C.table(spark, sf_dir, "benchmark"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; every row stays, and n_chars follows its text (as it was where the text is null)."""
    return redact(docs).withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text").cast("long")).otherwise(F.col("n_chars")))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows with their places in sequences of 2048 tokens: a null or empty text is one token, a null id
    stays null, an empty table gives no row."""
    return pack(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("secrets", secrets), ("packing", packing)]

#: The classifier and the tokenizer cannot be expressed in SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = C.table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        with C.scratch():  # what a stage wrote on its way goes once its result is written
            kept = Table(stage(spark, docs, sf_dir), name)
        if before is not None:
            before.delete()
        docs, before = kept.df, kept
    return STAGES[-1][1](spark, docs, sf_dir)
