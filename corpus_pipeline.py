"""The corpus pipeline: toxicity, quality, near duplicates, personal data, packing, in this order.

Each stage gets what the stage before kept, with the columns of documents; the last returns the pieces of the packed
sequences. The two classifiers learn from the labelled documents under sf_dir, by the rules of their operators.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from shapebalance.llm.common import Work
from shapebalance.llm.neardup import deduplicated
from shapebalance.llm.packing import pack_documents
from shapebalance.llm.pii import redact_documents
from shapebalance.llm.quality import keep_good, train_quality
from shapebalance.llm.toxicity import keep_clean, train_toxicity


def _tables(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain does not reject."""
    return keep_clean(docs, train_toxicity(*_tables(spark, sf_dir)))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine predicts to be good."""
    return keep_good(docs, train_quality(*_tables(spark, sf_dir)))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group of near duplicates (five-word shingles, likeness 0.8)."""
    return deduplicated(docs)


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced by its kind."""
    return redact_documents(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents with their places in sequences of 2048 ids."""
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("toxicity", toxicity), ("quality", quality), ("near_dedup", near_dedup), ("pii", pii), ("packing", packing)]
#: Classifiers and packing are beyond SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents, each result but the last written as Parquet and read again."""
    docs, work = _tables(spark, sf_dir)[0], Work(spark)
    for name, stage in STAGES[:-1]:
        docs = work.table(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
