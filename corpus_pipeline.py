"""The corpus pipeline: five stages over documents, each an operator of ugraph.llm, each written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ugraph.llm.common import materialise
from ugraph.llm.mixing import mix_documents
from ugraph.llm.near_dedup import drop_near_duplicates
from ugraph.llm.packing import pack_documents
from ugraph.llm.pii import masked, session_key
from ugraph.llm.quality_rules import keep_good

#: Near-duplicate stages work on five-word shingles and a similarity of 0.8 or more.
STAGE_WORDS, STAGE_PERCENT = 5, 80


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the isolation forest."""
    return keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one of least doc_id."""
    return drop_near_duplicates(docs, STAGE_PERCENT, STAGE_WORDS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with pseudonyms for personal numbers, dates and addresses."""
    return masked(docs, session_key(spark))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the source weights take them."""
    return mix_documents(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in windows of token ids."""
    return pack_documents(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("personal_data", personal_data), ("mixing", mixing), ("packing", packing)]

#: Tokenisation and the forest have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
