"""The subpackage's registered queries and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_retrieval_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(_docs(spark, sf_dir), with_ids=False)


def op2_tensored_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import near_duplicates

    return near_duplicates(_docs(spark, sf_dir))


def op3_id_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .id_store import store_digest

    return store_digest(_docs(spark, sf_dir))


def op4_png_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .media import media_digest

    return media_digest(_docs(spark, sf_dir))


def op5_systematic_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix_digest

    return mix_digest(_docs(spark, sf_dir))


def op6_rule_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import quality_digest

    return quality_digest(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op8_bayes_support_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_classifier import quality_scores

    return quality_scores(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op7_snapshot_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .chats import render

    return render(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def op9_suffix_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .repeats import repeats_digest

    return repeats_digest(_docs(spark, sf_dir))


def op10_feistel_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import pii_digest

    return pii_digest(_docs(spark, sf_dir))


def _sql() -> dict[str, str]:
    from .chats import CHAT_SQL
    from .mixing import MIX_SQL

    return {"op5_systematic_mixing": MIX_SQL, "op7_snapshot_collapse": CHAT_SQL}


QUERIES = {f.__name__: f for f in (op1_retrieval_packing, op2_tensored_minhash, op3_id_store, op4_png_media, op5_systematic_mixing, op6_rule_forest, op7_snapshot_collapse, op8_bayes_support_vectors, op9_suffix_levels, op10_feistel_pseudonyms)}
SQL = _sql()
