"""The queries of this subpackage: each applies one operator to its whole table, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import ann, chat, flac, html_main, langid, neardup, packing, pii, sharding, wfst


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), keep_ids=False)


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(_table(spark, sf_dir, "documents"))


def op3_flac(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.store_and_read_back(_table(spark, sf_dir, "documents"))


def op4_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.link_conversations(_table(spark, sf_dir, "conversations"))


def op4_chat_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.conversation_results(_table(spark, sf_dir, "conversations"))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.detect(_table(spark, sf_dir, "documents"))


def op6_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_main.extract(_table(spark, sf_dir, "pages"))


def op7_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(_table(spark, sf_dir, "embeddings"))


def op8_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.predict_documents(_table(spark, sf_dir, "documents"))


def op9_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.classes(_table(spark, sf_dir, "documents"))


def op10_wfst(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wfst.digests(_table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_packing, op2_sharding, op3_flac, op4_chat, op5_pii, op6_html, op7_ann, op8_langid, op9_neardup, op10_wfst, op4_chat_results)}


def oracle_sql() -> dict[str, str]:
    """DuckDB SQL where it can express a query; the others are tested against brute force, round trips or held-out rows."""
    return {"op4_chat": chat.ORACLE}
