"""Queries of the ten operators over their whole tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from featgreedy.llm import chat, decontam, embeddup, linededup, mixing, ominhash, quality, suffix, tokencount, toxicity


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def op1_chat_format(spark, sf_dir):
    return chat.contract(_t(spark, sf_dir, "conversations"))


def op2_line_dedup(spark, sf_dir):
    return linededup.contract(_t(spark, sf_dir, "documents"))


def op3_toxicity(spark, sf_dir):
    return toxicity.contract(_t(spark, sf_dir, "documents"), _t(spark, sf_dir, "labels"))


def op4_decontaminate(spark, sf_dir):
    return decontam.contract(_t(spark, sf_dir, "documents"), _t(spark, sf_dir, "benchmark"))


def op5_mix_sources(spark, sf_dir):
    return mixing.contract(_t(spark, sf_dir, "documents"))


def op6_suffix_dedup(spark, sf_dir):
    return suffix.contract(_t(spark, sf_dir, "documents"))


def op7_token_counts(spark, sf_dir):
    return tokencount.contract(_t(spark, sf_dir, "documents"))


def op8_near_vectors(spark, sf_dir):
    return embeddup.contract(_t(spark, sf_dir, "embeddings"))


def op9_quality(spark, sf_dir):
    return quality.contract(_t(spark, sf_dir, "documents"), _t(spark, sf_dir, "labels"))


def op10_near_documents(spark, sf_dir):
    return ominhash.contract(_t(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_chat_format, op2_line_dedup, op3_toxicity, op4_decontaminate, op5_mix_sources, op6_suffix_dedup, op7_token_counts, op8_near_vectors, op9_quality, op10_near_documents)}
ORACLES = {"op1_chat_format": chat.ORACLE, "op5_mix_sources": mixing.ORACLE, "op8_near_vectors": embeddup.ORACLE}
