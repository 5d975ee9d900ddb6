"""The corpus pipeline: each stage takes (spark, docs, sf_dir), is written as Parquet and read again for the next."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from featgreedy.llm import decontam, linededup, mixing, ominhash, quality
from featgreedy.llm.common import shared_dir, small, stored


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def reject_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go; labels are read by id, texts from ``docs``."""
    return quality.keep_good(docs, _t(spark, sf_dir, "labels"), least=0.5)


def remove_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Aligned common blocks go from the later document, near copies of a whole are left to the next stage; a document that loses all its lines goes too."""
    out = linededup.drop_blocks(docs, spare=0.8).filter("n_removed = 0 OR n_removed < n_lines")
    held = {c: F.col(f"_{c}") if c in linededup.ADDED else F.col(c) for c in docs.columns}
    held["text"] = F.col("kept_text")
    if "n_chars" in held:
        held["n_chars"] = F.when(F.col("n_removed") > 0, F.length("kept_text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return out.select(*[held[c].alias(c) for c in docs.columns])


def drop_near_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays."""
    return ominhash.drop_near(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item within its error budget go."""
    bad = decontam.contaminated(docs, _t(spark, sf_dir, "benchmark")).filter("contaminated")
    bad = stored(bad.select("doc_id", "_t").distinct().withColumnsRenamed({"doc_id": "__fg_d", "_t": "__fg_u"}), "leaks")
    same = F.col("doc_id").eqNullSafe(F.col("__fg_d")) & F.xxhash64("text").eqNullSafe(F.col("__fg_u"))
    return docs.join(small(bad), same, "left_anti")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with the words that the mix takes of them."""
    return mixing.mix(docs)


STAGES = [
    ("quality classifier", reject_low_quality),
    ("line dedup", remove_common_lines),
    ("near-duplicate documents", drop_near_documents),
    ("benchmark decontamination", drop_contaminated),
    ("source mixing", mix_sources),
]

#: No SQL: three stages are models, alignments or sketches. tests/llm compares each with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _t(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{shared_dir(spark)}/featgreedy/pipeline-{uuid.uuid4().hex}/{name.replace(' ', '-')}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
