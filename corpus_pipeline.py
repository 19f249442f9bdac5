"""A corpus pipeline of five stages over `documents`: quality rules, line dedup, near-duplicate removal,
benchmark decontamination, packing. Each stage's result is written and read again by the next one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from semjoin.llm import decontaminate, linededup, packing, quality, simhash
from semjoin.llm.common import materialize, stage_scope


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the risk-controlled rules reject go."""
    with stage_scope(docs):
        return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier line repeats, exactly or within one edit, are cut; emptied documents go."""
    with stage_scope(docs):
        return linededup.first_lines(docs, near_chars=linededup.NEAR_CHARS, every=True)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates one row stays, of the smallest id; texts that share an id are told apart."""
    with stage_scope(docs):
        return simhash.first_of_group(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    with stage_scope(docs):
        return decontaminate.without_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in length buckets and token-budget batches."""
    with stage_scope(docs):
        return packing.pack(docs)


STAGES = [
    ("quality_rules", quality_stage),
    ("line_dedup", line_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("packing", packing_stage),
]

#: Not SQL: components over fingerprints, edit distances by deletion and the dynamic program need more.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
