"""Readers for the given tables and durable intermediates."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_own: list[str] = []


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for n in names or TABLES:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def work_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a folder of our own where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not _own:
        local = spark.sparkContext.master.split("[")[0] == "local"
        _own.append("file://" + tempfile.mkdtemp(prefix="semjoin-") if local else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/semjoin-work")
    return _own[0]


def keep(df: DataFrame, tag: str) -> DataFrame:
    """Write df once and read it from then on: paid answers are never asked for twice."""
    path = f"{work_folder(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def write_calls(calls: DataFrame, path: str) -> None:
    """Append a call log as JSON lines, partitioned by stage."""
    calls.write.mode("append").partitionBy("stage").json(path)


CALLS = "call_id string, attempt int, model string, n_a int, n_b int, in_tok long, out_tok long, status string, stage string"


def read_calls(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CALLS).json(path)
