"""Cuts of lineage that survive lost executors: tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that a broadcast side may have.
BROADCAST_ROWS = 1_000_000
#: Ends the life of shuffle files with the statement that made them.
_FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``. Only a local session that names none gets a temporary folder."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        at = f"{tempfile.gettempdir()}/checkpoints"
        spark.conf.set("spark.checkpoint.dir", at)
    return at.rstrip("/")


def fresh_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """``df`` written as a table and read again; its shuffles leave no files behind."""
    spark, at = df.sparkSession, fresh_path(df.sparkSession, "step")
    before = spark.conf.get(_FREED)
    spark.conf.set(_FREED, "true")
    try:
        df.write.parquet(at)
    finally:
        spark.conf.set(_FREED, before)
    return spark.read.schema(df.schema).parquet(at)


def small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` marked for broadcast if ``rows``, its measured count, allows that."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df
