"""Tables and edge lists in and out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: The tables of the test data.
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def sql_over(spark: SparkSession, sf_dir: str, text: str, **more: DataFrame) -> DataFrame:
    """Spark SQL in which ``{name}`` stands for a table of ``sf_dir`` or for one of ``more``."""
    used = {t: load(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in text}
    return spark.sql(text, **used, **more)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """parent, child from parquet, orc, json or csv; a malformed row is an error."""
    reader = spark.read.schema("parent long, child long")
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.format(fmt).load(path)


def read_nodes(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    reader = spark.read.schema("node_id long, label string")
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.format(fmt).load(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None) -> None:
    writer = df.write.format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
