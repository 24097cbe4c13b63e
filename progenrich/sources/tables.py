"""The given tables, column by column as a query needs them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def register(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views for SQL users."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
