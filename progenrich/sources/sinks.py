"""Sinks: round trips through file formats, and the output log of scorers."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def work_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder of the session (a local one only where none is set)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or "/tmp/checkpoints"
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """Written in a format and read again with the explicit schema."""
    path = work_path(df.sparkSession, fmt)
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(path)
    reader = df.sparkSession.read.format(fmt).options(**options)
    return (reader if fmt == "text" else reader.schema(df.schema)).load(path)


def write_log(log: DataFrame, path: str | None = None, overwrite_partitions: bool = False) -> str:
    """Append scorer outputs to a log partitioned by type and scorer, or replace just the partitions given."""
    path = path or work_path(log.sparkSession, "log")
    w = log.write.partitionBy("tag_type", "scorer")
    if overwrite_partitions:
        w.mode("overwrite").option("partitionOverwriteMode", "dynamic").parquet(path)
    else:
        w.mode("append").parquet(path)
    return path


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """A bucketed and sorted table, so that later joins on the key need no shuffle.

    The rows lie in the shared folder, under a fresh name that begins with ``name``.
    """
    path = work_path(df.sparkSession, name)
    fresh = path.rsplit("/", 1)[1].replace("-", "_")
    df.write.option("path", path).bucketBy(buckets, key).sortBy(key).saveAsTable(fresh)
    return df.sparkSession.table(fresh)


def write_jdbc(df: DataFrame, url: str, name: str, connections: int = 8, mode: str = "append", **properties: str) -> None:
    """Rows to a database table over at most ``connections`` connections at a time."""
    df.coalesce(connections).write.jdbc(url, name, mode, {k: str(v) for k, v in properties.items()})


def read_jdbc(spark: SparkSession, url: str, name: str, key: str, connections: int = 8, **properties: str) -> DataFrame:
    """A database table, read in ``connections`` ranges of an integer key; filters and columns are pushed down.

    The bounds come from one aggregate in the database. Rows outside them or with a null key are read as well.
    """
    given = {k: str(v) for k, v in properties.items()}
    ends = spark.read.jdbc(url, f"(SELECT MIN({key}) AS LO, MAX({key}) AS HI FROM {name}) ends", properties=given).first()
    if ends[0] is None or ends[0] == ends[1]:
        return spark.read.jdbc(url, name, properties=given)
    return spark.read.jdbc(url, name, column=key, lowerBound=int(ends[0]), upperBound=int(ends[1]) + 1, numPartitions=connections, properties=given)
