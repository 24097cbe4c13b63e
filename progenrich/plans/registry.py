"""Registration of queries with the SQL they must agree with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
#: Decimal places to which doubles are rounded on both sides.
PLACES = 6


def rounded(df: DataFrame) -> DataFrame:
    doubles = {f.name for f in df.schema.fields if f.dataType.simpleString() == "double"}
    return df.select(*[(F.round(F.col(f"`{c}`"), PLACES) + F.lit(0.0)).alias(c) if c in doubles else F.col(f"`{c}`") for c in df.columns])


def query(name: str, sql: str | None = None, doubles: str = ""):
    """Register a function of (spark, sf_dir); ``doubles`` names the double columns of the SQL."""

    def add(fn):
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = lambda spark, sf_dir: rounded(fn(spark, sf_dir))
        QUERIES[name].__name__ = name
        if sql is not None:
            parts = ", ".join(f"round({c}, {PLACES}) + 0.0::DOUBLE AS {c}" for c in doubles.split())
            ORACLES[name] = f"SELECT * REPLACE ({parts}) FROM ({sql})" if parts else sql
        return fn

    return add
