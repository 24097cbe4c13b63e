"""A session for tests, and the comparison of a query with its SQL in DuckDB."""

from __future__ import annotations

import glob
import math
import os
import sys

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.01")


def session():
    from pyspark.sql import SparkSession

    return (
        SparkSession.builder.master("local[8]").appName("tests").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )


def duck(sf: str = SF):
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for p in glob.glob(f"{sf}/*.parquet"):
        name = os.path.basename(p)[: -len(".parquet")]
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{p}{'/*' if os.path.isdir(p) else ''}')")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.10g}") + 0.0
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    if hasattr(v, "asDict"):
        return plain(tuple(v))
    if isinstance(v, dict):
        return sorted((str(k), plain(x)) for k, x in v.items())
    return v


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return [names[i] for i in order], sorted((tuple(plain(r[i]) for i in order) for r in rows), key=repr)


def differences(spark, name: str, query, sql: str, con, sf: str = SF) -> str:
    """Empty when both give the same columns and rows."""
    df = query(spark, sf)
    a_names, a = rows_of(df.columns, [tuple(r) for r in df.collect()])
    got = con.execute(sql)
    b_names, b = rows_of([d[0] for d in got.description], got.fetchall())
    if a_names != b_names:
        return f"{name}: columns {a_names} and {b_names}"
    if len(a) != len(b):
        return f"{name}: {len(a)} and {len(b)} rows"
    bad = [(x, y) for x, y in zip(a, b) if repr(x) != repr(y)]
    return f"{name}: {len(bad)} of {len(a)} rows differ, as {bad[0]}" if bad else ""
