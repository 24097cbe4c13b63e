"""Queries for the kinds of pandas functions: iterators that load a model once, groups, and grouped aggregates.

Groups are bins that were aggregated before, so what one task holds is bounded by the number of bins.
"""

# No postponed annotations here: Spark reads the types of pandas functions from their hints.
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F

from ..sources.tables import table
from .registry import query

#: Width and number of the bins of quantities.
BINS = 10


def _model():
    """A model that is dear to load: here the weights of a line."""
    return {"slope": 0.25, "offset": 2.0}


@query("fn_pandas_iterator", "SELECT o_orderkey, 0.25 * o_totalprice + 2.0 AS score FROM orders", "score")
def _(spark, sf):
    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m = _model()  # once for each task, not for each batch
        for b in batches:
            yield m["slope"] * b + m["offset"]

    return table(spark, sf, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", score("o_totalprice").alias("score"))


@query("fn_pandas_scalar", "SELECT o_orderkey, o_totalprice * o_totalprice AS squared FROM orders", "squared")
def _(spark, sf):
    @F.pandas_udf("double")
    def square(x: pd.Series) -> pd.Series:
        return x * x

    return table(spark, sf, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", square("o_totalprice").alias("squared"))


def _binned(spark, sf):
    at = F.floor(F.col("l_quantity") / BINS).cast("long")
    return table(spark, sf, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag", at.alias("bin")).agg(F.count("*").alias("n"))


_BINNED_SQL = f"SELECT l_returnflag, CAST(floor(l_quantity / {BINS}) AS BIGINT) AS bin, count(*) AS n FROM lineitem GROUP BY ALL"


@query("agg_pandas_grouped", f"SELECT l_returnflag, sum(bin * n) / sum(n) AS mean_bin FROM ({_BINNED_SQL}) GROUP BY l_returnflag", "mean_bin")
def _(spark, sf):
    @F.pandas_udf("double")
    def weighted(x: pd.Series, n: pd.Series) -> float:
        return float((x * n).sum() / n.sum())

    return _binned(spark, sf).groupBy("l_returnflag").agg(weighted("bin", "n").alias("mean_bin"))


@query("agg_apply_pandas", f"SELECT l_returnflag, bin, sum(n) OVER (PARTITION BY l_returnflag ORDER BY bin) / sum(n) OVER (PARTITION BY l_returnflag) AS share FROM ({_BINNED_SQL})", "share")
def _(spark, sf):
    def shares(group: pd.DataFrame) -> pd.DataFrame:
        g = group.sort_values("bin")
        return g.assign(share=g["n"].cumsum() / g["n"].sum())[["l_returnflag", "bin", "share"]]

    return _binned(spark, sf).groupBy("l_returnflag").applyInPandas(shares, "l_returnflag string, bin long, share double")
