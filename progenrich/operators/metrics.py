"""Accuracy and cost measures of answers, curves and plans."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..session import cut


def f_measure(hit: float, size: float, relevant: float, alpha: float = 1.0) -> float:
    return (1 + alpha) * hit / (alpha * relevant + size) if alpha * relevant + size else 0.0


def true_quality(answer: DataFrame, truth: DataFrame, alpha: float = 1.0) -> DataFrame:
    """Precision, recall and F of the ids in ``answer`` against those in ``truth``."""
    a = answer.select("object_id", F.lit(1).alias("a"))
    t = truth.select("object_id", F.lit(1).alias("t"))
    s = a.join(t, "object_id", "full_outer").agg(F.count(F.when(F.col("a").isNotNull() & F.col("t").isNotNull(), 1)).alias("hit"), F.count("a").alias("size"), F.count("t").alias("relevant"))
    return s.select(
        F.when(F.col("size") > 0, F.col("hit") / F.col("size")).otherwise(0.0).alias("precision"),
        F.when(F.col("relevant") > 0, F.col("hit") / F.col("relevant")).otherwise(0.0).alias("recall"),
        F.when(alpha * F.col("relevant") + F.col("size") > 0, (1 + alpha) * F.col("hit") / (alpha * F.col("relevant") + F.col("size"))).otherwise(0.0).alias("f_measure"),
    )


def gain_curve(curve: DataFrame) -> DataFrame:
    """``gain`` of each epoch: (F1 - first F1) / (greatest F1 of the approach - first F1); 0 without a rise."""
    by = W.partitionBy("approach")
    first = F.first("f1").over(by.orderBy("epoch").rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    rise = F.max("f1").over(by) - first
    return curve.withColumn("gain", F.when(rise > 0, (F.col("f1") - first) / rise).otherwise(0.0))


def epoch_improvement(curve: DataFrame, value: str = "f1") -> DataFrame:
    before = F.lag(value).over(W.partitionBy("approach").orderBy("epoch"))
    return curve.withColumn("improvement", F.col(value) - F.coalesce(before, F.col(value)))


def sample_points(curves: DataFrame, points: int = 10) -> DataFrame:
    """``points`` equal steps up to the least total cost among the approaches."""
    last = curves.groupBy("approach").agg(F.max("spent").alias("end")).agg(F.min("end").alias("horizon"))
    return last.select("horizon", F.explode(F.sequence(F.lit(1), F.lit(points))).alias("i")).select("i", (F.col("horizon") * F.col("i") / points).alias("v"), "horizon")


def weight(i: Column, v: Column, horizon: Column, points: int = 10, weighting: str | Callable = "previous") -> Column:
    """``previous``: 1 - v(i-1)/v(max); ``printed``: 1 - (v(i) - 1)/v(max); both at least 0; or a function."""
    if callable(weighting):
        return weighting(i, v, horizon)
    if weighting == "printed":
        return F.greatest(F.lit(0.0), 1 - (v - 1) / horizon)
    return F.greatest(F.lit(0.0), 1 - (i - 1) / points)


def progressiveness(curves: DataFrame, value: str = "gain", points: int = 10, weighting: str | Callable = "previous") -> DataFrame:
    """Weighted sum of improvements between sample points; the value at a point is that of the last epoch
    finished by then (an as-of lookup: curves and points are both tiny)."""
    at = curves.select("approach").distinct().join(F.broadcast(sample_points(curves, points)), how="cross")
    c = curves.select(F.col("approach").alias("approach"), F.col("spent"), F.col(value).alias("value"), "epoch")
    asof = at.join(c, "approach").where(F.col("spent") <= F.col("v") + 1e-9).groupBy("approach", "i", "v", "horizon").agg(F.max_by("value", "epoch").alias("value"))
    start = curves.groupBy("approach").agg(F.min_by(value, "epoch").alias("start"))
    steps = asof.join(start, "approach")
    before = F.coalesce(F.lag("value").over(W.partitionBy("approach").orderBy("i")), F.col("start"))
    steps = steps.withColumn("term", weight(F.col("i"), F.col("v"), F.col("horizon"), points, weighting) * (F.col("value") - before))
    return steps.groupBy("approach").agg(F.sum("term").alias("progressiveness"))


def work_stats(log: DataFrame) -> DataFrame:
    """Items and cost by epoch, predicate and scorer, with totals (rollup)."""
    return log.rollup("epoch", "pred", "scorer").agg(F.count("*").alias("items"), F.sum("cost").alias("cost"))


def repeat_summary(runs: DataFrame, value: str) -> DataFrame:
    """Mean and deviation over repeated runs."""
    return runs.groupBy("approach").agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("deviation"), F.count("*").alias("runs"))


def selectivity(df: DataFrame, condition: Column | str) -> DataFrame:
    c = F.expr(condition) if isinstance(condition, str) else condition
    return df.agg(F.avg(c.cast("double")).alias("selectivity"))


def rank_agreement(items: DataFrame, a: str, b: str) -> DataFrame:
    """Share of item pairs that two benefits order alike.

    Items of equal benefits are counted together: the pairs are those of distinct (a, b), with the product of their
    numbers, and the pairs within one, which agree. Quadratic in distinct values alone.
    """
    groups = cut(items.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").alias("n")))
    other = groups.select(F.col("a").alias("a2"), F.col("b").alias("b2"), F.col("n").alias("n2"))
    ahead = (F.col("a") < F.col("a2")) | ((F.col("a") == F.col("a2")) & (F.col("b") < F.col("b2")))
    same = F.signum(F.round(F.col("a") - F.col("a2"), 9)) == F.signum(F.round(F.col("b") - F.col("b2"), 9))
    apart = groups.join(other, ahead).select((F.col("n") * F.col("n2")).alias("pairs"), same.alias("same"))
    within = groups.select(F.expr("n * (n - 1) div 2").alias("pairs"), F.lit(True).alias("same"))
    pairs, agree = F.coalesce(F.sum("pairs"), F.lit(0)), F.sum(F.when(F.col("same"), F.col("pairs")).otherwise(0))
    return apart.unionByName(within).agg(F.when(pairs > 0, agree / pairs).alias("agreement"), pairs.alias("pairs"))


def monotone_report(curve: DataFrame) -> DataFrame:
    """Epochs after which the expected F fell."""
    fell = epoch_improvement(curve, "expected_f")
    return fell.groupBy("approach").agg(F.count(F.when(F.col("improvement") < -1e-9, 1)).alias("falls"), F.count("*").alias("epochs"))


def plan_report(df: DataFrame) -> dict:
    """Counts of costly operators in the physical plan: exchanges, sorts, windows, Python steps, joins."""
    import re

    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: len(re.findall(p, text)) for k, p in {"exchange": r"\bExchange\b", "single": "SinglePartition", "window": r"\bWindow\b", "sort": r"\bSort\b", "python": "Python|Pandas|Arrow", "cartesian": "CartesianProduct", "nested_loop": "BroadcastNestedLoopJoin", "broadcast": "BroadcastExchange"}.items()}
