"""Joins on uncertain tags: pairs of objects that have the same tag."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def tag_distribution(probs: DataFrame, least: float = 0.0) -> DataFrame:
    """``object_id, tag, p`` with p scaled to a sum of 1 for each object; tags under ``least`` are left out of
    the pairs (their mass is reported by ``dropped_mass``)."""
    total = probs.groupBy("object_id").agg(F.sum("p").alias("total"))
    return probs.join(total, "object_id").select("object_id", "tag", (F.col("p") / F.col("total")).alias("p")).where((F.col("p") > 0) & (F.col("p") >= least))


def dropped_mass(probs: DataFrame, least: float) -> DataFrame:
    kept = tag_distribution(probs, least).groupBy("object_id").agg(F.sum("p").alias("kept"))
    return kept.agg(F.max(1 - F.col("kept")).alias("most_dropped"), F.avg(1 - F.col("kept")).alias("mean_dropped"))


def tag_join(left: DataFrame, right: DataFrame, key: list[str] | None = None, least: float = 0.0, cutoff: float = 0.0) -> DataFrame:
    """``left_id, right_id, p``: p is the sum over tags of both probabilities.

    An equality join on the tag (and on ``key``, exact columns that both sides share) then an aggregate by
    pair; there is no product of all objects with all objects.
    """
    key = key or []
    a = left.select(F.col("object_id").alias("left_id"), "tag", F.col("p").alias("pl"), *key)
    b = right.select(F.col("object_id").alias("right_id"), "tag", F.col("p").alias("pr"), *key)
    pairs = a.where(F.col("pl") >= least).join(b.where(F.col("pr") >= least), ["tag", *key])
    return pairs.groupBy("left_id", "right_id").agg(F.sum(F.col("pl") * F.col("pr")).alias("p")).where(F.col("p") > cutoff)


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """An inner join whose hot keys spread over ``salts`` tasks: the big side is salted by its other columns,
    the small side repeats each row for every salt."""
    others = [c for c in big.columns if c != key]
    left = big.withColumn("salt", F.pmod(F.xxhash64(*others), F.lit(salts)).cast("int"))
    right = small.withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(salts)])))
    return left.join(right, [key, "salt"]).drop("salt")


def as_of(points: DataFrame, facts: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """For each point, the last ``value`` of its group at or before it: one union and one window by group."""
    from pyspark.sql import Window as W

    both = points.select(by, at, F.lit(1).alias("kind"), F.lit(None).cast(facts.schema[value].dataType).alias(value)).unionByName(facts.select(by, at, F.lit(0).alias("kind"), value))
    last = F.last(value, ignorenulls=True).over(W.partitionBy(by).orderBy(at, "kind").rowsBetween(W.unboundedPreceding, 0))
    return both.withColumn(value, last).where("kind = 1").drop("kind")
