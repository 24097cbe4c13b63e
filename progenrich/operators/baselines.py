"""Baselines: orders of work items that do not plan, and none at all."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .state import Query

#: Modulus and factors of the repeatable "random" order (fixed values).
PRIME = 1000003


def every_item(state: DataFrame, query: Query) -> DataFrame:
    """All items not yet run: ``object_id, pred, scorer, cost, match_p``."""
    cells = [F.struct(F.lit(i).alias("pred"), F.lit(s.number).alias("scorer"), F.lit(float(s.cost)).alias("cost"), F.col(f"m{i}").alias("mask")) for i in range(len(query.preds)) for s in query.scorers(i)]
    rows = state.select("object_id", "match_p", F.inline(F.array(*cells)))
    return rows.where(F.col("mask").bitwiseAND(F.expr("shiftleft(1, scorer)")) == 0).drop("mask")


def scorer_order(query: Query) -> dict[tuple[int, int], int]:
    """Rank of (pred, scorer) by quality per cost, best first."""
    each = sorted(((-s.ratio, i, s.number) for i in range(len(query.preds)) for s in query.scorers(i)))
    return {(i, s): k for k, (_, i, s) in enumerate(each)}


def _rank_of(query: Query):
    arms = [((F.col("pred") == i) & (F.col("scorer") == s), F.lit(k)) for (i, s), k in scorer_order(query).items()]
    return reduce(lambda c, arm: c.when(*arm), arms[1:], F.when(*arms[0]))


#: Steps of probability told apart in one rank key.
P_STEPS = 10**9


def _by_probability():
    return F.lit(P_STEPS) - F.floor(F.col("match_p") * P_STEPS)


def scorer_first(first: DataFrame, query: Query) -> DataFrame:
    """One scorer over all objects, by starting match probability, then the next scorer. ``first`` holds
    the items at the start; the order never changes."""
    key = -(_rank_of(query).cast("long") * (2 * P_STEPS) + _by_probability())
    return first.withColumn("rank_key", key.cast("long"))


def object_first(first: DataFrame, query: Query) -> DataFrame:
    """One object after the other, by starting match probability; all its predicates and scorers.

    Items of one object tie in the key; the order by object, predicate and scorer settles them.
    """
    return first.withColumn("rank_key", F.floor(F.col("match_p") * P_STEPS).cast("long"))


def random_epoch(state: DataFrame, query: Query, epoch: int, seed: int = 1, pool: str = "remaining") -> DataFrame:
    """Random objects with a random predicate and scorer among those left, by repeatable arithmetic.

    ``pool='applied'`` draws from the scorers already run, which changes nothing; it is kept for the record.
    """
    items = every_item(state, query)
    if pool == "applied":
        cells = [F.struct(F.lit(i).alias("pred"), F.lit(s.number).alias("scorer"), F.lit(float(s.cost)).alias("cost"), F.col(f"m{i}").alias("mask")) for i in range(len(query.preds)) for s in query.scorers(i)]
        items = state.select("object_id", "match_p", F.inline(F.array(*cells))).where(F.col("mask").bitwiseAND(F.expr("shiftleft(1, scorer)")) != 0).drop("mask")
    mix = F.pmod((F.col("object_id") % PRIME) * 7919 + F.col("pred") * 15485863 + F.col("scorer") * 32452843 + F.lit(epoch * 49979687 + seed * 67867967), F.lit(PRIME))
    pick = items.withColumn("mix", mix).groupBy("object_id").agg(F.min(F.struct("mix", "pred", "scorer", "cost", "match_p")).alias("m"))
    spread = F.pmod((F.col("object_id") % PRIME) * 104729 + F.lit(epoch * 1299709 + seed * 15485863), F.lit(PRIME))
    return pick.select("object_id", "m.pred", "m.scorer", "m.cost", "m.match_p").withColumn("rank_key", spread.cast("long"))
