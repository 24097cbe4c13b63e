"""Execution of a plan: the payload of planned objects meets their scorers."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .state import Query

#: Plans up to this many items are broadcast; larger ones meet the payload by a shuffle join.
BROADCAST_ITEMS = 500_000


def execute_plan(plan: DataFrame, payload: DataFrame, query: Query, items: int | None = None) -> DataFrame:
    """``object_id, pred, scorer, prob, cost`` for each item.

    Simulated scorers are Columns, so all items run in one pass over the fetched payload; other scorers
    run in a branch each, on their own objects alone. ``items`` is the size of the plan where known.
    """
    n = plan.count() if items is None else items
    wanted = plan.select("object_id", "pred", "scorer", "cost")
    wanted = F.broadcast(wanted) if n <= BROADCAST_ITEMS else wanted
    fetched = payload.join(wanted, "object_id")
    if sum(s.column is None for i in range(len(query.preds)) for s in query.scorers(i)) > 1:
        fetched = cut(fetched)  # several branches read it: the payload of planned objects is fetched once
    branches = []
    for i, p in enumerate(query.preds):
        for s in query.scorers(i):
            if s.column is None:
                mine = fetched.where((F.col("pred") == i) & (F.col("scorer") == s.number))
                done = s.apply(mine, p.tag).select("object_id", query.calibration.apply(F.col("prob"), p.type, p.tag, s.number).alias("prob"))
                prob = 1.0 - F.col("prob") if p.op == "!=" else F.col("prob")
                branches.append(done.select("object_id", F.lit(i).alias("pred"), F.lit(s.number).alias("scorer"), prob.alias("prob"), F.lit(float(s.cost)).alias("cost")))
    prob = query.once("outputs", lambda: _column_outputs(query))
    if prob is not None:
        branches.append(fetched.select("object_id", "pred", "scorer", prob.alias("prob"), "cost").where("prob IS NOT NULL"))
    return reduce(DataFrame.unionByName, branches)


def _column_outputs(query: Query) -> Column | None:
    """The output of an item's scorer, of those that are Columns; None where none is."""
    arms = []
    for i, p in enumerate(query.preds):
        t = query.catalog.type(p.type)
        arms += [((F.col("pred") == i) & (F.col("scorer") == s.number), query.output(i, s, F.col(t.truth) == F.lit(p.tag))) for s in query.scorers(i) if s.column is not None]
    return reduce(lambda c, arm: c.when(*arm), arms[1:], F.when(*arms[0])) if arms else None
