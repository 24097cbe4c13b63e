"""Per-object state of a query: one wide row per object.

For predicate i: ``m{i}`` done mask, ``ws{i}`` weighted sum of outputs, ``qs{i}`` sum of weights; the
predicate probability is ``ws/qs``. All later steps on one object are narrow projections of this row.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.entropy import entropy_bits
from ..functions.tagexpr import Pred, match_probability, predicates
from ..model import Catalog
from .scorers import outputs, whole


@dataclass(frozen=True)
class Calibration:
    """Maps from raw output to probability by (type, tag, scorer).

    ``rates``: shares of objects with the tag by bin of output. ``curves``: a fitted map instead, either
    ("sigmoid", slope, intercept) or ("isotonic", outputs, rates) with linear steps between its points.
    """

    rates: dict = field(default_factory=dict)
    bins: int = 20
    curves: dict = field(default_factory=dict)

    def apply(self, raw: Column, type_name: str, tag, scorer: int) -> Column:
        curve = self.curves.get((type_name, tag, scorer))
        if curve and curve[0] == "sigmoid":
            return 1 / (1 + F.exp(-(F.lit(float(curve[1])) * raw + F.lit(float(curve[2])))))
        if curve:
            xs, ys, n = F.lit(np.array(curve[1], "float64")), F.lit(np.array(curve[2], "float64")), len(curve[1])
            k = F.size(F.filter(xs, lambda x: x <= raw))
            lo, hi = F.greatest(k, F.lit(1)), F.least(k + 1, F.lit(n))
            x0, x1, y0, y1 = (F.element_at(a, i) for a, i in ((xs, lo), (xs, hi), (ys, lo), (ys, hi)))
            return F.when(x1 > x0, y0 + (y1 - y0) * (F.greatest(raw, x0) - x0) / (x1 - x0)).otherwise(y0)
        rates = self.rates.get((type_name, tag, scorer))
        if not rates:
            return raw
        at = F.least(F.floor(raw * self.bins), F.lit(self.bins - 1)).cast("int")
        return F.element_at(F.lit(np.array(rates, "float64")), at + 1)  # one literal: every plan that scores is analysed anew


@dataclass
class Query:
    """A tag expression over a catalog, with what has been learned."""

    expr: object
    catalog: Catalog
    calibration: Calibration = field(default_factory=Calibration)
    method: str = "auto"
    built: dict = field(default_factory=dict, init=False, repr=False, compare=False)

    def __post_init__(self):
        self.preds: list[Pred] = predicates(self.expr)

    def once(self, name: str, make, part=None):
        """What ``make()`` builds of this query and ``part``, built once: each call that makes a Column takes PySpark
        milliseconds, and every epoch needs the same ones."""
        known = self.built.get(name)
        if known is None or known[0] is not part:
            known = self.built[name] = (part, make())
        return known[1]

    def scorers(self, i: int):
        return self.catalog.of(self.preds[i].type)

    def full_mask(self, i: int) -> int:
        return sum(1 << s.number for s in self.scorers(i))

    def probability(self, i: int) -> Column:
        return F.col(f"ws{i}") / F.col(f"qs{i}")

    def match(self, probs: list[Column]) -> Column:
        return match_probability(self.expr, dict(zip(self.preds, probs)), self.method)

    def output(self, i: int, scorer, truth_has_tag: Column, key: str = "object_id") -> Column:
        """Calibrated output of a simulated scorer for predicate i, flipped for ``!=``."""
        p = self.preds[i]
        return self.adjusted(i, scorer, scorer.column(F.col(key), truth_has_tag, self.catalog.type(p.type).number(p.tag)))

    def adjusted(self, i: int, scorer, raw: Column) -> Column:
        """A raw output of any scorer, calibrated, and flipped for ``!=``."""
        p = self.preds[i]
        out = self.calibration.apply(raw, p.type, p.tag, scorer.number)
        return 1.0 - out if p.op == "!=" else out


def with_probabilities(state: DataFrame, query: Query) -> DataFrame:
    """Adds ``p{i}`` and ``match_p`` in one projection each."""


    def make():
        k = len(query.preds)
        probs = {f"p{i}": F.when(F.col(f"m{i}") == 0, F.lit(0.5)).otherwise(query.probability(i)) for i in range(k)}
        return probs, query.match([F.col(f"p{i}") for i in range(k)])

    probs, match = query.once("probabilities", make)
    return state.withColumns(probs).withColumn("match_p", match)


def raw_columns(query: Query) -> list[str]:
    return ["object_id", *[f"{c}{i}" for i in range(len(query.preds)) for c in ("m", "ws", "qs")]]


def raw_outputs(objects: DataFrame, catalog: Catalog, type_name: str, tag, scorers, keep: tuple[str, ...] = ()) -> DataFrame:
    """``object_id``, the columns of ``keep``, and the raw output ``f<number>`` of each scorer.

    Simulated scorers are Columns of the objects; any other kind scores the objects in a branch of its own,
    whose outputs are joined by id.
    """
    t = catalog.type(type_name)
    cols = [s.column(F.col("object_id"), F.col(t.truth) == F.lit(tag), t.number(tag)).alias(f"f{s.number}") for s in scorers if s.column is not None]
    out = objects.select("object_id", *keep, *cols)
    for s in scorers:
        if s.column is None:
            out = out.join(s.apply(objects, tag).select("object_id", F.col("prob").alias(f"f{s.number}")), "object_id")
    return out


def seed_state(objects: DataFrame, query: Query) -> DataFrame:
    """State after the seed scorer of each type has run on every object: a narrow projection where all are Columns."""
    cols: list[Column] = [F.col("object_id")]
    base = objects
    for i, p in enumerate(query.preds):
        s, t = query.catalog.seed(p.type), query.catalog.type(p.type)
        if s.column is not None:
            out = query.output(i, s, F.col(t.truth) == F.lit(p.tag))
        else:
            scored = raw_outputs(objects, query.catalog, p.type, p.tag, [s])
            base = base.join(scored.select("object_id", F.col(f"f{s.number}").alias(f"__seed{i}")), "object_id")
            out = query.adjusted(i, s, F.col(f"__seed{i}"))
        cols += [F.lit(1 << s.number).alias(f"m{i}"), (F.lit(s.quality) * out).alias(f"ws{i}"), F.lit(float(s.quality)).alias(f"qs{i}")]
    return with_probabilities(base.select(*cols), query)


def state_from_log(objects: DataFrame, log: DataFrame, query: Query) -> DataFrame:
    """State rebuilt from an output log ``object_id, pred, scorer, prob``; objects without rows have mask 0."""
    return with_probabilities(_merge(empty_state(objects, query), log, query), query)


def empty_state(objects: DataFrame, query: Query) -> DataFrame:
    cols = [F.col("object_id")]
    for i in range(len(query.preds)):
        cols += [F.lit(0).alias(f"m{i}"), F.lit(0.0).alias(f"ws{i}"), F.lit(0.0).alias(f"qs{i}")]
    return objects.select(*cols)


def _quality(query: Query) -> Column:
    """Quality of the row's (pred, scorer) as a literal lookup."""
    arms = [((F.col("pred") == i) & (F.col("scorer") == s.number), s.quality) for i in range(len(query.preds)) for s in query.scorers(i)]
    return reduce(lambda c, arm: c.when(arm[0], F.lit(float(arm[1]))), arms[1:], F.when(arms[0][0], F.lit(float(arms[0][1]))))


def _merge(state: DataFrame, rows: DataFrame, query: Query) -> DataFrame:
    """Fold output rows into the raw state columns. One shuffle of the rows, which the budget bounds."""


    def make():
        aggs = []
        for i in range(len(query.preds)):
            mine = F.col("pred") == i
            aggs += [
                F.coalesce(F.bit_or(F.when(mine, F.expr("shiftleft(1, scorer)"))), F.lit(0)).alias(f"dm{i}"),
                F.coalesce(F.sum(F.when(mine, F.col("q") * F.col("prob"))), F.lit(0.0)).alias(f"dws{i}"),
                F.coalesce(F.sum(F.when(mine, F.col("q"))), F.lit(0.0)).alias(f"dqs{i}"),
            ]
        cols = [F.col("object_id")]
        for i in range(len(query.preds)):
            cols += [F.col(f"m{i}").bitwiseOR(F.coalesce(f"dm{i}", F.lit(0))).alias(f"m{i}")]
            cols += [(F.col(f"{c}{i}") + F.coalesce(f"d{c}{i}", F.lit(0.0))).alias(f"{c}{i}") for c in ("ws", "qs")]
        return _quality(query), aggs, cols

    quality, aggs, cols = query.once("merge", make)
    delta = rows.withColumn("q", quality).groupBy("object_id").agg(*aggs)
    return state.select(*raw_columns(query)).join(delta, "object_id", "left").select(*cols)


def apply_outputs(state: DataFrame, rows: DataFrame, query: Query) -> DataFrame:
    """State after output rows ``object_id, pred, scorer, prob``; only touched objects change."""
    return with_probabilities(_merge(state, rows, query), query)


def state_vector(state: DataFrame, query: Query) -> DataFrame:
    """``object_id, pred, mask, probability, uncertainty`` in long form."""
    cells = F.array(*[F.struct(F.lit(i).alias("pred"), F.col(f"m{i}").alias("mask"), F.col(f"p{i}").alias("probability"), entropy_bits(F.col(f"p{i}")).alias("uncertainty")) for i in range(len(query.preds))])
    return state.select("object_id", F.inline(cells))


def cached_log(objects: DataFrame, query: Query, percent: int, scorer: int = 3) -> DataFrame:
    """Stored outputs of earlier queries: the seed for every object, and ``scorer`` for ``percent`` of them."""
    parts = []
    for i, p in enumerate(query.preds):
        for s in query.scorers(i):
            if s.number == query.catalog.seed(p.type).number:
                rows = objects
            elif s.number == scorer:
                rows = objects.where(F.pmod(whole(F.col("object_id"), 7), F.lit(100)) < percent)
            else:
                continue
            scored = raw_outputs(rows, query.catalog, p.type, p.tag, [s])
            parts.append(scored.select("object_id", F.lit(i).alias("pred"), F.lit(s.number).alias("scorer"), query.adjusted(i, s, F.col(f"f{s.number}")).alias("prob")))
    return reduce(DataFrame.unionByName, parts)


def all_outputs(objects: DataFrame, query: Query) -> list[list[Column]]:
    """Raw outputs of every scorer for every predicate, as Columns of ``objects``."""
    return [outputs(objects, query.catalog.type(p.type), p.tag, query.scorers(i)) for i, p in enumerate(query.preds)]
