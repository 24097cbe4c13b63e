"""The join form of the operator: pairs of objects that agree on exact columns and on an uncertain tag, over epochs."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.tagexpr import parse_tag_expr
from ..model import Catalog
from ..session import cut
from .cutoff import Answer, choose_answer
from .execution import execute_plan
from .metrics import f_measure
from .planning import NextScorer, make_items, select_plan, with_rank
from .state import Calibration, Query, apply_outputs, seed_state


@dataclass
class PairEpoch:
    number: int
    spent: float
    items: int
    answer: Answer
    f1: float | None
    pairs: DataFrame = field(repr=False)

    def members(self) -> DataFrame:
        return self.answer.members(self.pairs).select("left_id", "right_id", "match_p", F.lit(self.number).alias("epoch"))


def tag_query(catalog: Catalog, type_name: str, calibration: Calibration | None = None) -> Query:
    """A query with one predicate for each tag of the type, in the order of its domain."""
    expr = parse_tag_expr(" OR ".join(f"{type_name} = {tag!r}" for tag in catalog.type(type_name).domain))
    return Query(expr, catalog, calibration or Calibration())


def distribution(state: DataFrame, query: Query) -> DataFrame:
    """``object_id, pred, p``: the probabilities of all tags of an object, scaled to a sum of 1; a narrow map."""
    k = range(len(query.preds))
    total = sum((F.col(f"p{i}") for i in k), F.lit(0.0))
    cells = F.array(*[F.struct(F.lit(i).alias("pred"), (F.col(f"p{i}") / total).alias("p")) for i in k])
    return state.where(total > 0).select("object_id", F.inline(cells)).where(F.col("p") > 0)


def tag_items(state: DataFrame, query: Query, table: NextScorer) -> DataFrame:
    """``side, object_id, pred, scorer, cost, p, p_est``: a narrow branch for each tag. All tags in one projection would
    be too much generated code for types of many tags."""
    out = None
    for i, pred in enumerate(query.preds):
        one = state.select(F.struct("side", "object_id").alias("object_id"), F.col(f"m{i}").alias("m0"), F.col(f"p{i}").alias("p0"), F.col(f"p{i}").alias("match_p"))
        items = make_items(one, Query(pred, query.catalog, query.calibration), table)
        part = items.select("object_id.side", "object_id.object_id", F.lit(i).alias("pred"), "scorer", "cost", "p", "p_est")
        out = part if out is None else out.unionByName(part)
    return out


class PairRun:
    """A run over two collections of objects with distinct ids on each side.

    ``key`` names exact columns that both sides share; without one, pairs would be all objects of a tag with all others,
    so it is required, and null keys pair with nothing. Pairs whose probability is at most ``least`` are no candidates.
    An item's benefit is the sum over its object's pairs outside the answer of ``P * (P + dP)``, per cost; when no such
    pair has a scorer left, all pairs are considered.
    """

    def __init__(self, left: DataFrame, right: DataFrame, key: list[str], query: Query, budget: float, table: NextScorer | None = None, alpha: float = 1.0, least: float = 0.0):
        if not key:
            raise ValueError("a join on an uncertain tag needs exact columns as well")
        self.sides, self.key, self.query, self.budget = (left, right), key, query, float(budget)
        self.table, self.alpha, self.least = table or NextScorer({}), alpha, least
        self.states = [cut(seed_state(side, query)) for side in self.sides]
        types = {p.type for p in query.preds}
        truth = query.catalog.type(next(iter(types))).truth
        self.truth = None
        if len(types) == 1 and all(truth in side.columns for side in self.sides):
            a = left.select(F.col("object_id").alias("left_id"), truth, *key)
            self.truth = cut(a.join(right.select(F.col("object_id").alias("right_id"), truth, *key), [truth, *key]).select("left_id", "right_id"))
            self.relevant = self.truth.count()

    def shares(self) -> DataFrame:
        """``left_id, right_id, pred, pl, pr``: what each tag could add to each pair."""
        l, r = (distribution(s, self.query).join(o.select("object_id", *self.key), "object_id") for s, o in zip(self.states, self.sides))
        l = l.withColumnsRenamed({"object_id": "left_id", "p": "pl"})
        r = r.withColumnsRenamed({"object_id": "right_id", "p": "pr"})
        return l.join(r, ["pred", *self.key]).select("left_id", "right_id", "pred", "pl", "pr")

    def pairs(self, shares: DataFrame) -> DataFrame:
        return shares.groupBy("left_id", "right_id").agg(F.sum(F.col("pl") * F.col("pr")).alias("match_p")).where(F.col("match_p") > self.least)

    def items(self, shares: DataFrame, pairs: DataFrame) -> DataFrame:
        """Ranked items of both sides; those of the right have ``pred`` raised by the number of tags, so that orders are total."""
        k, reach, gains = len(self.query.preds), shares.join(pairs, ["left_id", "right_id"]), None
        for side, (mine, other) in enumerate((("left_id", "pr"), ("right_id", "pl"))):
            base = pairs.groupBy(F.col(mine).alias("object_id")).agg(F.sum(F.col("match_p") * F.col("match_p")).alias("base"))
            lift = reach.groupBy(F.col(mine).alias("object_id"), "pred").agg(F.sum(F.col("match_p") * F.col(other)).alias("lift"))
            part = base.join(lift, "object_id").select(F.lit(side).alias("side"), "object_id", "pred", "base", "lift")
            gains = part if gains is None else gains.unionByName(part)
        both = self.states[0].withColumn("side", F.lit(0)).unionByName(self.states[1].withColumn("side", F.lit(1)))
        items = tag_items(both, self.query, self.table).join(gains, ["side", "object_id", "pred"])
        ranked = with_rank(items.withColumn("benefit", (F.col("base") + (F.col("p_est") - F.col("p")) * F.col("lift")) / F.col("cost")))
        return ranked.select("object_id", (F.col("pred") + F.col("side") * k).alias("pred"), "scorer", "cost", "rank_key")

    def _epoch(self, number: int, spent: float, n: int) -> tuple[PairEpoch, DataFrame]:
        shares = cut(self.shares())
        pairs = cut(self.pairs(shares))
        answer = choose_answer(pairs, self.alpha)
        f1 = None
        if self.truth is not None:
            hit = answer.members(pairs).join(self.truth, ["left_id", "right_id"], "left_semi").count()
            f1 = f_measure(hit, answer.size, self.relevant, self.alpha)
        return PairEpoch(number, spent, n, answer, f1, pairs), shares

    def epochs(self, most: int) -> Iterator[PairEpoch]:
        """The answer of the seeds (epoch 0), then one an epoch, until no object of a pair has a scorer left."""
        k, spent = len(self.query.preds), 0.0
        epoch, shares = self._epoch(0, 0.0, 0)
        yield epoch
        for number in range(1, most + 1):
            outside = epoch.pairs.where(F.col("match_p") <= F.lit(epoch.answer.ratio))
            plan = cut(select_plan(cut(self.items(shares, outside)), self.budget))
            if plan.isEmpty():
                plan = cut(select_plan(cut(self.items(shares, epoch.pairs)), self.budget))
            side_of = (F.col("pred") >= k).cast("int").alias("side")
            counts = {r["side"]: r for r in plan.groupBy(side_of).agg(F.count("*").alias("n"), F.sum("cost").alias("cost")).collect()}
            if not counts:
                return
            for side, r in counts.items():
                mine = plan.where(F.col("pred") >= k if side else F.col("pred") < k).withColumn("pred", F.col("pred") - side * k)
                outputs = cut(execute_plan(mine, self.sides[side], self.query, r["n"]))
                self.states[side] = cut(apply_outputs(self.states[side], outputs, self.query))
            spent += sum(r["cost"] for r in counts.values())
            epoch, shares = self._epoch(number, spent, sum(r["n"] for r in counts.values()))
            yield epoch


def enrich_join(left: DataFrame, right: DataFrame, key: list[str], type_name: str, budget: float, catalog: Catalog, **settings) -> PairRun:
    """Start a run over the pairs that agree on ``key`` and on the tag of a type."""
    return PairRun(left, right, key, tag_query(catalog, type_name), budget, **settings)
