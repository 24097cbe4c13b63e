"""Planning of an epoch: candidates, work items, benefits, and the plan that fits the budget."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.entropy import entropy_bits, raised, root_columns
from .cutoff import Answer
from .state import Query

#: Benefits are compared after this many decimal places, so that orders agree between engines.
PLACES = 9


def select_candidates(state: DataFrame, answer: Answer, rule: str = "outside") -> DataFrame:
    """``outside``: objects that are not in the last answer; ``all``: every object; ``gaining``: as
    outside here, the guard applies to items, once their estimate is known."""
    if rule == "all":
        return state
    if rule in ("outside", "gaining"):
        return state.where(F.col("match_p") <= F.lit(answer.ratio))
    raise ValueError(f"unknown rule {rule!r}")


@dataclass(frozen=True)
class NextScorer:
    """Next-scorer table: (type, tag, mask, bin) -> (scorer, change of uncertainty), with fallbacks.

    Its size depends on types, masks and bins, never on objects; it is compiled into literal arrays.
    """

    cells: dict
    bins: int = 10

    def lookup(self, type_name: str, tag, mask: int, b: int) -> tuple[int, float] | None:
        for key in ((type_name, tag, mask, b), (type_name, tag, mask, None)):
            if key in self.cells:
                return self.cells[key]
        return None


def uncertainty_bin(h: Column, bins: int) -> Column:
    """Half-open bins of equal width, the last one closed."""
    return F.least(F.floor(h * bins), F.lit(bins - 1)).cast("int")


def _next(query: Query, table: NextScorer, i: int) -> Column:
    """Struct (scorer, delta) for predicate i by literal lookup on mask and bin; null when all have run."""
    p, scorers = query.preds[i], query.scorers(i)
    full, cells = query.full_mask(i), []
    for mask in range(full):
        rest = [s for s in scorers if not mask >> s.number & 1]
        default = max(rest, key=lambda s: (s.ratio, -s.number))
        cells += [table.lookup(p.type, p.tag, mask, b) or (default.number, 0.0) for b in range(table.bins)]
    at = F.col(f"m{i}") * table.bins + uncertainty_bin(F.col(f"h{i}"), table.bins) + 1
    scorer, delta = F.lit(np.array([c[0] for c in cells], "int32")), F.lit(np.array([c[1] for c in cells], "float64"))
    return F.when(F.col(f"m{i}") != full, F.struct(F.element_at(scorer, at).alias("scorer"), F.element_at(delta, at).alias("delta")))


def _cost(query: Query, i: int, scorer: Column) -> Column:
    arms = [(scorer == s.number, F.lit(float(s.cost))) for s in query.scorers(i)]
    return reduce(lambda c, arm: c.when(*arm), arms[1:], F.when(*arms[0]))


def make_items(candidates: DataFrame, query: Query, table: NextScorer) -> DataFrame:
    """One item for each object and predicate that has a scorer left: a narrow map of the state.

    ``object_id, pred, scorer, cost, h, h_est, p, p_est, match_p, match_est``.
    """
    steps, cells = query.once("items", lambda: _item_columns(query, table), table)
    for columns in steps:
        candidates = candidates.withColumns(columns)
    return candidates.select("object_id", cells).where("scorer IS NOT NULL")


def _item_columns(query: Query, table: NextScorer) -> tuple[list[dict[str, Column]], Column]:
    """The projections of ``make_items``, in order, and the items of a row."""
    k = len(query.preds)
    steps = [
        {f"h{i}": entropy_bits(F.col(f"p{i}")) for i in range(k)},
        {f"next{i}": _next(query, table, i) for i in range(k)},
        {f"he{i}": F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.col(f"h{i}") + F.col(f"next{i}.delta"))) for i in range(k)},
        *root_columns({f"up{i}": f"he{i}" for i in range(k)}),
        {f"pe{i}": raised(F.col(f"p{i}"), F.col(f"up{i}")) for i in range(k)},
    ]
    cells = []
    for i in range(k):
        probs = [F.col(f"pe{j}") if j == i else F.col(f"p{j}") for j in range(k)]
        cells.append(
            F.struct(
                F.lit(i).alias("pred"), F.col(f"next{i}.scorer").alias("scorer"), _cost(query, i, F.col(f"next{i}.scorer")).alias("cost"), F.col(f"h{i}").alias("h"), F.col(f"he{i}").alias("h_est"),
                F.col(f"p{i}").alias("p"), F.col(f"pe{i}").alias("p_est"), F.col("match_p"), query.match(probs).alias("match_est"),
            )
        )
    return steps, F.inline(F.array(*cells))


def benefit_relative(items: DataFrame) -> DataFrame:
    """``benefit = P * (P + dP) / cost``: constant work for an item."""
    return with_rank(items.withColumn("benefit", F.col("match_p") * F.col("match_est") / F.col("cost")))


def with_rank(items: DataFrame) -> DataFrame:
    return items.withColumn("rank_key", F.floor(F.col("benefit") * 10**PLACES).cast("long"))


def guard_gaining(items: DataFrame, answer: Answer) -> DataFrame:
    """Items predicted to raise the expected F: the estimate exceeds lambda * (1 + a * dP)."""
    lam = F.lit(answer.ratio)
    return items.where(F.col("match_est") > lam * (1 + answer.alpha * (F.col("match_est") - F.col("match_p"))))


#: Cuts of the answer that are compiled into literals; more of them meet the items by a join.
CUTS = 2000


def _near_cuts(state: DataFrame, answer: Answer) -> tuple[float, DataFrame]:
    """A value ``high`` and rows ``v, n, s``: the objects by match probability (2.0: all above ``high``), where the answer
    can end after one change.

    One object's new value moves the total by at most 1, and the sums and sizes of the sets by at most one object. So the
    best ratio stays within a range around the present one, about 2 / total wide; it takes all objects above itself and none below.
    """
    alpha, k = answer.alpha, answer.alpha * answer.total
    room = k - alpha - 1
    high = min(1.0, (answer.ratio * k + 1) / room * (1 + 1e-9)) if room > 0 else 1.0
    low = max(0.0, (answer.mass - 1) / (k + alpha + answer.size + 1) * (1 - 1e-9))
    p = F.col("match_p")
    return high, state.where(p >= low).groupBy(F.when(p > high, 2.0).otherwise(p).alias("v")).agg(F.count("*").alias("n"), F.sum("match_p").alias("s"))


def benefit_exact(items: DataFrame, state: DataFrame, answer: Answer, weighted: bool = False, most: int | None = None) -> DataFrame:
    """Benefit by definition: the best expected F with the item's estimate, less the present one, per cost.

    The answer is solved anew for every item, over every cut at which it can end: with the item's object taken out
    of the order, without or with its new value. Sums are concave along the order, so the best cut lies between two
    values of the match probability, and near the present one (``_near_cuts``): linear in items, nothing is
    approximated. ``most``: refuse more objects than that.
    """
    if most is not None and (n := state.count()) > most:
        raise ValueError(f"{n} objects, of {most} at most")
    alpha, (high, near) = answer.alpha, _near_cuts(state, answer)
    own, est = F.col("match_p"), F.col("match_est")
    total = F.lit(alpha) * (F.lit(answer.total) - own + est)

    def ratio(v, n, s):
        inside = (own >= v) | ((v > 1) & (own > high))
        base_s, base_n = s - F.when(inside, own).otherwise(0.0), n - F.when(inside, 1).otherwise(0)
        return F.greatest(F.when(base_n > 0, base_s / (total + base_n)).otherwise(0.0), (base_s + est) / (total + base_n + 1))

    rows = sorted(near.limit(CUTS + 1).collect(), key=lambda r: -r["v"])
    if len(rows) <= CUTS:
        cuts, n, s = [], 0, 0.0
        for r in rows:
            n, s = n + r["n"], s + r["s"]
            cuts.append((r["v"], n, s))
        arr = F.array(*[F.struct(F.lit(float(v)).alias("v"), F.lit(int(n)).alias("n"), F.lit(float(s)).alias("s")) for v, n, s in cuts])
        best = F.array_max(F.transform(arr, lambda c: ratio(c["v"], c["n"], c["s"]))) if cuts else F.lit(0.0)
        out = items.withColumn("f_est", (1 + alpha) * F.greatest(best, est / (total + 1)))
    else:
        order = W.orderBy(F.desc("v")).rowsBetween(W.unboundedPreceding, 0)
        cuts = near.select("v", F.sum("n").over(order).alias("n"), F.sum("s").over(order).alias("s"))
        both = items.select("object_id", "pred", "match_p", "match_est").join(F.broadcast(cuts), F.lit(True), "cross")
        solved = both.groupBy("object_id", "pred").agg(((1 + alpha) * F.greatest(F.max(ratio(F.col("v"), F.col("n"), F.col("s"))), F.max(est / (total + 1)))).alias("f_est"))
        out = items.join(solved, ["object_id", "pred"])
    gain = F.col("match_p") * F.col("f_est") / F.col("cost") if weighted else (F.col("f_est") - F.lit(answer.expected_f)) / F.col("cost")
    return with_rank(out.withColumn("benefit", gain))


def benefit_prefix(items: DataFrame, state: DataFrame, answer: Answer, bins: int = 512) -> DataFrame:
    """The exact benefit from sums by bin instead of objects: linear in items, the bins are literals.

    Equal to the exact one up to the objects that share a bin with the new cut.
    """
    at = F.least(F.floor(F.col("match_p") * bins), F.lit(bins - 1)).cast("int")
    rows = sorted(state.groupBy(at.alias("b")).agg(F.count("*").alias("n"), F.sum("match_p").alias("s")).collect(), key=lambda r: -r["b"])
    cuts, n, s = [(1.0, 0, 0.0)], 0, 0.0
    for r in rows:
        n, s = n + r["n"], s + r["s"]
        cuts.append((r["b"] / bins, n, s))
    arr = F.array(*[F.struct(F.lit(float(lo)).alias("lo"), F.lit(int(c)).alias("n"), F.lit(float(x)).alias("s")) for lo, c, x in cuts])
    own, est = F.col("match_p"), F.col("match_est")
    total = F.lit(answer.alpha) * (F.lit(answer.total) - own + est)

    def ratio(c):
        inside = F.when(own >= c["lo"], 1).otherwise(0)
        base_s, base_n = c["s"] - inside * own, c["n"] - inside
        return F.greatest(F.when(base_n > 0, base_s / (total + base_n)).otherwise(0.0), (base_s + est) / (total + base_n + 1))

    f_est = (1 + answer.alpha) * F.array_max(F.transform(arr, ratio))
    return with_rank(items.withColumn("f_est", f_est).withColumn("benefit", (F.col("f_est") - F.lit(answer.expected_f)) / F.col("cost")))


#: Cells of one refinement of the budget cut.
CUT_BINS = 1024
#: Items of the cut cell that are put in exact order.
CUT_ROWS = 50_000


@dataclass(frozen=True)
class Chosen:
    plan: DataFrame
    items: int
    cost: float
    available: int  # items there were to choose from


def select_plan(items: DataFrame, budget: float, overshoot: bool = True) -> DataFrame:
    """Items by ``rank_key`` descending, then object, predicate and scorer, until the budget is used."""
    return choose_plan(items, budget, overshoot).plan


def choose_plan(items: DataFrame, budget: float, overshoot: bool = True) -> Chosen:
    """The plan of ``select_plan``, its size and its cost.

    No global sort: costs are summed by cells of the rank key, the driver finds the cell in which the budget
    ends and refines it (then by object id, where keys are equal) until few items are left to order. The plan is a
    condition on the items: better cells, and the cut cell up to the last item that fits. With ``overshoot`` the last
    item may pass the budget.
    """
    bounds = items.selectExpr("min(rank_key) AS lo", "max(rank_key) AS hi", "min(object_id) AS ilo", "max(object_id) AS ihi", "sum(cost) AS cost", "count(*) AS n").first()
    if bounds["lo"] is None or budget <= 0:
        return Chosen(items.limit(0), 0, 0.0, bounds["n"])
    if bounds["cost"] <= budget:
        return Chosen(items, bounds["n"], bounds["cost"], bounds["n"])
    taken, spent, many, cell = "false", 0.0, 0, "true"  # conditions in SQL, as one call each
    for column, lo, hi, sign in (("rank_key", bounds["lo"], bounds["hi"], -1), ("object_id", bounds["ilo"], bounds["ihi"], 1)):
        while hi > lo:
            step = (hi - lo) // CUT_BINS + 1
            inside = f"({cell} AND {column} BETWEEN {lo} AND {hi})"
            rows = items.where(inside).selectExpr(f"CAST(floor(({column} - {lo}) / {step}) AS bigint) AS b", "cost").groupBy("b").agg(F.expr("sum(cost) AS cost"), F.expr("count(*) AS n")).collect()
            rows.sort(key=lambda r: sign * r["b"])
            cut = None
            for r in rows:
                if spent + r["cost"] >= budget:
                    cut = r
                    break
                spent, many = spent + r["cost"], many + r["n"]
            if cut is None:
                cut = rows[-1]
                spent, many = spent - cut["cost"], many - cut["n"]
            b_lo, b_hi = lo + cut["b"] * step, min(hi, lo + (cut["b"] + 1) * step - 1)
            better = f"{column} > {b_hi}" if sign < 0 else f"{column} < {b_lo}"
            taken = f"({taken} OR ({inside} AND {better}))"
            lo, hi = b_lo, b_hi
            if cut["n"] <= CUT_ROWS:
                break
        cell = f"({cell} AND {column} BETWEEN {lo} AND {hi})"
        if hi > lo:
            break
    order = W.orderBy(F.desc("rank_key"), "object_id", "pred", "scorer").rowsBetween(W.unboundedPreceding, 0)
    last = items.where(cell).withColumn("running", F.sum("cost").over(order) + F.lit(spent))
    fits = last.where((F.col("running") - F.col("cost") < budget) if overshoot else (F.col("running") <= budget))
    end = fits.agg(F.expr("max(struct(~rank_key, object_id, pred, scorer)) AS at"), F.expr("count(*) AS n"), F.expr("sum(cost) AS cost")).first()
    if not end["n"]:
        return Chosen(items.where(taken), many, spent, bounds["n"])
    key, obj, pred, scorer = ~end["at"][0], *end["at"][1:]
    upto = f"(rank_key > {key} OR (rank_key = {key} AND (object_id < {obj} OR (object_id = {obj} AND (pred < {pred} OR (pred = {pred} AND scorer <= {scorer}))))))"
    return Chosen(items.where(f"{taken} OR ({cell} AND {upto})"), many + end["n"], spent + end["cost"], bounds["n"])


def select_limit(items: DataFrame, k: int) -> DataFrame:
    """The k best items."""
    return items.orderBy(F.desc("rank_key"), "object_id", "pred", "scorer").limit(k)


def select_by_sort(items: DataFrame, budget: float) -> DataFrame:
    """Reference: one window over all items, with the running cost."""
    order = W.orderBy(F.desc("rank_key"), "object_id", "pred", "scorer").rowsBetween(W.unboundedPreceding, 0)
    return items.withColumn("running", F.sum("cost").over(order)).where(F.col("running") - F.col("cost") < budget)


def refresh_items(before: DataFrame, changed: DataFrame, again: DataFrame, answer: Answer) -> DataFrame:
    """Items kept from the last epoch: those of changed objects are replaced by ``again``, and those of
    objects that entered the answer go."""
    kept = before.join(changed.select("object_id").distinct(), "object_id", "left_anti")
    return kept.where(F.col("match_p") <= F.lit(answer.ratio)).unionByName(again)
