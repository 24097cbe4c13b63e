"""The progressive enrichment operator: epochs of plan, execution and answer.

State is checkpointed once an epoch, which bounds lineage. Costs are virtual units by default, so runs
repeat exactly; with ``clock='wall'`` the seconds of planning, at ``unit_seconds`` a unit, are taken off the budget
of their epoch and count as spent.
"""

from __future__ import annotations

import copy
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.tagexpr import holds_column, parse_tag_expr, split_predicates
from ..session import cut
from . import baselines, planning
from .cutoff import Answer, answer_changes, choose_answer
from .execution import execute_plan
from .metrics import f_measure
from .state import Query, apply_outputs, seed_state


@dataclass
class Settings:
    """How a run plans. Defaults are the published ones."""

    alpha: float = 1.0
    approach: str = "progressive"  # or scorer_first, object_first, random
    rule: str = "outside"  # or all, gaining
    benefit: str = "relative"  # or exact, weighted, prefix
    answer: str = "ratio"
    on_exhausted: str = "drain"  # or stop
    seed: int = 1
    pool: str = "remaining"
    clock: str = "virtual"  # or wall: planning is paid for too
    unit_seconds: float = 1.0  # seconds of planning that one unit of cost stands for, under the wall clock
    steps: bool = False  # time the steps of planning apart; each of them is stored then
    refresh_every: int = 0  # epochs after which the next-scorer table is learned again from the run's own objects
    refresh_percent: int = 5  # share of objects that each refresh adds to the sample


@dataclass
class Epoch:
    number: int
    spent: float
    items: int
    answer: Answer
    f1: float | None
    state: DataFrame = field(repr=False)
    outputs: DataFrame | None = field(repr=False, default=None)
    times: dict = field(default_factory=dict)

    def members(self) -> DataFrame:
        return self.answer.members(self.state).select("object_id", "match_p", F.lit(self.number).alias("epoch"))


class EnrichmentRun:
    """A run over one collection; ``epochs`` yields the seed answer (epoch 0) and then one answer an epoch."""

    def __init__(self, objects: DataFrame, query: Query, budget: float, table: planning.NextScorer | None = None, settings: Settings | None = None, state: DataFrame | None = None, truth: bool | None = None):
        self.objects, self.query, self.budget = objects, query, float(budget)
        self.table = table or planning.NextScorer({})
        self.settings = settings or Settings()
        used = {p.type for p in query.preds}
        if truth is None:  # without hidden truth columns a run is the same, but has no true quality
            truth = all(t.truth in objects.columns for t in query.catalog.types if t.name in used)
        began = time.time()
        self.size = objects.count()
        loaded = time.time()
        self.state = cut(seed_state(objects, query) if state is None else state)
        seeded = time.time()
        self.init_times = {"load": loaded - began, "seed": seeded - loaded, "structures": 0.0}
        self.truth = objects.select("object_id", holds_column(query.expr, {t.name: t.truth for t in query.catalog.types}).alias("relevant")) if truth else None
        if truth:
            self.truth = cut(self.truth)  # every epoch asks for it
        self.relevant = self.truth.where("relevant").count() if truth else None
        #: Outputs of other scorers than Columns are stored, as computing them again would be dear.
        self.columns = all(s.column is not None for i in range(len(query.preds)) for s in query.scorers(i))
        self.first = None
        structured = time.time()
        if self.settings.approach in ("scorer_first", "object_first"):
            make = baselines.scorer_first if self.settings.approach == "scorer_first" else baselines.object_first
            self.first = cut(make(baselines.every_item(self.state, query), query))
        self.init_times["structures"] = time.time() - structured
        self.sampled = 0  # percent of the objects that refreshes of the table have paid for
        self.drained = False

    def again(self, budget: float) -> EnrichmentRun:
        """The same run from its start, in epochs of another size: what was loaded, seeded and built is shared."""
        other = copy.copy(self)
        other.budget = float(budget)
        return other

    def _quality(self, answer: Answer, state: DataFrame) -> float | None:
        if self.truth is None:
            return None
        hit = answer.members(state).join(self.truth.where("relevant"), "object_id", "left_semi").count()
        return f_measure(hit, answer.size, self.relevant, self.settings.alpha)

    def items(self, state: DataFrame, answer: Answer, number: int, keep=lambda step, df: df) -> DataFrame:
        """Ranked items of an epoch under the settings; ``keep`` may store the rows after each step."""
        s = self.settings
        if s.approach == "random":
            return baselines.random_epoch(state, self.query, number, s.seed, s.pool)
        if s.approach != "progressive":
            done = state.select("object_id", *[f"m{i}" for i in range(len(self.query.preds))])
            mask = F.element_at(F.array(*[F.col(f"m{i}") for i in range(len(self.query.preds))]), F.col("pred") + 1)
            return self.first.join(done, "object_id").where(mask.bitwiseAND(F.expr("shiftleft(1, scorer)")) == 0)
        rule = "all" if self.drained else s.rule
        candidates = keep("candidates", planning.select_candidates(state, answer, rule))
        items = keep("items", planning.make_items(candidates, self.query, self.table))
        if s.benefit == "exact":
            return planning.benefit_exact(items, state, answer)
        if s.benefit == "weighted":
            return planning.benefit_exact(items, state, answer, weighted=True)
        items = planning.benefit_prefix(items, state, answer) if s.benefit == "prefix" else planning.benefit_relative(items)
        return planning.guard_gaining(items, answer) if rule == "gaining" else items

    def _refresh(self, percent: int) -> float:
        """Learn the table from a sample of the run's own objects; what the sample's scorers cost is paid by the epoch."""
        from .learning import learn_online, online_sample

        self.table, _ = learn_online(self.objects, self.query, percent, self.table.bins)
        new = online_sample(self.objects, percent).count() - (online_sample(self.objects, self.sampled).count() if self.sampled else 0)
        self.sampled = percent
        return float(new) * sum(s.cost for i in range(len(self.query.preds)) for s in self.query.scorers(i))

    def _plan(self, state: DataFrame, answer: Answer, number: int, budget: float) -> tuple[DataFrame, int, float | None, bool, dict]:
        """The plan of an epoch, its items and cost, whether there was nothing to choose from, and the seconds by step.

        One query as a rule; step by step where steps are timed apart.
        """
        s, steps, at = self.settings, {}, time.time()

        def keep(step: str, df: DataFrame) -> DataFrame:
            nonlocal at
            out, began = cut(df), at
            at = time.time()
            steps[step] = at - began
            return out

        if not s.steps:
            # several passes look for the budget's end: they read narrow stored rows instead of planning anew
            ranked = cut(self.items(state, answer, number).select("object_id", "pred", "scorer", "cost", "rank_key"))
            if s.clock == "wall":
                budget -= (time.time() - at) / s.unit_seconds
            got = planning.choose_plan(ranked, budget)  # a condition on stored rows: choosing again costs less than storing the choice
            return got.plan, got.items, got.cost, not got.items and (s.clock != "wall" or not got.available), steps
        items = keep("benefit", self.items(state, answer, number, keep))
        if s.clock == "wall":
            budget -= sum(steps.values()) / s.unit_seconds
        got = planning.choose_plan(items, budget)
        return keep("choose", got.plan), got.items, got.cost, not got.items and not got.available, steps

    def epochs(self, most: int) -> Iterator[Epoch]:
        s, state, spent, debt = self.settings, self.state, 0.0, 0.0
        drains = s.approach == "progressive" and s.rule != "all" and s.on_exhausted == "drain"
        left = " OR ".join(f"m{i} != {self.query.full_mask(i)}" for i in range(len(self.query.preds))) if drains else None
        answer = choose_answer(state, s.alpha, s.answer, left)
        yield Epoch(0, 0.0, 0, answer, self._quality(answer, state), state)
        for number in range(1, most + 1):
            began = time.time()
            self.drained = answer.open == 0  # nothing outside has a scorer left: planning of that alone would find nothing
            budget = self.budget - debt
            if s.refresh_every and number % s.refresh_every == 0:
                paid = self._refresh(min(100, s.refresh_percent * number))
                spent += paid
                budget -= paid
            debt = max(0.0, -budget)  # a sample dearer than the epoch is paid for by the next ones as well
            if budget <= 0:
                yield Epoch(number, spent, 0, answer, self._quality(answer, state), state, None, {"plan": time.time() - began})
                continue
            plan, n, cost, empty, steps = self._plan(state, answer, number, budget)
            if empty and drains and not self.drained:
                self.drained = True
                plan, n, cost, empty, more = self._plan(state, answer, number, budget)
                steps = {k: steps.get(k, 0.0) + v for k, v in more.items()}
            planned = time.time()
            if empty:
                return
            if s.clock == "wall":
                paid = (planned - began) / s.unit_seconds
                spent += paid
                if not n or paid >= budget:
                    yield Epoch(number, spent, 0, answer, self._quality(answer, state), state, None, {"plan": planned - began, **steps})
                    continue
            outputs = execute_plan(plan, self.objects, self.query, n)
            outputs = outputs if self.columns else cut(outputs)
            state = cut(apply_outputs(state, outputs, self.query))
            executed = time.time()
            spent += cost
            answer = choose_answer(state, s.alpha, s.answer, left)
            yield Epoch(number, spent, n, answer, self._quality(answer, state), state, outputs, {"plan": planned - began, **steps, "execute": executed - planned, "answer": time.time() - executed})

    def curve(self, most: int) -> list[tuple]:
        """(approach, epoch, spent, items, answer size, expected F, F1)."""
        return [(self.settings.approach, e.number, float(e.spent), e.items, e.answer.size, e.answer.expected_f, e.f1) for e in self.epochs(most)]


CURVE = "approach string, epoch int, spent double, items long, answer_size long, expected_f double, f1 double"


def enrich(objects: DataFrame, expr, budget: float, catalog, *, conditions=(), mode: str = "aware", table=None, settings=None, calibration=None, state=None) -> EnrichmentRun:
    """Start a run. ``conditions`` are exact predicates: with ``mode='aware'`` they filter the objects first,
    with ``'function'`` the whole collection is enriched and the caller filters the answers."""
    e = parse_tag_expr(expr) if isinstance(expr, str) else expr
    exact, tags = split_predicates([*conditions, e])
    if mode == "aware":
        for c in exact:
            objects = objects.where(c)
    query = Query(tags[0], catalog, calibration) if calibration else Query(tags[0], catalog)
    return EnrichmentRun(objects, query, budget, table, settings, state)


def enrich_once(run: EnrichmentRun) -> tuple[DataFrame, DataFrame]:
    """Table-function form: one epoch on the stored state; the answer, and the state to pass on."""
    last = None
    for last in run.epochs(1):
        pass
    return last.members(), last.state


def enrich_budget(run: EnrichmentRun, total: float) -> Epoch:
    """One answer for a total budget: epochs until it is used, or nothing is left."""
    last = None
    for last in run.epochs(10_000):
        if last.spent >= total:
            break
    return last


def enrich_many(runs: list[EnrichmentRun], epochs: int, total: float | None = None) -> list[list[Epoch]]:
    """Several operators of one query: an epoch's budget is shared in proportion to what each has left to do."""
    if total is not None:
        sizes = [r.state.count() * len(r.query.preds) for r in runs]
        for r, n in zip(runs, sizes):
            r.budget = total * n / max(1, sum(sizes))
    return [list(r.epochs(epochs)) for r in runs]


def changes(epochs: list[Epoch]) -> DataFrame:
    """Rows that entered or left the answer, over all epochs."""
    parts = [answer_changes(a.members(), b.members(), b.number) for a, b in zip(epochs, epochs[1:])]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def full_enrichment(objects: DataFrame, query: Query) -> DataFrame:
    """Every scorer on every object: the offline practice, and the end of every run."""
    from .state import empty_state

    state = empty_state(objects, query)
    items = baselines.every_item(state.withColumn("match_p", F.lit(0.0)), query)
    return apply_outputs(state, execute_plan(items, objects, query), query)


def is_exhausted(state: DataFrame, query: Query) -> bool:
    """Whether no object has a scorer left."""
    left = None
    for i in range(len(query.preds)):
        c = F.col(f"m{i}") != query.full_mask(i)
        left = c if left is None else left | c
    return state.where(left).isEmpty()
