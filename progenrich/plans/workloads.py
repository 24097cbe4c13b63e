"""Experiment workloads: specifications of runs, their execution, and curves over approaches."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

from ..functions.tagexpr import parse_tag_expr
from ..operators import learning
from ..operators.blocks import BlockSettings, block_curve
from ..operators.enrich import CURVE, EnrichmentRun, Settings
from ..operators.scorers import LADDER
from ..operators.state import Query, cached_log, state_from_log
from ..operators.tuning import tune_epoch
from ..session import cut
from ..sources.objects import COLLECTIONS, objects, split_part

APPROACHES = ("progressive", "scorer_first", "object_first", "random")
#: Cost of every scorer on one object and predicate.
FULL_COST = sum(c for c, _, _ in LADDER)


@dataclass(frozen=True)
class RunSpec:
    """One run, in terms that both Spark and SQL can follow."""

    collection: str
    expr: str
    where: str = "true"
    share: float = 0.03  # epoch budget as a share of the cost of everything
    epochs: int = 3
    approach: str = "progressive"
    rule: str = "outside"
    benefit: str = "relative"
    pick: str = "avg"
    alpha: float = 1.0
    cached: int = -1  # percent of objects with a stored output of the best scorer
    seed: int = 1
    blocks: int = 0
    capacity: int = 0
    load_share: float = 0.1  # cost of loading a block as a share of the epoch budget
    clock: str = "virtual"
    whole_seconds: float = 600.0  # seconds that the cost of everything stands for, under the wall clock
    steps: bool = False

    def as_(self, approach: str) -> RunSpec:
        return replace(self, approach=approach)


# Exact predicates that tune selectivity (by date, time or key ranges).
ORDERS_025 = "o_orderdate < date '1995-03-01'"
ORDERS_050 = "o_orderdate < date '1995-05-01'"
ORDERS_075 = "o_orderdate < date '1995-07-01'"
ORDERS_100 = "o_orderdate < date '1995-08-29'"
ORDERS_500 = "o_orderdate < date '1998-04-16'"
ORDERS_750 = "o_orderdate < date '1999-12-09'"
FIVE = " AND o_custkey >= 0 AND c_nationkey < 25 AND n_regionkey < 5 AND o_totalprice > 1000"

SMALL_075 = RunSpec("orders", "Status = 'F'", ORDERS_075 + FIVE)
SMALL_100 = RunSpec("orders", "Status = 'F'", ORDERS_100 + FIVE)
LARGE_10 = RunSpec("lineitem", "ReturnFlag = 'R'", "l_shipdate < date '1995-03-01' AND l_quantity >= 1")
LARGE_20 = RunSpec("lineitem", "ReturnFlag = 'R'", "l_shipdate < date '1995-04-15' AND l_quantity >= 1")
TWEETS_10 = RunSpec("events", "Kind = 'purchase'", "ts < timestamp '2024-01-04 00:00:00' AND location >= 0 AND user_id >= 0")
TWEETS_20 = RunSpec("events", "Kind = 'purchase'", "ts < timestamp '2024-01-07 00:00:00' AND location >= 0 AND user_id >= 0")
#: Four selectivities of each collection.
SELECTIVITIES = {
    "orders": {"025": ORDERS_025, "050": ORDERS_050, "075": ORDERS_075, "100": ORDERS_100},
    "lineitem": {d: f"l_shipdate < date '{d}' AND l_quantity >= 1" for d in ("1995-03-01", "1995-04-15", "1995-05-15", "1995-07-01")},
    "events": {d: f"ts < timestamp '{d} 00:00:00' AND location >= 0 AND user_id >= 0" for d in ("2024-01-04", "2024-01-07", "2024-01-10", "2024-01-13")},
}
DOCS = RunSpec("docs", "Quality = 1", "n_chars > 0")
Q3 = RunSpec("orders", "Status = 'F' AND Segment = 'BUILDING'", ORDERS_100 + FIVE)
Q4 = RunSpec("orders", "Status = 'F' AND Priority = '1-URGENT'", ORDERS_100)
Q5 = RunSpec("orders", "Status = 'F' AND Segment = 'BUILDING' AND Priority = '1-URGENT'", ORDERS_100)


def prepared(spark: SparkSession, sf_dir: str, spec: RunSpec):
    """(objects of the query, query with calibration, next-scorer table)."""
    c = COLLECTIONS[spec.collection]
    everything = objects(spark, sf_dir, spec.collection)
    validation = everything.where(split_part() < 2)
    query = Query(parse_tag_expr(spec.expr), c.catalog())
    key = ("learned", spark.sparkContext.applicationId, sf_dir, spec.collection, spec.expr, spec.pick)
    if key not in _KNOWN:
        calibrated = Query(query.expr, query.catalog, learning.learn_calibration(validation, query))
        _KNOWN[key] = (calibrated, learning.learn_next_scorer(validation, calibrated, pick=spec.pick))
    query, table = _KNOWN[key]
    return everything.where(split_part() >= 2).where(spec.where), query, table


_KNOWN: dict = {}


def run(spark: SparkSession, sf_dir: str, spec: RunSpec) -> EnrichmentRun:
    chosen, query, table = prepared(spark, sf_dir, spec)
    state = state_from_log(chosen, cached_log(chosen, query, spec.cached), query) if spec.cached >= 0 else None
    everything = FULL_COST * len(query.preds) * chosen.count()
    settings = Settings(spec.alpha, spec.approach, spec.rule, spec.benefit, seed=spec.seed, clock=spec.clock, unit_seconds=spec.whole_seconds / max(1.0, everything), steps=spec.steps)
    return EnrichmentRun(chosen, query, spec.share * everything, table, settings, state)


def _key(spark: SparkSession, sf_dir: str, spec: RunSpec) -> tuple:
    return spark.sparkContext.applicationId, sf_dir, spec


#: Runs that go on at a time.
SIDE_BY_SIDE = 4


def run_all(spark: SparkSession, sf_dir: str, specs: list[RunSpec]) -> None:
    """Runs the session does not know yet, some at a time: their jobs are short and leave cores idle.

    What they learn from is learned first, once. Runs under the wall clock come one by one afterwards, as others beside
    them would count as their planning.
    """
    left = [s for s in dict.fromkeys(specs) if _key(spark, sf_dir, s) not in _KNOWN]
    free = [s for s in left if s.clock != "wall"]
    for s in {(s.collection, s.expr, s.pick): s for s in free}.values():
        prepared(spark, sf_dir, s)
    with ThreadPoolExecutor(SIDE_BY_SIDE) as pool:
        list(pool.map(inheritable_thread_target(spark)(lambda s: rows_of(spark, sf_dir, s)), free))


def rows_of(spark: SparkSession, sf_dir: str, spec: RunSpec) -> list[tuple]:
    """Curve rows of a run; runs repeat exactly, so a session keeps them."""
    key = _key(spark, sf_dir, spec)
    if key not in _KNOWN:
        made = run(spark, sf_dir, spec)
        if spec.blocks:
            _KNOWN[key] = block_curve(made, spec.epochs, BlockSettings(spec.blocks, spec.capacity, spec.load_share * made.budget))
        else:
            _KNOWN[key] = made.curve(spec.epochs)
    return _KNOWN[key]


def curves(spark: SparkSession, sf_dir: str, specs: list[tuple[str, RunSpec]]) -> DataFrame:
    """Curves of several runs under the given labels."""
    run_all(spark, sf_dir, [s for _, s in specs])
    rows = [(label, *r[1:]) for label, spec in specs for r in rows_of(spark, sf_dir, spec)]
    return spark.createDataFrame([(a, e, s, int(i), int(n), float(x), float(f)) for a, e, s, i, n, x, f in rows], CURVE)


#: More epochs than any run has: it ends when no item is left.
UNTIL_DONE = 10_000


def whole(spec: RunSpec) -> RunSpec:
    """The run until nothing is left, in epochs of 10 % of the cost of everything."""
    return replace(spec, share=0.1, epochs=UNTIL_DONE)


#: Trials of the epoch size: ten equal steps up to half the cost of everything, then 1 to 10 % of the least completion.
EPOCH_SIZES = tuple(k / 20 for k in range(1, 11))
EPOCH_SHARES = tuple(k / 100 for k in range(1, 11))


def tuned(spark: SparkSession, sf_dir: str, spec: RunSpec, sizes: tuple[float, ...] = EPOCH_SIZES, shares: tuple[float, ...] = EPOCH_SHARES) -> DataFrame:
    """Trials of the epoch size under the wall clock; ``sizes`` are shares of the cost of everything."""
    base = run(spark, sf_dir, replace(spec, share=1.0, clock="wall"))
    base.objects = cut(base.objects)  # read by every epoch of every trial
    return tune_epoch(base.again, [s * base.budget for s in sizes], list(shares)).report(spark)


def all_approaches(spec: RunSpec) -> list[tuple[str, RunSpec]]:
    return [(a, spec.as_(a)) for a in APPROACHES]
