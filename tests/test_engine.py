"""Planning, epochs and measures on the orders collection."""

from dataclasses import replace

import pytest
from harness import SF
from pyspark.sql import functions as F

from progenrich.operators import baselines, cutoff, metrics, planning
from progenrich.operators.enrich import EnrichmentRun, Settings, enrich_once, full_enrichment, is_exhausted
from progenrich.operators.planning import NextScorer
from progenrich.operators.state import seed_state
from progenrich.plans import workloads as w

SPEC = replace(w.Q3, where=w.ORDERS_025, share=0.05)


@pytest.fixture(scope="module")
def made(spark):
    chosen, q, t = w.prepared(spark, SF, SPEC)
    chosen = chosen.cache()
    return chosen, q, t, seed_state(chosen, q).cache()


def test_table_lookup_examples():
    t = NextScorer({("T", 1, 5, 9): (3, -0.22), ("T", 1, 3, 9): (2, -0.28), ("T", 1, 3, None): (1, -0.1)})
    assert t.lookup("T", 1, 5, 9) == (3, -0.22) and t.lookup("T", 1, 3, 9) == (2, -0.28)
    assert t.lookup("T", 1, 3, 0) == (1, -0.1) and t.lookup("T", 1, 7, 0) is None


@pytest.mark.parametrize("budget", [0.5, 7, 333, 2500, 10**9])
def test_plan_by_cells_is_the_sorted_plan(made, budget, monkeypatch):
    _, q, t, st = made
    monkeypatch.setattr(planning, "CUT_ROWS", 10)
    monkeypatch.setattr(planning, "CUT_BINS", 8)
    items = planning.benefit_relative(planning.make_items(st, q, t)).cache()
    key = ("object_id", "pred", "scorer")
    a = {tuple(r) for r in planning.select_plan(items, budget).select(*key).collect()}
    b = {tuple(r) for r in planning.select_by_sort(items, budget).select(*key).collect()}
    assert a == b


def test_plan_with_ties(spark, monkeypatch):
    monkeypatch.setattr(planning, "CUT_ROWS", 5)
    items = spark.range(0, 1000).select(F.col("id").alias("object_id"), F.lit(0).alias("pred"), F.lit(1).alias("scorer"), F.lit(3.0).alias("cost"), (F.col("id") % 2).alias("rank_key"))
    got = sorted(r["object_id"] for r in planning.select_plan(items, 100.0).collect())
    assert got == list(range(1, 68, 2))


def test_planning_is_one_narrow_projection(made):
    _, q, t, st = made
    report = metrics.plan_report(planning.benefit_relative(planning.make_items(planning.select_candidates(st, cutoff.choose_answer(st)), q, t)))
    assert all(report[k] == 0 for k in ("exchange", "window", "sort", "python", "cartesian", "nested_loop", "single")), report


def test_exact_predicates_reach_the_scan(spark):
    chosen, _, _ = w.prepared(spark, SF, w.SMALL_100)
    text = chosen.select("object_id")._jdf.queryExecution().executedPlan().toString()
    scan = next(x for x in text.splitlines() if "o_orderdate" in x and "FileScan" in x)
    assert "isnotnull(o_orderdate" in scan.split("DataFilters")[1] and "o_orderpriority" not in text


def test_guarded_items_raise_the_expected_f(spark):
    """Brute force: an item passes the guard exactly if putting it into the answer raises the expected F."""
    ps = [0.9, 0.8, 0.75, 0.3, 0.2, 0.45]
    st = spark.createDataFrame([(i, p) for i, p in enumerate(ps)], "object_id long, match_p double")
    a = cutoff.choose_answer(st)
    tries = [(i, p, e) for i, p in enumerate(ps) if p <= a.ratio for e in (0.31, 0.46, 0.5, 0.7, 0.99) if e >= p]
    items = spark.createDataFrame([(i * 100 + k, p, e, 1.0) for k, (i, p, e) in enumerate(tries)], "object_id long, match_p double, match_est double, cost double")
    kept = {r["object_id"] for r in planning.guard_gaining(items, a).collect()}
    for k, (i, p, e) in enumerate(tries):
        new = [e if j == i else x for j, x in enumerate(ps)]
        inside = a.mass + e
        f = 2 * inside / (sum(new) + a.size + 1)
        assert (i * 100 + k in kept) == (f > a.expected_f), (i, p, e)


def test_relative_benefit_can_disagree_with_the_exact_one(spark):
    """Two single changes of the five-object example: the ranking of the constant-time score is not the exact one."""
    st = spark.createDataFrame(list(enumerate([0.9, 0.8, 0.75, 0.3, 0.2])), "object_id long, match_p double")
    a = cutoff.choose_answer(st)
    items = spark.createDataFrame([(3, 0, 0.3, 0.5, 1.0), (4, 0, 0.2, 0.6, 1.0)], "object_id long, pred int, match_p double, match_est double, cost double")
    rel = {r["object_id"]: r["benefit"] for r in planning.benefit_relative(items).collect()}
    exact = {r["object_id"]: r["benefit"] for r in planning.benefit_exact(items, st, a).collect()}
    prefix = {r["object_id"]: r["benefit"] for r in planning.benefit_prefix(items, st, a, 1000).collect()}
    assert rel[3] == pytest.approx(0.15) and rel[4] == pytest.approx(0.12)
    for o, est in ((3, 0.5), (4, 0.6)):
        ps = [0.9, 0.8, 0.75, 0.3, 0.2]
        ps[o] = est
        order = sorted(ps, reverse=True)
        best = max(2 * sum(order[:k]) / (sum(ps) + k) for k in range(1, 6))
        assert exact[o] == pytest.approx(best - a.expected_f) and prefix[o] == pytest.approx(exact[o])
    with pytest.raises(ValueError):
        planning.benefit_exact(items, st, a, most=2)


@pytest.mark.parametrize("approach", w.APPROACHES)
def test_run_invariants(made, approach):
    chosen, q, t, _ = made
    budget = 0.2 * w.FULL_COST * 2 * chosen.count()
    run = EnrichmentRun(chosen, q, budget, t, Settings(approach=approach))
    before, seen, last = None, set(), None
    for e in run.epochs(30):
        masks = {r["object_id"]: (r["m0"], r["m1"]) for r in e.state.select("object_id", "m0", "m1").collect()}
        if before:
            assert all(a | b == b for o in masks for a, b in zip(before[o], masks[o]))
            rows = [(r["object_id"], r["pred"], r["scorer"]) for r in e.outputs.collect()]
            assert len(rows) == len(set(rows)) and not seen & set(rows)
            seen |= set(rows)
            spent = e.spent - last.spent
            assert spent < budget + 40 + 1e-9
        before, last = masks, e
    assert is_exhausted(last.state, q)
    assert last.spent == pytest.approx((w.FULL_COST - 1) * 2 * chosen.count())
    done = cutoff.choose_answer(full_enrichment(chosen, q))
    assert done.size == last.answer.size and done.expected_f == pytest.approx(last.answer.expected_f)


def test_pushdown_and_table_function_agree_without_a_limit(spark, made):
    chosen, q, t, _ = made
    whole, _, _ = w.prepared(spark, SF, replace(SPEC, where="o_orderdate < date '1995-05-01'"))
    a = full_enrichment(chosen, q).select("object_id", F.round("match_p", 9).alias("p"))
    b = full_enrichment(whole, q).join(chosen.select("object_id"), "object_id").select("object_id", F.round("match_p", 9).alias("p"))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_enrich_once_passes_its_state_on(made):
    chosen, q, t, _ = made
    first = EnrichmentRun(chosen, q, 500, t)
    _, state = enrich_once(first)
    again = EnrichmentRun(chosen, q, 500, t, state=state)
    members, _ = enrich_once(again)
    two = EnrichmentRun(chosen, q, 500, t)
    *_, last = two.epochs(2)
    assert members.select("object_id").exceptAll(last.members().select("object_id")).isEmpty()


def test_wall_clock_spends_time_on_planning(made):
    chosen, q, t, _ = made
    run = EnrichmentRun(chosen, q, 1e-6, t, Settings(clock="wall"))
    rows = list(run.epochs(2))
    assert rows[-1].items == 0 and rows[-1].spent > 0


def test_empty_collection(spark, made):
    chosen, q, t, _ = made
    rows = list(EnrichmentRun(chosen.limit(0), q, 10, t).epochs(3))
    assert len(rows) == 1 and rows[0].answer.size == 0


def test_random_applied_pool_changes_nothing(made):
    _, q, _, st = made
    rows = baselines.random_epoch(st, q, 1, pool="applied")
    assert rows.where("scorer <> 0").isEmpty()


def test_progressiveness_by_hand(spark):
    rows = [("a", 0, 0.0, 0.0), ("a", 1, 5.0, 0.5), ("a", 2, 10.0, 1.0)]
    c = spark.createDataFrame(rows, "approach string, epoch int, spent double, gain double")
    got = metrics.progressiveness(c).first()["progressiveness"]
    assert got == pytest.approx(0.5 * (1 - 4 / 10) + 0.5 * (1 - 9 / 10))
    printed = metrics.progressiveness(c, weighting="printed").first()["progressiveness"]
    assert printed == pytest.approx(0.5 * (1 - 4 / 10) + 0.5 * (1 - 9 / 10))
    flat = metrics.progressiveness(c, weighting=lambda i, v, h: F.lit(1.0)).first()["progressiveness"]
    assert flat == pytest.approx(1.0)


def test_blocks_respect_capacity(spark):
    from progenrich.operators.blocks import resident_after

    q = spark.createDataFrame([("memory", 1, 5, 0.1), ("memory", 2, 6, 0.2), ("disk", 1, 1, 0.9), ("disk", 2, 2, 0.8)], "queue string, place int, block_id int, benefit double")
    assert resident_after(q, 0, 2) == [5, 6]
    assert resident_after(q, 1, 2) == [6, 1]
    assert resident_after(q, 2, 2) == [1, 2]
    assert resident_after(q, 2, 4) == [5, 6, 1, 2]  # free room: nothing is written back


def test_table_is_refreshed_online(made):
    chosen, q, t, _ = made
    run = EnrichmentRun(chosen, q, 300, NextScorer({}), Settings(refresh_every=1, refresh_percent=50))
    assert [e.items for e in run.epochs(2)] == [0, 0, 0]  # the sample costs more than two epochs hold
    run = EnrichmentRun(chosen, q, 54 * 2 * chosen.count(), NextScorer({}), Settings(refresh_every=1, refresh_percent=50))
    rows = list(run.epochs(1))
    assert run.table.cells and rows[-1].items > 0


def test_other_kinds_of_scorers(spark):
    """A column, a pandas function and a service score the objects of a plan; outputs land in the state."""
    from progenrich.functions.tagexpr import Pred
    from progenrich.model import Catalog, TagType
    from progenrich.operators import scorers as sc
    from progenrich.operators.execution import execute_plan
    from progenrich.operators.state import Query, apply_outputs, empty_state

    objects = spark.createDataFrame([(1, 0.2, "a"), (2, 0.9, "b")], "object_id long, x double, t_kind string")
    made = (
        sc.from_column("Kind", 0, 1.0, 0.6, lambda tag: F.col("x")),
        sc.from_pandas("Kind", 1, 2.0, 0.7, lambda tag, x: 1 - x, ["x"]),
        sc.from_service("Kind", 2, 3.0, 0.8, lambda: lambda tag, frame: [0.5] * len(frame), ["x"]),
    )
    q = Query(Pred("Kind", "a"), Catalog((TagType("Kind", ("a", "b"), "t_kind"),), made))
    state = empty_state(objects, q).withColumn("match_p", F.lit(0.0))
    out = execute_plan(baselines.every_item(state, q), objects, q)
    got = {(r["object_id"], r["scorer"]): r["prob"] for r in out.collect()}
    assert got == {(1, 0): 0.2, (2, 0): 0.9, (1, 1): 0.8, (2, 1): pytest.approx(0.1), (1, 2): 0.5, (2, 2): 0.5}
    final = {r["object_id"]: (r["m0"], r["p0"]) for r in apply_outputs(empty_state(objects, q), out, q).collect()}
    assert final[1] == (7, pytest.approx((0.6 * 0.2 + 0.7 * 0.8 + 0.8 * 0.5) / 2.1))


def test_fitted_classifiers_run_to_the_end(spark):
    """Seed, calibration, table and epochs with classifiers that never see the truth of the queried documents."""
    from progenrich.plans.real import real_runs

    rows = real_runs(spark, SF, approaches=("progressive", "scorer_first"), share=1.0).collect()
    ends = {}
    for r in rows:
        assert 0 <= r["f1"] <= 1 and 0 <= r["expected_f"] <= 1
        ends[r["approach"]] = r
    assert len({e["spent"] for e in ends.values()}) == 1 and ends["progressive"]["spent"] > 0
    assert ends["progressive"]["answer_size"] == ends["scorer_first"]["answer_size"]


def test_runs_without_a_truth_column(spark):
    """Objects without hidden truth: a run by a plain scorer, with answers and no true quality."""
    from progenrich.functions.tagexpr import Pred
    from progenrich.model import Catalog, TagType
    from progenrich.operators import scorers as sc
    from progenrich.operators.state import Query

    objects = spark.createDataFrame([(i, i / 10) for i in range(10)], "object_id long, x double")
    made = (sc.from_column("Kind", 0, 1.0, 0.7, lambda tag: F.col("x")), sc.from_pandas("Kind", 1, 5.0, 0.9, lambda tag, x: (x > 0.4).astype("float64"), ["x"]))
    run = EnrichmentRun(objects, Query(Pred("Kind", "a"), Catalog((TagType("Kind", ("a", "b"), "t_kind"),), made)), 12.0)
    *_, last = run.epochs(20)
    assert last.f1 is None and {r["object_id"] for r in last.members().collect()} == {5, 6, 7, 8, 9}


def test_a_refresh_is_paid_for(made):
    chosen, q, t, _ = made
    plain = list(EnrichmentRun(chosen, q, 3000, NextScorer({})).epochs(1))[-1]
    paid = list(EnrichmentRun(chosen, q, 3000, NextScorer({}), Settings(refresh_every=1, refresh_percent=5)).epochs(1))[-1]
    assert paid.items < plain.items and paid.spent >= 2900


def test_fitted_curves_are_applied(spark):
    from progenrich.operators.state import Calibration

    c = Calibration(curves={("T", 1, 0): ("sigmoid", 2.0, -1.0), ("T", 1, 1): ("isotonic", [0.2, 0.6, 0.6, 0.9], [0.1, 0.3, 0.7, 0.8])})
    df = spark.createDataFrame([(x,) for x in (0.0, 0.2, 0.4, 0.6, 0.75, 1.0)], "x double")
    got = df.select(c.apply(F.col("x"), "T", 1, 0).alias("a"), c.apply(F.col("x"), "T", 1, 1).alias("b")).collect()
    assert got[1]["a"] == pytest.approx(1 / (1 + 2.718281828 ** 0.6)) and [round(r["b"], 6) for r in got] == [0.1, 0.1, 0.2, 0.7, 0.75, 0.8]


def test_line_keys_refuse_to_overflow(spark, tmp_path):
    from progenrich.sources.objects import objects

    spark.sql("SELECT 6000000000L AS l_orderkey, 7 AS l_linenumber, 200000000L AS l_partkey, 1000000L AS l_suppkey").write.parquet(f"{tmp_path}/lineitem.parquet")
    with pytest.raises(ValueError):
        objects(spark, str(tmp_path), "lineitem")
