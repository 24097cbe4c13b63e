"""Epoch sizes, paid planning, the join form, hashed features and database tables."""

import math
from collections import Counter, defaultdict
from dataclasses import replace

import pytest
import xxhash
from harness import differences

from progenrich import plans
from progenrich.operators import pair_join
from progenrich.operators.enrich import EnrichmentRun
from progenrich.operators.scorers import LADDER
from progenrich.operators.text_scorers import hashed_tfidf
from progenrich.operators.tuning import tune_epoch
from progenrich.plans import workloads as w
from progenrich.sources import sinks
from progenrich.sources.objects import COLLECTIONS, objects

SMALLEST = "/root/testdata/sf0.001"
QUERIES, ORACLES = plans.queries(), plans.oracles()


def test_steps_do_not_change_the_run(spark):
    plain = w.run(spark, SMALLEST, w.SMALL_100).curve(2)
    made = list(w.run(spark, SMALLEST, replace(w.SMALL_100, steps=True)).epochs(2))
    assert [(e.number, e.spent, e.items) for e in made] == [r[1:4] for r in plain]
    assert set(made[1].times) == {"candidates", "items", "benefit", "choose", "plan", "execute", "answer"}


def test_wall_clock_ends_and_pays_for_planning(spark):
    made = w.run(spark, SMALLEST, replace(w.SMALL_100, clock="wall", share=0.5))
    virtual = w.run(spark, SMALLEST, replace(w.SMALL_100, share=0.5))
    *_, last = made.epochs(100)
    *_, free = virtual.epochs(100)
    assert last.number < 100 and last.spent > free.spent  # all scorers, and planning on top
    assert last.f1 == pytest.approx(free.f1)


def test_tune_epoch(spark):
    base = w.run(spark, SMALLEST, replace(w.SMALL_100, share=1.0))
    got = tune_epoch(lambda size: EnrichmentRun(base.objects, base.query, size, base.table, base.settings, base.state), [base.budget, base.budget / 2], [0.5, 1.0])
    tried = [t for t in got.trials if t.stage == "size"]
    assert got.completion == min(t.completion for t in tried) > 0
    scored = [t for t in got.trials if t.stage == "share"]
    assert [t.size for t in scored] == [0.5 * got.completion, got.completion]
    assert got.size == max(scored, key=lambda t: (t.score, -t.size)).size
    assert got.report(spark).where("chosen").count() == 1


def _sides(spark):
    o = objects(spark, SMALLEST, "orders").select("object_id", "o_custkey", "t_priority")
    return o.where("object_id % 2 = 0"), o.where("object_id % 2 = 1")


def test_pairs_by_hand(spark):
    left, right = _sides(spark)
    run = pair_join.enrich_join(left, right, ["o_custkey"], "Priority", 1000, COLLECTIONS["orders"].catalog())
    first = next(run.epochs(0))
    key = [{r["object_id"]: r["o_custkey"] for r in side.collect()} for side in (left, right)]
    tags = [{r["object_id"]: [r[f"p{i}"] / sum(r[f"p{j}"] for j in range(5)) for i in range(5)] for r in s.collect()} for s in run.states]
    want = {(a, b): sum(x * y for x, y in zip(tags[0][a], tags[1][b])) for a in tags[0] for b in tags[1] if key[0][a] == key[1][b]}
    got = {(r["left_id"], r["right_id"]): r["match_p"] for r in first.pairs.collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)


def test_join_epochs(spark):
    left, right = _sides(spark)
    budget = 5_000.0  # less than what the items of either epoch cost
    made = list(pair_join.enrich_join(left, right, ["o_custkey"], "Priority", budget, COLLECTIONS["orders"].catalog()).epochs(2))
    dearest = max(c for c, _, _ in LADDER)
    steps = [b.spent - a.spent for a, b in zip(made, made[1:])]
    assert len(steps) == 2 and all(budget <= x < budget + dearest for x in steps)
    assert all(e.answer.size == e.members().count() for e in made)
    empty = list(pair_join.enrich_join(left.limit(0), right, ["o_custkey"], "Priority", 10, COLLECTIONS["orders"].catalog()).epochs(3))
    assert len(empty) == 1 and empty[0].answer.size == 0
    with pytest.raises(ValueError):
        pair_join.enrich_join(left, right, [], "Priority", 10, COLLECTIONS["orders"].catalog())


def test_hashed_features(spark):
    texts = {1: "the cat  the Dog\n", 2: "dog", 3: "", 4: None, 5: "é ü the"}
    got = {(r["object_id"], r["bucket"]): (r["tf"], r["weight"]) for r in hashed_tfidf(spark.createDataFrame(list(texts.items()), "object_id long, text string"), buckets=64).collect()}
    tf, df = {}, defaultdict(set)
    for k, t in texts.items():
        for b, n in Counter((xxhash.xxh64_intdigest(x.encode(), seed=42) + (1 << 63)) % (1 << 64) % 64 for x in (t or "").lower().split()).items():
            tf[k, b] = n
            df[b].add(k)
    assert got.keys() == tf.keys()
    for (k, b), n in tf.items():
        assert got[k, b] == (n, pytest.approx(n * math.log(6 / (1 + len(df[b])))))


def test_database_round_trip(spark):
    url, rows = "jdbc:derby:memory:progenrich;create=true", [(i, f"t{i % 7}") for i in range(1000)]
    df = spark.createDataFrame(rows, "ID long, TAG string")
    sinks.write_jdbc(df, url, "TAGS", mode="overwrite")
    back = sinks.read_jdbc(spark, url, "TAGS", "ID", 4)
    assert back.rdd.getNumPartitions() == 4
    assert sorted(map(tuple, back.collect())) == rows
    sinks.write_jdbc(df.limit(0), url, "EMPTY_TAGS", mode="overwrite")
    assert sinks.read_jdbc(spark, url, "EMPTY_TAGS", "ID", 4).isEmpty()


@pytest.mark.parametrize("name", ["fn_pandas_iterator", "fn_pandas_scalar", "agg_pandas_grouped", "agg_apply_pandas"])
def test_pandas_functions(spark, con, name):
    from harness import SF

    assert differences(spark, name, QUERIES[name], ORACLES[name], con) == ""


def test_columns_of_an_epoch_are_built_once(spark, monkeypatch):
    """The same Columns serve every epoch; another next-scorer table gets its own."""
    from progenrich.operators import planning
    from progenrich.operators.state import Query

    chosen, q, table = w.prepared(spark, SMALLEST, w.SMALL_100)
    q, made, build = Query(q.expr, q.catalog, q.calibration), [], planning._next
    monkeypatch.setattr(planning, "_next", lambda *a: made.append(a) or build(*a))
    run = EnrichmentRun(chosen, q, 500.0, table)
    assert len(run.curve(3)) == 4 and len(made) == len(q.preds)
    planning.make_items(run.state, q, planning.NextScorer({}))
    assert len(made) == 2 * len(q.preds)


def test_trials_share_their_start(spark, monkeypatch):
    """Objects are seeded once for all trials, each begins with that seed, and only scored trials look up the quality."""
    from progenrich.operators import enrich

    seeded, seed, runs = [], enrich.seed_state, []
    monkeypatch.setattr(enrich, "seed_state", lambda *a: seeded.append(a) or seed(*a))
    monkeypatch.setattr(EnrichmentRun, "curve", lambda run, most: runs.append(run) or [("progressive", 0, 0.0, 0, 1, 0.1, 0.1), ("progressive", 1, 5.0, 1, 1, 0.2, 0.2)])
    got = w.tuned(spark, SMALLEST, w.SMALL_075, (0.5, 1.0), (0.4, 1.0)).collect()
    assert len(seeded) == 1 and len({id(r.state) for r in runs}) == 1
    assert [r["stage"] for r in got] == ["size", "size", "share", "share"]
    assert [r.budget for r in runs] == [r["size"] for r in got] and runs[1].budget == 2 * runs[0].budget and runs[2].budget == 2.0
    assert [r.truth is None for r in runs] == [True, True, False, False]


def _one_epoch(run, most):
    return [("progressive", 0, 0.0, 0, 1, 0.1, 0.1), ("progressive", 1, 5.0, 1, 1, 0.2, 0.2)]


def _trials(rows, whole):
    """Sizes as shares of the cost of everything, and shares of the least completion (5 in each of the runs above)."""
    at = {stage: [r["size"] for r in rows if r["stage"] == stage] for stage in ("size", "share")}
    return [pytest.approx(s / whole) for s in at["size"]], [pytest.approx(s / 5.0) for s in at["share"]]


def test_epoch_tuning_tries_ten_sizes_and_ten_shares(spark, monkeypatch):
    monkeypatch.setattr(EnrichmentRun, "curve", _one_epoch)
    whole = w.run(spark, SMALLEST, replace(w.SMALL_075, share=1.0)).budget
    sizes, shares = _trials(QUERIES["epoch_tuning"](spark, SMALLEST).collect(), whole)
    assert sizes == [k / 20 for k in range(1, 11)] and shares == [k / 100 for k in range(1, 11)]


def test_exp2_epoch_size_tries_them_at_every_selectivity(spark, monkeypatch):
    from progenrich.plans.methods import TUNED

    monkeypatch.setattr(EnrichmentRun, "curve", _one_epoch)
    rows = QUERIES["exp2_epoch_size"](spark, SMALLEST).collect()
    assert {r["selectivity"] for r in rows} == set(TUNED) and len(TUNED) == 4
    for name, where in TUNED.items():
        whole = w.run(spark, SMALLEST, replace(w.SMALL_075, share=1.0, where=where)).budget
        sizes, shares = _trials([r for r in rows if r["selectivity"] == name], whole)
        assert sizes == [k / 20 for k in range(1, 11)] and shares == [*[k / 100 for k in range(1, 11)], 0.2]


def test_an_unfinished_run_has_no_completion(spark):
    class Endless:
        def curve(self, most):
            return [("progressive", n, float(n), 0, 1, 0.1, 0.1) for n in range(most + 1)]

    with pytest.raises(ValueError):
        tune_epoch(lambda size: Endless(), [1.0], [0.1], most=3)


def test_an_epoch_is_planned_once(spark, monkeypatch):
    """Also where nothing outside the answer has a scorer left: the answer has counted that."""
    from progenrich.operators import planning

    made, build = [], planning.make_items
    monkeypatch.setattr(planning, "make_items", lambda *a: made.append(a) or build(*a))
    run = w.run(spark, SMALLEST, replace(w.SMALL_100, share=0.5))
    drained = [run.drained for _ in run.epochs(100)]
    assert any(drained) and len(made) == len(drained)  # no plan for epoch 0, one that finds nothing left at the end


def test_next_scorers_are_those_of_the_table(spark):
    from progenrich.operators import planning

    _, q, table = w.prepared(spark, SMALLEST, w.SMALL_100)
    p, full, cells = q.preds[0], q.full_mask(0), [(m, (b + 0.5) / table.bins) for m in range(q.full_mask(0) + 1) for b in range(table.bins)]
    df = spark.createDataFrame(cells, "m0 int, h0 double")
    step = planning._next(q, table, 0)
    got = {(r["m0"], r["h0"]): r["n"] for r in df.select("m0", "h0", step.alias("n")).collect()}
    for m, h in cells:
        rest = [s for s in q.scorers(0) if not m >> s.number & 1]
        want = (table.lookup(p.type, p.tag, m, int(h * table.bins)) or (max(rest, key=lambda s: (s.ratio, -s.number)).number, 0.0)) if m != full else None
        assert (got[m, h] and tuple(got[m, h])) == want


@pytest.mark.parametrize("budget", [0.5, 2.0, 33, 250, 900.0, 10**6])
def test_a_plan_knows_its_size_and_cost(spark, budget, monkeypatch):
    from progenrich.operators import planning

    monkeypatch.setattr(planning, "CUT_ROWS", 7)
    monkeypatch.setattr(planning, "CUT_BINS", 8)
    items = spark.range(0, 300, numPartitions=3).selectExpr("id AS object_id", "CAST(id % 2 AS int) AS pred", "CAST(id % 3 AS int) AS scorer", "double(1 + id % 5) AS cost", "(id * 7919) % 23 - 11 AS rank_key")
    got = planning.choose_plan(items, budget)
    rows = {tuple(r) for r in got.plan.select("object_id", "pred", "scorer", "cost").collect()}
    assert rows == {tuple(r) for r in planning.select_by_sort(items, budget).select("object_id", "pred", "scorer", "cost").collect()}
    assert (got.items, got.cost, got.available) == (len(rows), sum(r[3] for r in rows), 300)
