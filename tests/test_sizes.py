"""Operators at sizes and on tables where they used to give up."""

import random

import pytest
from harness import SF

from progenrich import plans
from progenrich.operators import cutoff, metrics, planning


def _solved(ps, at, est, alpha):
    """The best expected F after one change, over all prefixes."""
    new = sorted((est if j == at else x for j, x in enumerate(ps)), reverse=True)
    return max((1 + alpha) * sum(new[:k]) / (alpha * sum(new) + k) for k in range(1, len(new) + 1))


@pytest.mark.parametrize("alpha, ties, cuts", [(1.0, False, 2000), (0.5, True, 2000), (1.0, True, 0), (0.5, False, 0)])
def test_exact_benefit_is_that_of_brute_force(spark, monkeypatch, alpha, ties, cuts):
    monkeypatch.setattr(planning, "CUTS", cuts)
    rnd = random.Random(7)
    for n in (1, 2, 5, 60):
        ps = [round(rnd.random(), 1 if ties else 6) for _ in range(n)]
        st = spark.createDataFrame(list(enumerate(ps)), "object_id long, match_p double")
        a = cutoff.choose_answer(st, alpha)
        tries = [(i, k, ps[i], ps[i] + (1 - ps[i]) * x) for i in range(n) for k, x in enumerate((0.0, 0.3, 1.0))]
        items = spark.createDataFrame([(*t, 2.0) for t in tries], "object_id long, pred int, match_p double, match_est double, cost double")
        got = {(r["object_id"], r["pred"]): r["benefit"] for r in planning.benefit_exact(items, st, a).collect()}
        assert len(got) == len(tries)
        for i, k, _, est in tries:
            assert got[i, k] == pytest.approx((_solved(ps, i, est, alpha) - a.expected_f) / 2, abs=1e-12)


def test_exact_benefit_of_many_objects(spark):
    """More objects than the quadratic form took (20,000), of many values."""
    st = spark.range(30_000).selectExpr("id AS object_id", "(id * 7919 % 29989) / 29989.0D AS match_p")
    a = cutoff.choose_answer(st)
    items = st.where("object_id % 5000 = 0").selectExpr("object_id", "0 AS pred", "match_p", "least(1.0D, match_p + 0.25D) AS match_est", "1.0D AS cost")
    ps = [(i * 7919 % 29989) / 29989.0 for i in range(30_000)]
    for r in planning.benefit_exact(items, st, a).collect():
        new = sorted((r["match_est"] if j == r["object_id"] else x for j, x in enumerate(ps)), reverse=True)
        total, s, best = sum(new), 0.0, 0.0
        for k, x in enumerate(new, 1):
            s += x
            best = max(best, 2 * s / (total + k))
        assert r["benefit"] == pytest.approx(best - a.expected_f, abs=1e-12)


def test_agreement_of_many_items(spark):
    """More items than pairs were taken of before (2,000), and the same share as over all pairs."""
    rows = [(i, 0, (i * 37 % 50) / 10, (i * 53 % 40) / 10) for i in range(3000)]
    df = spark.createDataFrame(rows, "object_id long, pred int, a double, b double")
    got = metrics.rank_agreement(df, "a", "b").first()
    sign = lambda x: (x > 1e-10) - (x < -1e-10)
    alike = sum(sign(x[2] - y[2]) == sign(x[3] - y[3]) for i, x in enumerate(rows) for y in rows[:i])
    assert got["pairs"] == 3000 * 2999 // 2 and got["agreement"] == pytest.approx(alike / got["pairs"])
    assert metrics.rank_agreement(df.limit(0), "a", "b").first()["pairs"] == 0


def _lines(spark, path, rows):
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber long, l_partkey long, l_suppkey long, l_quantity double, l_discount double, l_returnflag string, l_linestatus string").selectExpr("*", "date '1995-01-01' AS l_shipdate").write.parquet(f"{path}/lineitem.parquet")


def _fold(o, n, p, s):
    return ((o * 8 + n) * 20011 + p) * 1009 + s


def test_keys_of_lines_of_large_tables(spark, tmp_path):
    """Parts, suppliers and orders far above those of sf0.1: the key of the SQL, its noise and its part, in exact numbers."""
    from pyspark.sql import functions as F

    from progenrich.operators.learning import online_sample
    from progenrich.operators.scorers import noise
    from progenrich.sources.objects import objects, split_part

    keys = [(9_000_000 * k + k, k % 7 + 1, 1_200_000 - k, 60_000 - k) for k in range(40)]
    _lines(spark, tmp_path, [(*k, 1.0, 0.0, "A", "F") for k in keys])
    df = objects(spark, str(tmp_path), "lineitem")
    ids = {_fold(*k) for k in keys}
    got = df.select("object_id", noise(F.col("object_id"), 2, 3).alias("u"), split_part().alias("part")).collect()
    assert {r["object_id"] for r in got} == ids and max(ids) > 1 << 53
    for r in got:
        k = r["object_id"]
        assert r["part"] == k * 7919 % 10
        assert r["u"] == (7919 * k + 31337 * 2 + 104729 * 3 + 613 * 54 * (k // 97)) % 10007 / 10007.0
    assert {r["object_id"] for r in online_sample(df, 50).collect()} == {k for k in ids if k // 11 % 100 < 50}


def test_keys_of_lines_that_fold_alike(spark, tmp_path):
    """Two lines with one folded key get two ids; a line that is there twice keeps one."""
    from progenrich.sources.objects import objects

    a, b = (1, 1, 25_000, 5), (1, 2, 25_000 - 20_011, 5)
    assert _fold(*a) == _fold(*b)
    _lines(spark, tmp_path, [(*k, 1.0, 0.0, "A", "F") for k in (a, b, b)])
    assert objects(spark, str(tmp_path), "lineitem").select("object_id").distinct().count() == 2


@pytest.mark.parametrize("name, source", [("answer_edge_cases", "customer"), ("blend_weights", "orders"), ("inverse_entropy", "orders"), ("inverse_entropy_both", "orders")])
def test_queries_read_a_given_table(spark, tmp_path, name, source):
    """Without the table there is no result: it is not made up."""
    import os

    for f in os.listdir(SF):
        if f != f"{source}.parquet":
            os.symlink(f"{SF}/{f}", tmp_path / f)
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        plans.queries()[name](spark, str(tmp_path)).count()


@pytest.mark.parametrize("mode", ["complete", "append", "update"])
def test_streams_end_in_stored_rows(spark, mode):
    """Rows of a stream lie in files of the executors, not on the driver; the last whole table counts, or every batch."""
    from pyspark.sql import functions as F

    from progenrich.streaming import ingest

    events = spark.read.parquet(f"{SF}/events.parquet")
    stream = ingest.event_stream(spark, SF, 3).select("event_id", "event_type")
    out = ingest.finished(stream if mode == "append" else stream.groupBy("event_type").agg(F.count("*").alias("n")), mode)
    assert len(out.inputFiles()) > 0
    got = sorted(map(tuple, out.collect()))
    if mode == "append":
        assert got == sorted(map(tuple, events.select("event_id", "event_type").collect()))
        return
    want = {r["event_type"]: r["count"] for r in events.groupBy("event_type").count().collect()}
    assert {k: max(n for x, n in got if x == k) for k, _ in got} == want
    assert len(got) == len(want) * (1 if mode == "complete" else 3)
