"""Queries that run the whole workload, with no early stop."""

import pytest
from harness import SF

from progenrich import plans
from progenrich.operators.scorers import LADDER
from progenrich.plans import workloads as w

SMALLEST = "/root/testdata/sf0.001"
QUERIES = plans.queries()


def test_plans_are_not_capped(spark, tmp_path):
    keys = spark.range(100_500).selectExpr("id * 40 AS o_orderkey")
    keys.write.parquet(f"{tmp_path}/orders.parquet")
    keys.selectExpr("o_orderkey AS l_orderkey", "1 AS l_linenumber", "2 AS l_partkey").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert QUERIES["join_broadcast_plan"](spark, str(tmp_path)).count() == 100_500


@pytest.mark.parametrize("name, key, table", [("agg_mode", "g", "(SELECT o_custkey % 7 AS g FROM orders)"), ("stream_dedup", "user_id", "events"), ("stream_session", "user_id", "events"), ("sql_table_function", "object_id", "(SELECT o_orderkey AS object_id FROM orders)")])
def test_every_key_is_there(spark, con, name, key, table):
    got = {r[key] for r in QUERIES[name](spark, SF).select(key).collect()}
    assert got == {k for (k,) in con.execute(f"SELECT DISTINCT {key} FROM {table}").fetchall()}


def test_completion_spends_every_scorer(spark):
    chosen, q, _ = w.prepared(spark, SMALLEST, w.SMALL_100)
    all_cost = chosen.count() * sum(c for c, _, _ in LADDER[1:])  # the seed is the first scorer
    spent = {r["approach"]: r["spent"] for r in QUERIES["completion_cost_whole"](spark, SMALLEST).collect()}
    assert spent == {a: pytest.approx(all_cost) for a in w.APPROACHES}
    ends = {}
    for r in QUERIES["gain_curve_whole"](spark, SMALLEST).collect():
        ends[r["approach"]] = max(ends.get(r["approach"], 0.0), r["spent"])
    assert ends == {a: pytest.approx(all_cost) for a in w.APPROACHES}
