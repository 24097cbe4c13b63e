"""The cutoff: worked examples, brute force over subsets, agreement of all methods."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from progenrich.operators import cutoff


def state(spark, ps):
    return spark.createDataFrame([(i, float(p)) for i, p in enumerate(ps)], "object_id long, match_p double").coalesce(2)


def f_of(ps, members, alpha=1.0):
    return (1 + alpha) * sum(ps[i] for i in members) / (alpha * sum(ps) + len(members)) if members else 0.0


FIVE = [0.9, 0.8, 0.75, 0.3, 0.2]


def test_prefix_example():
    assert [round(f_of(FIVE, range(k)), 4) for k in range(1, 6)] == [0.4557, 0.6869, 0.8235, 0.7914, 0.7421]


@pytest.mark.parametrize("method", list(cutoff.METHODS))
def test_five_objects(spark, method):
    a = cutoff.choose_answer(state(spark, FIVE), 1.0, method)
    assert a.size == 3 and a.expected_f == pytest.approx(0.8235, abs=5e-5)


@pytest.mark.parametrize("at, p, best", [(1, 0.78, 0.8156), (1, 0.5, 0.7), (3, 0.7, None), (3, 0.31, 0.8221), (3, 0.45, 0.8169), (3, 0.1, 0.8522)])
def test_changes_of_one_object(spark, at, p, best):
    ps = list(FIVE)
    ps[at] = p
    brute = max(f_of(ps, s) for k in range(6) for s in itertools.combinations(range(5), k))
    a = cutoff.choose_answer(state(spark, ps))
    assert a.expected_f == pytest.approx(brute)
    if best and at == 3:
        assert brute == pytest.approx(best, abs=5e-5)


def test_brute_force_over_subsets(spark):
    rng = random.Random(3)
    for alpha in (0.25, 0.5, 1.0, 2.0):
        for _ in range(2):
            ps = [rng.choice([rng.random(), round(rng.random(), 1)]) for _ in range(8)]
            brute = max(f_of(ps, s, alpha) for k in range(9) for s in itertools.combinations(range(8), k))
            for m in cutoff.METHODS:
                assert cutoff.choose_answer(state(spark, ps), alpha, m).expected_f == pytest.approx(brute), (m, ps, alpha)


@pytest.mark.parametrize("ps, size", [([], 0), ([0.0, 0.0], 0), ([0.4] * 4, 4), ([0.7], 1), ([1.0, 1.0, 0.9], 3)])
def test_degenerate(spark, ps, size):
    for m in cutoff.METHODS:
        assert cutoff.choose_answer(state(spark, ps), 1.0, m).size == size, m


def test_methods_agree_on_many(spark):
    df = spark.range(0, 20_000).select(F.col("id").alias("object_id"), F.pow(F.pmod(F.col("id") * 7919, F.lit(10007)) / 10007.0, F.lit(3)).alias("match_p"))
    found = [cutoff.choose_answer(df, 1.0, m) for m in ("ratio", "bins", "sort")]
    assert len({a.size for a in found}) == 1
    assert max(a.ratio for a in found) - min(a.ratio for a in found) < 1e-12
    assert cutoff.by_bins(df, bins=16).size == found[0].size


def test_answer_changes(spark):
    a, b = state(spark, [0.9, 0.1]), state(spark, [0.9, 0.1, 0.8]).where("object_id > 0")
    rows = {(r["object_id"], r["present"]) for r in cutoff.answer_changes(a, b, 1).collect()}
    assert rows == {(0, False), (2, True)}
