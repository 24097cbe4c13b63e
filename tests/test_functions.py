"""Expressions, entropy and probabilities against hand-made values and enumeration."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from progenrich.functions import entropy
from progenrich.functions.blending import blend
from progenrich.functions.tagexpr import And, Or, Pred, holds, match_probability, negate, normalize, parse_tag_expr, predicates, split_predicates


def test_parse_and_normal_form():
    e = parse_tag_expr("NOT (A = 'x' OR B != 3) AND (C IN ('p', 'q') OR D = 'it''s')")
    assert e == And((Pred("A", "x", "!="), Pred("B", 3), Or((Pred("C", "p"), Pred("C", "q"), Pred("D", "it's")))))
    assert normalize(And((And((Pred("A", 1), Pred("B", 1))), Pred("A", 1)))) == And((Pred("A", 1), Pred("B", 1)))
    assert negate(negate(e)) == e
    for bad in ("A =", "A = 'x' AND", "(A = 1", "A LIKE 'x'", "A = 1 B = 2"):
        with pytest.raises(ValueError):
            parse_tag_expr(bad)


def test_split_predicates():
    exact, tags = split_predicates(["n > 3", "tag:A = 1", Pred("B", 2)])
    assert exact == ["n > 3"] and tags == [Pred("A", 1), Pred("B", 2)]


def value(spark, column):
    return spark.range(1).select(column.cast("double")).first()[0]


def enumerate_worlds(e, p):
    """Sum over assignments with exclusive tags within a type."""
    tags = {}
    for x in predicates(e):
        tags.setdefault(x.type, set()).add(x.tag)
    total = 0.0
    for world in itertools.product(*[[(t, v) for v in [*sorted(vs), None]] for t, vs in tags.items()]):
        if holds(e, dict(world)):
            m = 1.0
            for t, v in world:
                m *= p[t, v] if v is not None else 1 - sum(p[t, x] for x in tags[t])
            total += m
    return total


EXPRESSIONS = [
    "A = 'x'", "A != 'x'", "A = 'x' AND B = 'u'", "A = 'x' OR B = 'u'", "A = 'x' OR A = 'y'", "A = 'x' AND A = 'y'", "(A = 'x' AND B = 'u') OR (A = 'y' AND B != 'u')",
    "NOT (A = 'x' OR B = 'u') OR (A = 'x' AND C = 'k')", "A != 'x' AND A != 'y'", "(A = 'x' OR C = 'k') AND (A = 'x' OR B = 'u')",
]


@pytest.mark.parametrize("text", EXPRESSIONS)
def test_match_probability_is_the_sum_over_worlds(spark, text):
    e = parse_tag_expr(text)
    p = {("A", "x"): 0.3, ("A", "y"): 0.45, ("B", "u"): 0.6, ("C", "k"): 0.2}
    cols = {q: F.lit(p[q.type, q.tag] if q.op == "=" else 1 - p[q.type, q.tag]) for q in predicates(e)}
    assert value(spark, match_probability(e, cols)) == pytest.approx(enumerate_worlds(e, p), abs=1e-12)
    assert value(spark, match_probability(e, cols, "worlds")) == pytest.approx(enumerate_worlds(e, p), abs=1e-12)


def test_too_many_worlds():
    e = And(tuple(Pred(f"T{i}", j) for i in range(13) for j in range(2)))
    with pytest.raises(ValueError):
        match_probability(e, {p: F.lit(0.5) for p in predicates(e)}, "worlds")


def test_entropy_examples(spark):
    for p, h in ((0.7, 0.8813), (0.66, 0.9248), (0.84, 0.6343), (0.0, 0.0), (1.0, 0.0), (0.5, 1.0)):
        assert value(spark, entropy.entropy_bits(F.lit(p))) == pytest.approx(h, abs=5e-5)
    assert value(spark, entropy.entropy_of([F.lit(0.25)] * 4)) == pytest.approx(2.0)


def test_inverse_entropy(spark):
    assert value(spark, entropy.inverse_entropy(F.lit(0.64))) == pytest.approx(0.8376, abs=5e-4)
    assert value(spark, entropy.inverse_entropy(F.lit(0.64), "lower")) == pytest.approx(0.1624, abs=5e-4)
    rows = spark.range(0, 2001).select((F.col("id") / 2000.0).alias("h")).select("h", entropy.inverse_entropy(F.col("h")).alias("p")).select("h", "p", entropy.entropy_bits(F.col("p")).alias("b")).collect()
    assert max(abs(r["h"] - r["b"]) for r in rows) < 1e-6 and all(0.5 <= r["p"] <= 1 for r in rows)
    staged = entropy.with_upper_root(spark.range(0, 101).select((F.col("id") / 100.0).alias("h")), {"r": "h"}).select((F.abs(F.col("r") - entropy.inverse_entropy(F.col("h")))).alias("d"))
    assert staged.agg(F.max("d")).first()[0] < 1e-12


def test_raised_probability_never_falls(spark):
    for p, h in ((0.3, 0.2), (0.7, 0.5), (0.1, 0.95), (0.9, 1.0)):
        q = value(spark, entropy.raised_probability(F.lit(p), F.lit(h)))
        assert q >= p
    assert value(spark, entropy.raised_probability(F.lit(0.1), F.lit(0.95))) < 0.5


def test_blenders(spark):
    outs, w = [F.lit(0.9), F.lit(0.4)], [3.0, 1.0]
    m = lambda k: F.lit(k)
    assert value(spark, blend(m(3), outs, w)) == pytest.approx((2.7 + 0.4) / 4)
    assert value(spark, blend(m(1), outs, w)) == pytest.approx(0.9)
    assert value(spark, blend(m(1), outs, [0.75, 0.25], missing="literal")) == pytest.approx(0.675)
    assert value(spark, blend(m(3), outs, w, op="!=")) == pytest.approx(1 - 3.1 / 4)
    assert value(spark, blend(m(3), outs, w, kind="mean")) == pytest.approx(0.65)
    assert value(spark, blend(m(3), outs, w, kind="max")) == pytest.approx(0.9)
    assert value(spark, blend(m(3), outs, w, kind="noisy_or")) == pytest.approx(0.94)
    odds = (math.log(9) + math.log(2 / 3)) / 2
    assert value(spark, blend(m(3), outs, w, kind="log_odds")) == pytest.approx(1 / (1 + math.exp(-odds)))
    assert value(spark, blend(m(0), outs, w)) == 0.5
    random.seed(0)
