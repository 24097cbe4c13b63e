"""The answer of an epoch: the objects whose match probability exceeds the best expected ratio.

With K the sum of all match probabilities, a set has the expected F-measure (1+a)*sum(P)/(a*K + size).
It is greatest for the objects with P above lambda, where lambda = sum(P)/(a*K + size) of that very set.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

BINS = 1 << 16


@dataclass(frozen=True)
class Answer:
    ratio: float
    alpha: float
    total: float
    size: int
    mass: float
    open: int | None = None  # objects outside that have a scorer left, where they were counted

    @property
    def expected_f(self) -> float:
        return (1 + self.alpha) * self.ratio

    @property
    def precision(self) -> float:
        return self.mass / self.size if self.size else 0.0

    @property
    def recall(self) -> float:
        return self.mass / self.total if self.total else 0.0

    def members(self, state: DataFrame) -> DataFrame:
        return state.where(F.col("match_p") > F.lit(self.ratio))


def _above(state: DataFrame, ratio: float, alpha: float, left: str | None = None) -> Answer:
    inside = f"match_p > {float(ratio)!r}D"
    r = state.selectExpr("sum(match_p) AS k", f"sum(CASE WHEN {inside} THEN match_p END) AS s", f"count(CASE WHEN {inside} THEN 1 END) AS n", f"count(CASE WHEN NOT ({inside}) AND ({left or 'false'}) THEN 1 END) AS o").first()
    return Answer(ratio, alpha, r["k"] or 0.0, r["n"], r["s"] or 0.0, r["o"] if left else None)


def _start(state: DataFrame, alpha: float, bins: int = 1024) -> float:
    """A ratio that some prefix of whole bins has, so none above the best: one aggregate of at most ``bins`` rows."""
    rows = state.selectExpr(f"CAST(least(floor(match_p * {bins}), {bins - 1}) AS int) AS b", "match_p").groupBy("b").agg(F.expr("count(*) AS n"), F.expr("sum(match_p) AS s")).collect()
    rows.sort(key=lambda r: -r["b"])
    total, ratio, n, s = sum(r["s"] for r in rows), 0.0, 0, 0.0
    for r in rows if total else ():
        n, s = n + r["n"], s + r["s"]
        ratio = max(ratio, s / (alpha * total + n))
    return ratio


def by_ratio(state: DataFrame, alpha: float = 1.0, rounds: int = 64, left: str | None = None) -> Answer:
    """Fixed point of the ratio, upwards from the best cut between bins: a few aggregates, no sort and no exchange of rows."""
    ratio = _start(state, alpha)
    for _ in range(rounds):
        a = _above(state, ratio, alpha, left)
        new = a.mass / (alpha * a.total + a.size) if a.size else 0.0
        if new <= ratio:
            return a
        ratio = new
    return _above(state, ratio, alpha, left)


def by_bins(state: DataFrame, alpha: float = 1.0, bins: int = BINS) -> Answer:
    """One pass of sums by bin, the fixed point on the driver, and one pass over the bin that it falls in.

    The driver gets a row per bin, whatever the number of objects.
    """
    at = F.least(F.floor(F.col("match_p") * bins), F.lit(bins - 1)).cast("int")
    rows = state.groupBy(at.alias("b")).agg(F.count("*").alias("n"), F.sum("match_p").alias("s")).collect()
    rows.sort(key=lambda r: -r["b"])
    total = sum(r["s"] for r in rows)
    if not total:
        return Answer(0.0, alpha, total, 0, 0.0)
    ratio, n, s, above = 0.0, 0, 0.0, {}
    for r in rows:
        above[r["b"]] = (n, s)
        n, s = n + r["n"], s + r["s"]
        ratio = max(ratio, s / (alpha * total + n))
    while True:
        # bins above that of the ratio are in as a whole; only the one bin it falls in is looked at again
        b = min(int(ratio * bins), bins - 1)
        n, s = above.get(b) or max(((c, above[c]) for c in above if c < b), default=(0, (n, s)))[1]
        x = state.where((at == b) & (F.col("match_p") > F.lit(ratio))).agg(F.count("*").alias("n"), F.sum("match_p").alias("s")).first()
        a = Answer(ratio, alpha, total, n + x["n"], s + (x["s"] or 0.0))
        new = a.mass / (alpha * total + a.size) if a.size else 0.0
        if new <= ratio:
            return a
        ratio = new


def by_sort(state: DataFrame, alpha: float = 1.0) -> Answer:
    """Reference: a global order and running sums. One task sees all objects; for small inputs."""
    ranked = state.select("match_p", F.row_number().over(W.orderBy(F.desc("match_p"), "object_id")).alias("k"), F.sum("match_p").over(W.orderBy(F.desc("match_p"), "object_id").rowsBetween(W.unboundedPreceding, 0)).alias("s"))
    total = state.agg(F.sum("match_p")).first()[0] or 0.0
    best = ranked.select((F.col("s") / (alpha * total + F.col("k"))).alias("r")).agg(F.max("r")).first()[0] if total else 0.0
    return _above(state, best or 0.0, alpha)


def by_rule(state: DataFrame, alpha: float = 1.0) -> Answer:
    """Reference: an object is admitted while its P exceeds the running sum before it over (k - 1 + a*K)."""
    order = W.orderBy(F.desc("match_p"), "object_id")
    total = state.agg(F.sum("match_p")).first()[0] or 0.0
    before = F.coalesce(F.sum("match_p").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    ranked = state.select("match_p", before.alias("s"), F.row_number().over(order).alias("k"))
    admitted = ranked.where(F.col("match_p") > F.col("s") / (F.col("k") - 1 + alpha * total)) if total else ranked.limit(0)
    r = admitted.agg(F.count("*").alias("n"), F.sum("match_p").alias("s")).first()
    return _above(state, (r["s"] or 0.0) / (alpha * total + r["n"]) if r["n"] else 0.0, alpha)


METHODS = {"ratio": by_ratio, "bins": by_bins, "sort": by_sort, "rule": by_rule}


def choose_answer(state: DataFrame, alpha: float = 1.0, method: str = "ratio", left: str | None = None) -> Answer:
    """Answer of a state with ``match_p``. An empty state, or one of zeros, has an empty answer; equal
    probabilities stay together. The method by ratio also counts the objects outside for which ``left`` holds."""
    return by_ratio(state, alpha, left=left) if method == "ratio" else METHODS[method](state, alpha)


def expected_quality(state: DataFrame, members: str, alpha: float = 1.0) -> DataFrame:
    """Expected precision, recall and F of the objects for which the boolean column ``members`` is true."""
    inside = F.coalesce(F.sum(F.when(F.col(members), F.col("match_p"))), F.lit(0.0))
    size, total = F.count(F.when(F.col(members), 1)), F.sum("match_p")
    return state.agg(
        F.when(size > 0, inside / size).otherwise(0.0).alias("expected_precision"),
        F.when(total > 0, inside / total).otherwise(0.0).alias("expected_recall"),
        F.when(alpha * total + size > 0, (1 + alpha) * inside / (alpha * total + size)).otherwise(0.0).alias("expected_f"),
    )


def answer_changes(before: DataFrame, after: DataFrame, epoch: int) -> DataFrame:
    """``object_id, epoch, present``: rows that entered (true) or left (false) the answer."""
    a, b = before.select("object_id", F.lit(True).alias("was")), after.select("object_id", F.lit(True).alias("now"))
    both = a.join(b, "object_id", "full_outer").where(F.col("was").isNull() | F.col("now").isNull())
    return both.select("object_id", F.lit(epoch).alias("epoch"), F.col("now").isNotNull().alias("present"))
