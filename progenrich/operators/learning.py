"""Parameters from validation objects: quality, cost, calibration, and the next-scorer table.

Outputs of all scorers are computed once; the probability of every mask follows by arithmetic, so no
scorer runs again for another order.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.entropy import entropy_bits
from ..model import Catalog
from ..session import cut
from .planning import NextScorer, uncertainty_bin
from .scorers import whole
from .state import Calibration, Query, raw_outputs


def validation_log(objects: DataFrame, query: Query) -> DataFrame:
    """``object_id, tag_type, tag, scorer, prob, truth, cost`` with raw outputs of every scorer."""
    parts = []
    for p in query.preds:
        t = query.catalog.type(p.type)
        scorers = query.catalog.of(p.type)
        scored = raw_outputs(objects, query.catalog, p.type, p.tag, scorers, keep=(t.truth,))
        cells = [F.struct(F.lit(s.number).alias("scorer"), F.col(f"f{s.number}").alias("prob"), F.lit(float(s.cost)).alias("cost")) for s in scorers]
        parts.append(scored.select("object_id", F.lit(p.type).alias("tag_type"), F.lit(str(p.tag)).alias("tag"), (F.col(t.truth) == F.lit(p.tag)).alias("truth"), F.inline(F.array(*cells))))
    return reduce(DataFrame.unionByName, parts)


def learn_quality(log: DataFrame) -> DataFrame:
    """Area under the ROC curve for each scorer, by mean ranks of equal outputs."""
    by = ["tag_type", "tag", "scorer"]
    # counts by distinct output first: the ordered window then has a row per value
    per = log.groupBy(*by, "prob").agg(F.count("*").alias("n"), F.count(F.when(F.col("truth"), 1)).alias("pos"))
    order = W.partitionBy(*by).orderBy("prob").rowsBetween(W.unboundedPreceding, -1)
    ranked = per.withColumn("below", F.coalesce(F.sum("n").over(order), F.lit(0)))
    sums = ranked.groupBy(*by).agg(F.sum(F.col("pos") * (F.col("below") + (F.col("n") + 1) / 2)).alias("r"), F.sum("pos").alias("pos"), F.sum("n").alias("n"))
    neg = F.col("n") - F.col("pos")
    auc = F.when((F.col("pos") > 0) & (neg > 0), (F.col("r") - F.col("pos") * (F.col("pos") + 1) / 2) / (F.col("pos") * neg))
    return sums.select(*by, auc.alias("auc"))


def roc_curve(log: DataFrame) -> DataFrame:
    """``fpr, tpr`` at each distinct output as threshold, highest first."""
    by = ["tag_type", "tag", "scorer"]
    per = log.groupBy(*by, "prob").agg(F.count(F.when(F.col("truth"), 1)).alias("pos"), F.count(F.when(~F.col("truth"), 1)).alias("neg"))
    order = W.partitionBy(*by).orderBy(F.desc("prob")).rowsBetween(W.unboundedPreceding, 0)
    every = W.partitionBy(*by)
    return per.select(*by, F.col("prob").alias("threshold"), (F.sum("neg").over(order) / F.sum("neg").over(every)).alias("fpr"), (F.sum("pos").over(order) / F.sum("pos").over(every)).alias("tpr"))


def learn_cost(log: DataFrame) -> DataFrame:
    return log.groupBy("tag_type", "scorer").agg(F.avg("cost").alias("mean_cost"), F.count("*").alias("n"))


def pick_seeds(catalog_df: DataFrame) -> DataFrame:
    """The scorer of best quality per cost of each type."""
    return catalog_df.groupBy("tag_type").agg(F.max_by("scorer", F.struct(F.col("quality") / F.col("cost"), -F.col("scorer"))).alias("seed"))


def reliability(log: DataFrame, bins: int = 20) -> DataFrame:
    """Share of objects with the tag by bin of output."""
    at = F.least(F.floor(F.col("prob") * bins), F.lit(bins - 1)).cast("int")
    return log.groupBy("tag_type", "tag", "scorer", at.alias("bin")).agg(F.count("*").alias("n"), F.avg("prob").alias("mean_prob"), F.avg(F.col("truth").cast("double")).alias("rate"))


def calibration_error(log: DataFrame, bins: int = 20) -> DataFrame:
    """Brier score, and the mean gap between output and rate over bins, for each scorer."""
    by = ["tag_type", "tag", "scorer"]
    brier = log.groupBy(*by).agg(F.avg(F.pow(F.col("prob") - F.col("truth").cast("double"), F.lit(2))).alias("brier"))
    gap = reliability(log, bins).groupBy(*by).agg((F.sum(F.col("n") * F.abs(F.col("mean_prob") - F.col("rate"))) / F.sum("n")).alias("gap"))
    return brier.join(gap, by)


def learn_calibration(objects: DataFrame, query: Query, bins: int = 20, fits: dict | None = None) -> Calibration:
    """Rates by bin; types x tags x scorers x bins rows reach the driver. Empty bins keep their middle.

    ``fits`` names the scorers (by type and number) that get a fitted map instead: "isotonic" or "platt".
    """
    rates: dict = {}
    tags = {(p.type, str(p.tag)): p.tag for p in query.preds}
    log = validation_log(objects, query)
    if fits:
        log = cut(log)
    for r in reliability(log, bins).collect():
        key = (r["tag_type"], tags[r["tag_type"], r["tag"]], r["scorer"])
        rates.setdefault(key, [(b + 0.5) / bins for b in range(bins)])[r["bin"]] = r["rate"]
    curves = {}
    for p in {(p.type, p.tag) for p in query.preds}:
        for (type_name, number), method in (fits or {}).items():
            if type_name == p[0]:
                rows = log.where((F.col("tag_type") == p[0]) & (F.col("tag") == str(p[1])) & (F.col("scorer") == number))
                curves[p[0], p[1], number] = calibration_curve(fit_calibration(rows, method), method)
    return Calibration(rates, bins, curves)


#: Most points of an isotonic map that is written out as literals.
CURVE_POINTS = 200


def calibration_curve(model, method: str) -> tuple:
    """A fitted map as ``Calibration`` holds it."""
    if method == "platt":
        return "sigmoid", float(model.coefficients[0]), float(model.intercept)
    xs, ys = model.boundaries.toArray().tolist(), model.predictions.toArray().tolist()
    step = -(-len(xs) // CURVE_POINTS)
    at = sorted({*range(0, len(xs), step), len(xs) - 1})
    return "isotonic", [xs[i] for i in at], [ys[i] for i in at]


def fit_calibration(log: DataFrame, method: str = "isotonic"):
    """A fitted monotone map of one scorer's raw output: isotonic regression, or a sigmoid (Platt)."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import IsotonicRegression

    rows = log.select("prob", F.col("truth").cast("double").alias("label"))
    if method == "isotonic":
        return IsotonicRegression(featuresCol="prob", labelCol="label").fit(rows)
    if method == "platt":
        return LogisticRegression(featuresCol="x").fit(VectorAssembler(inputCols=["prob"], outputCol="x").transform(rows))
    raise ValueError(f"unknown calibration {method!r}")


def reductions(objects: DataFrame, query: Query, bins: int = 10) -> DataFrame:
    """``object_id, tag_type, tag, mask, bin, scorer, dh, cost`` for every mask with the seed and every
    scorer that is left. Pred i stands for its (type, tag, op)."""
    parts = []
    for i, p in enumerate(query.preds):
        scorers = query.scorers(i)
        seed = query.catalog.seed(p.type).number
        outs = raw_outputs(objects, query.catalog, p.type, p.tag, scorers)
        outs = outs.select("object_id", *[query.adjusted(i, s, F.col(f"f{s.number}")).alias(f"f{s.number}") for s in scorers])

        def blended(mask: int):
            on = [s for s in scorers if mask >> s.number & 1]
            return sum((F.lit(s.quality) * F.col(f"f{s.number}") for s in on), F.lit(0.0)) / F.lit(sum(s.quality for s in on))

        masks = [m for m in range(1, query.full_mask(i) + 1) if m >> seed & 1]
        outs = outs.select("object_id", *[entropy_bits(blended(m)).alias(f"h{m}") for m in masks])
        cells = [
            F.struct(F.lit(m).alias("mask"), uncertainty_bin(F.col(f"h{m}"), bins).alias("bin"), F.lit(s.number).alias("scorer"), (F.col(f"h{m | 1 << s.number}") - F.col(f"h{m}")).alias("dh"), F.lit(float(s.cost)).alias("cost"))
            for m in masks for s in scorers if not m >> s.number & 1
        ]
        parts.append(outs.select("object_id", F.lit(p.type).alias("tag_type"), F.lit(str(p.tag)).alias("tag"), F.inline(F.array(*cells))))
    return reduce(DataFrame.unionByName, parts)


def next_scorer_table(rows: DataFrame, pick: str = "avg") -> DataFrame:
    """``tag_type, tag, mask, bin, scorer, delta_h, n``: the best scorer for each cell.

    ``avg``: greatest mean reduction; ``per_cost``: the same for a unit of cost; ``vote``: the scorer that is
    best for most objects. The key space is tiny, so partial aggregation shrinks the shuffle to it.
    """
    cell = ["tag_type", "tag", "mask", "bin"]
    means = rows.groupBy(*cell, "scorer").agg(F.avg("dh").alias("delta_h"), F.count("*").alias("n"), F.first("cost").alias("cost"))
    if pick == "vote":
        best = rows.groupBy("object_id", *cell).agg(F.min(F.struct("dh", "scorer")).alias("b"))
        votes = best.groupBy(*cell, F.col("b.scorer").alias("scorer")).agg(F.count("*").alias("votes"))
        ranked = votes.join(means, [*cell, "scorer"]).withColumn("k", F.row_number().over(W.partitionBy(*cell).orderBy(F.desc("votes"), "scorer")))
    else:
        value = F.col("delta_h") / F.col("cost") if pick == "per_cost" else F.col("delta_h")
        # rounding keeps the choice among equals the same in every engine
        ranked = means.withColumn("k", F.row_number().over(W.partitionBy(*cell).orderBy(F.floor(value * 1e9), "scorer")))
    return ranked.where("k = 1").select(*cell, "scorer", "delta_h", "n")


def learn_next_scorer(objects: DataFrame, query: Query, bins: int = 10, pick: str = "avg") -> NextScorer:
    """The table as literals, with a row for each mask over all bins where a cell saw no object."""
    rows = reductions(objects, query, bins)
    if any(s.column is None for i in range(len(query.preds)) for s in query.scorers(i)):
        rows = cut(rows)  # both passes below would score every object again
    tags = {(p.type, str(p.tag)): p.tag for p in query.preds}
    cells = {}
    for r in next_scorer_table(rows.withColumn("bin", F.lit(-1)), pick).collect():
        cells[r["tag_type"], tags[r["tag_type"], r["tag"]], r["mask"], None] = (r["scorer"], r["delta_h"])
    for r in next_scorer_table(rows, pick).collect():
        cells[r["tag_type"], tags[r["tag_type"], r["tag"]], r["mask"], r["bin"]] = (r["scorer"], r["delta_h"])
    return NextScorer(cells, bins)


def learn_online(objects: DataFrame, query: Query, percent: int = 5, bins: int = 10, pick: str = "avg") -> tuple[NextScorer, DataFrame]:
    """Table and costs from a share of the query's own objects, chosen by key; part of the first epoch pays."""
    sample = online_sample(objects, percent)
    return learn_next_scorer(sample, query, bins, pick), learn_cost(validation_log(sample, query))


def online_sample(objects: DataFrame, percent: int) -> DataFrame:
    return objects.where(F.pmod(whole(F.col("object_id"), 11), F.lit(100)) < percent)


def catalog_with(catalog: Catalog, auc: DataFrame) -> Catalog:
    """The catalog with learned qualities, the mean over the tags that were seen."""
    from dataclasses import replace

    seen = {(r["tag_type"], r["scorer"]): r["q"] for r in auc.groupBy("tag_type", "scorer").agg(F.avg("auc").alias("q")).collect()}
    return Catalog(catalog.types, tuple(replace(s, quality=seen.get((s.tag_type, s.number), s.quality)) for s in catalog.scorers))
