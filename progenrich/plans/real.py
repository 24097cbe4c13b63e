"""Workloads with real scorers: text classifiers and rules, containment, and vectors without signal."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..model import Catalog
from ..operators import learning, sqlsurface
from ..operators import text_scorers as t
from ..operators.enrich import CURVE, EnrichmentRun, Settings
from ..operators.state import Query
from ..session import cut
from ..sources.objects import COLLECTIONS, objects, split_part
from ..sources.tables import table
from . import workloads as w
from .methods import S1, upto
from .registry import query


def _docs(spark, sf):
    d = t.extract_features(objects(spark, sf, "docs").where(F.length("text") > 0))
    return d.withColumn("y", F.col("t_quality").cast("double"))


@query("real_scorer_auc")
def _(spark, sf):
    """Area under the ROC curve of each fitted classifier on held-out documents."""
    d = _docs(spark, sf)
    d = cut(d.select("object_id", "y", *t.FEATURES))
    train, test = d.where(split_part() < 5), d.where(split_part() >= 5)
    out, models = None, {kind: t.fit_classifier(kind, train, list(t.FEATURES), "y") for kind in t.CLASSIFIERS}
    for i, kind in enumerate((*t.CLASSIFIERS, "ensemble")):
        scored = t.with_ensemble(test, models) if kind == "ensemble" else t.positive(models[kind], test, kind)
        part = scored.select("object_id", F.lit("Quality").alias("tag_type"), F.lit(kind).alias("tag"), F.lit(i).alias("scorer"), "prob", (F.col("y") == 1).alias("truth"))
        out = part if out is None else out.unionByName(part)
    return learning.learn_quality(out)


@query("lexical_scorers", r"SELECT doc_id AS object_id, CASE WHEN regexp_matches(lower(text), '(idiot|moron|clown)') THEN 0.95 ELSE 0.05 END AS toxic, greatest(0.02, least(0.98, 1 - 12 * len(regexp_extract_all(text, '[!%*#$&]'))::DOUBLE / greatest(length(text), 1))) AS quality FROM documents", "toxic quality")
def _(spark, sf):
    d = table(spark, sf, "documents", F.col("doc_id").alias("object_id"), "text")
    return d.select("object_id", t.lexical_toxic(F.col("text")).alias("toxic"), t.lexical_quality(F.col("text")).alias("quality"))


@query("lang_scorer_accuracy")
def _(spark, sf):
    d = table(spark, sf, "documents", "doc_id", "text", "lang")
    best = F.array_max(F.array(*[F.struct(t.lexical_lang(F.col("text"), k).alias("p"), F.lit(k).alias("k")) for k in t.STOPS]))["k"]
    return d.groupBy("lang").agg(F.avg((best == F.col("lang")).cast("double")).alias("accuracy"), F.count("*").alias("n"))


@query("containment_scorer")
def _(spark, sf):
    d = table(spark, sf, "documents", F.col("doc_id").alias("object_id"), "text")
    b = table(spark, sf, "benchmark", "item_id", "text")
    dear, cheap = t.containment(d, b), t.containment(d, b, rate=4).withColumnRenamed("prob", "cheap")
    return dear.join(cheap, "object_id").where("prob > 0")


def real_runs(spark, sf, approaches=w.APPROACHES, share=0.5, epochs=w.UNTIL_DONE):
    """Curves of the approaches with fitted classifiers on documents, each calibrated, until nothing is left.

    Parts 0-3 train, 4-5 validate (quality, calibration, next-scorer table), 6-9 are queried: low quality, the rare tag.
    """
    made = cut(_docs(spark, sf).drop("text"))  # features are extracted once, before any query
    train, validation, chosen = made.where(split_part() < 4), made.where(split_part().between(4, 5)), made.where(split_part() >= 6)
    fitted, fits = t.fitted_scorers("Quality", train, "t_quality")
    c = COLLECTIONS["docs"]
    q = Query(w.parse_tag_expr("Quality = 0"), Catalog(c.types, tuple(fitted)))
    catalog = learning.catalog_with(q.catalog, learning.learn_quality(cut(learning.validation_log(validation, q))))
    q = Query(q.expr, catalog)
    q = Query(q.expr, catalog, learning.learn_calibration(validation, q, fits=fits))
    table_ = learning.learn_next_scorer(validation, q)
    budget = share * sum(s.cost for s in fitted) * chosen.count()
    rows = []
    for a in approaches:
        rows += EnrichmentRun(chosen, q, budget, table_, Settings(approach=a)).curve(epochs)
    return spark.createDataFrame([(a, e, s, int(i), int(n), float(x), float(f)) for a, e, s, i, n, x, f in rows], CURVE)


@query("exp1_docs_real")
def _(spark, sf):
    return real_runs(spark, sf)


@query("exp1_docs_lexical")
def _(spark, sf):
    """The operator with a rule as its one scorer: it seeds the state, and nothing is left to run."""
    c = COLLECTIONS["docs"]
    q = Query(w.parse_tag_expr("Toxic = 1"), Catalog(c.types, tuple(t.text_catalog_scorers())))
    run = EnrichmentRun(objects(spark, sf, "docs").where(split_part() >= 2), q, 60.0)
    return spark.createDataFrame([("lexical", e, s, i, n, float(x), float(f)) for _, e, s, i, n, x, f in run.curve(3)], CURVE)


@query("exp10_control")
def _(spark, sf):
    """Negative control: neighbours of vectors whose labels carry no signal must score near one half."""
    v = objects(spark, sf, "vectors")
    train, test = v.where(split_part() < 5), v.where(split_part() >= 5)
    scored = t.knn(train, test, "embedding", "t_cluster", 1, k=15)
    log = scored.join(test.select("object_id", "t_cluster"), "object_id").select("object_id", F.lit("Cluster").alias("tag_type"), F.lit("1").alias("tag"), F.lit(0).alias("scorer"), "prob", (F.col("t_cluster") == 1).alias("truth"))
    return learning.learn_quality(log)


@query("sql_enrich", upto(replace(S1, epochs=1), 1, "SELECT object_id, P AS match_p FROM st1, lam1 WHERE P > lam"), "match_p")
def _(spark, sf):
    chosen, q, table_ = w.prepared(spark, sf, S1)
    objects(spark, sf, "orders").where(split_part() >= 2).createOrReplaceTempView("obj_orders")
    budget = S1.share * w.FULL_COST * chosen.count()
    out = sqlsurface.enrich_sql(spark, f"ENRICH obj_orders SATISFYING Status = 'F' WHERE {S1.where} BUDGET {budget!r} EPOCHS 1", q.catalog, table_, q.calibration)
    return out.select("object_id", "match_p")


@query("sql_functions", "SELECT o_orderkey, CASE WHEN x <= 0 OR x >= 1 THEN 0 ELSE -x * log2(x) - (1 - x) * log2(1 - x) END AS h, x * 0.9 / 3 AS b FROM (SELECT o_orderkey, (o_orderkey % 100) / 100.0::DOUBLE AS x FROM orders)", "h b")
def _(spark, sf):
    sqlsurface.register_functions(spark)
    table(spark, sf, "orders", "o_orderkey").selectExpr("o_orderkey", "o_orderkey % 100 / 100D AS x").createOrReplaceTempView("entropy_in")
    return spark.sql("SELECT o_orderkey, entropy_bits(x) AS h, relative_benefit(x, 0.9D, 3D) AS b FROM entropy_in")


@query("sql_table_function", "SELECT o_orderkey AS object_id, ((o_orderkey % 10) / 10.0::DOUBLE) / 2 AS benefit FROM orders", "benefit")
def _(spark, sf):
    return _items(spark, sf)


def _items(spark, sf):
    sqlsurface.register_item_function(spark)
    table(spark, sf, "orders", "o_orderkey").selectExpr("o_orderkey AS object_id", "o_orderkey % 10 / 10D AS p", "2D AS cost").createOrReplaceTempView("item_in")
    return spark.sql("SELECT * FROM enrich_items(TABLE(item_in))")


@query("doc_tfidf")
def _(spark, sf):
    """Hashed features of all documents."""
    return t.hashed_tfidf(objects(spark, sf, "docs").select("object_id", "text"))
