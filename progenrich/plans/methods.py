"""Queries for the methods, variants, baselines and measures."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import entropy
from ..functions.blending import blend
from ..functions.tagexpr import Pred, match_probability, parse_tag_expr
from ..operators import baselines, blocks, cutoff, joins, learning, metrics, pair_join, planning
from ..operators.enrich import EnrichmentRun, Settings, changes, enrich_budget, enrich_many, full_enrichment
from ..operators.execution import execute_plan
from ..operators.scorers import LADDER, noise, simulated
from ..operators.state import Query, apply_outputs, cached_log, seed_state, state_from_log, state_vector
from ..sources.objects import COLLECTIONS, objects, split_part
from ..sources.tables import table
from . import workloads as w
from .epoch_sql import SpecSql, curves_sql, h_sql, noise_sql, raw_sql
from .registry import query

S1, S3 = w.SMALL_100, w.Q3
CURVE = "spent expected_f f1"


def upto(spec, epochs: int, final: str, items: bool = False) -> str:
    """SQL with everything up to the state of an epoch (and the items planned from it)."""
    s = SpecSql(spec)
    ctes = [*s.base(), *s.table(), s.start(), *s.state(0)]
    for e in range(epochs):
        ctes += [*s.epoch(e), *s.state(e + 1)]
    if items:
        ctes.append(s.items(epochs))
    truth = " AND ".join(f"({s.has(i)})" for i in range(s.k))
    ctes.append(f"truth AS MATERIALIZED (SELECT object_id, ({truth}) AS rel FROM chosen)")
    return f"SELECT * FROM (WITH {', '.join(ctes)} {final})"


def seeded(spark: SparkSession, sf_dir: str, spec=S1):
    chosen, q, t = w.prepared(spark, sf_dir, spec)
    return chosen, q, t, seed_state(chosen, q)


def last_epoch(spark, sf_dir, spec):
    e = None
    for e in w.run(spark, sf_dir, spec).epochs(spec.epochs):
        pass
    return e


# --- the operator and its modes -------------------------------------------------------------------

ONE = replace(S1, epochs=1)
TWO = replace(S1, epochs=2)
MEMBERS = "SELECT object_id, P AS match_p, CAST({e} AS INTEGER) AS epoch FROM st{e}, lam{e} WHERE P > lam"


@query("enrich_orders_q1", upto(S1, 2, MEMBERS.format(e=2)), "match_p")
def _(spark, sf):
    return last_epoch(spark, sf, TWO).members()


WHOLE = replace(S1, where="true", share=0.01, epochs=1)


@query("mode_table_function", upto(WHOLE, 1, f"SELECT t.object_id, P AS match_p FROM st1 t JOIN chosen USING (object_id), lam1 WHERE P > lam AND {w.ORDERS_100}"), "match_p")
def _(spark, sf):
    chosen, _, _ = w.prepared(spark, sf, WHOLE)
    return last_epoch(spark, sf, WHOLE).members().join(chosen.where(w.ORDERS_100).select("object_id"), "object_id").select("object_id", "match_p")


@query("mode_pushdown", upto(ONE, 1, "SELECT object_id, P AS match_p FROM st1, lam1 WHERE P > lam"), "match_p")
def _(spark, sf):
    return last_epoch(spark, sf, ONE).members().select("object_id", "match_p")


@query("enrich_multi_epoch", curves_sql([("progressive", S1)]), CURVE)
def _(spark, sf):
    return w.curves(spark, sf, [("progressive", S1)])


SECOND = replace(S1, expr="Priority = '1-URGENT'", epochs=1)


@query("multi_operator_join", f"SELECT a.object_id, a.match_p AS p_status, b.match_p AS p_priority FROM ({upto(ONE, 1, 'SELECT object_id, P AS match_p FROM st1, lam1 WHERE P > lam')}) a JOIN ({upto(SECOND, 1, 'SELECT object_id, P AS match_p FROM st1, lam1 WHERE P > lam')}) b ON a.object_id = b.object_id", "p_status p_priority")
def _(spark, sf):
    a, b = enrich_many([w.run(spark, sf, ONE), w.run(spark, sf, SECOND)], 1)
    left = a[-1].members().select("object_id", F.col("match_p").alias("p_status"))
    return left.join(b[-1].members().select("object_id", F.col("match_p").alias("p_priority")), "object_id")


DIFF = """SELECT object_id, epoch, present FROM (
  SELECT object_id, CAST({b} AS INTEGER) AS epoch, b.P > (SELECT lam FROM lam{b}) AS present, a.P > (SELECT lam FROM lam{a}) AS was FROM st{a} a JOIN st{b} b USING (object_id)) WHERE present <> was"""


@query("answer_diff", upto(S1, 2, DIFF.format(a=0, b=1) + " UNION ALL " + DIFF.format(a=1, b=2)))
def _(spark, sf):
    return changes(list(w.run(spark, sf, TWO).epochs(2)))


@query("budget_run", curves_sql([("budget", TWO)]) + " WHERE epoch = 2", CURVE)
def _(spark, sf):
    run = w.run(spark, sf, TWO)
    e = enrich_budget(run, 1.5 * run.budget)
    return spark.createDataFrame([("budget", e.number, float(e.spent), e.items, e.answer.size, e.answer.expected_f, e.f1)], w.CURVE)


# --- probabilities --------------------------------------------------------------------------------

ORDERS = "(SELECT o_orderkey AS object_id, o_orderstatus AS t_status FROM orders)"


def _four(spark, sf):
    o = table(spark, sf, "orders", F.col("o_orderkey").alias("object_id"), F.col("o_orderstatus").alias("t_status"))
    outs = [simulated(wd, j)(F.col("object_id"), F.col("t_status") == "F", 0).alias(f"f{j}") for j, (_, wd, _) in enumerate(LADDER)]
    return o.select("object_id", (F.col("object_id") % 16).cast("int").alias("mask"), *outs)


FOUR = f"(SELECT object_id, CAST(object_id % 16 AS INTEGER) AS mask, {', '.join(raw_sql('object_id', chr(39).join(['t_status = ', 'F', '']), 0, j) + f' AS f{j}' for j in range(4))} FROM {ORDERS})"
QUALITY = [q for _, _, q in LADDER]


def _weighted_sql(flip: bool = False) -> str:
    f = (lambda j: f"(1 - f{j})") if flip else (lambda j: f"f{j}")
    top = " + ".join(f"CASE WHEN mask & {1 << j} > 0 THEN {QUALITY[j]} * {f(j)} ELSE 0 END" for j in range(4))
    low = " + ".join(f"CASE WHEN mask & {1 << j} > 0 THEN {QUALITY[j]} ELSE 0 END" for j in range(4))
    return f"CASE WHEN mask = 0 THEN 0.5 ELSE CAST({top} AS DOUBLE) / CAST(({low}) AS DOUBLE) END"


def _blended(spark, sf, **how):
    df = _four(spark, sf)
    return df.select("object_id", "mask", blend(F.col("mask"), [F.col(f"f{j}") for j in range(4)], QUALITY, **how).alias("p"))


@query("predicate_prob", f"SELECT object_id, mask, {_weighted_sql()} AS p FROM {FOUR}", "p")
def _(spark, sf):
    return _blended(spark, sf)


@query("predicate_prob_ne", f"SELECT object_id, mask, {_weighted_sql(True)} AS p FROM {FOUR}", "p")
def _(spark, sf):
    return _blended(spark, sf, op="!=")


_ON = [f"mask & {1 << j} > 0" for j in range(4)]
_N = "bit_count(mask)"
VARIANTS = {
    "literal": " + ".join(f"CASE WHEN {_ON[j]} THEN {QUALITY[j] / sum(QUALITY)!r} * f{j} ELSE 0 END" for j in range(4)),
    "mean": f"CASE WHEN mask = 0 THEN 0.5 ELSE ({' + '.join(f'CASE WHEN {_ON[j]} THEN f{j} ELSE 0 END' for j in range(4))}) / {_N} END",
    "max": f"CASE WHEN mask = 0 THEN 0.5 ELSE greatest({', '.join(f'CASE WHEN {_ON[j]} THEN f{j} ELSE 0 END' for j in range(4))}) END",
    "noisy_or": f"CASE WHEN mask = 0 THEN 0.5 ELSE 1 - {' * '.join(f'(CASE WHEN {_ON[j]} THEN 1 - f{j} ELSE 1 END)' for j in range(4))} END",
    "log_odds": "CASE WHEN mask = 0 THEN 0.5 ELSE 1 / (1 + exp(-(" + " + ".join(f"CASE WHEN {_ON[j]} THEN ln(least(greatest(f{j}, 1e-6), 1 - 1e-6) / (1 - least(greatest(f{j}, 1e-6), 1 - 1e-6))) ELSE 0 END" for j in range(4)) + f") / {_N})) END",
}


@query("blend_variants", f"SELECT object_id, mask, {', '.join(f'CAST({v} AS DOUBLE) AS {k}' for k, v in VARIANTS.items())} FROM {FOUR}", "literal mean max noisy_or log_odds")
def _(spark, sf):
    df, outs, m = _four(spark, sf), [F.col(f"f{j}") for j in range(4)], F.col("mask")
    cols = [blend(m, outs, [q / sum(QUALITY) for q in QUALITY], missing="literal").alias("literal")]
    return df.select("object_id", "mask", *cols, *[blend(m, outs, QUALITY, kind=k).alias(k) for k in ("mean", "max", "noisy_or", "log_odds")])


#: Predicate probabilities of orders by the seed alone, one column for each (type, tag).
ATOMS = {("Status", "F"): "sf", ("Status", "P"): "sp", ("Priority", "1-URGENT"): "pu", ("Priority", "5-LOW"): "pl", ("Segment", "BUILDING"): "gb"}


def _atoms(spark, sf):
    o, c = objects(spark, sf, "orders"), COLLECTIONS["orders"].catalog()
    cols = [c.of(t)[0].column(F.col("object_id"), F.col(c.type(t).truth) == tag, c.type(t).number(tag)).alias(n) for (t, tag), n in ATOMS.items()]
    return o.select("object_id", *cols)


def _atoms_sql() -> str:
    from .epoch_sql import BASES

    c = COLLECTIONS["orders"].catalog()
    cols = ", ".join(raw_sql("object_id", f"{c.type(t).truth} = '{tag}'", c.type(t).number(tag), 0) + f" AS {n}" for (t, tag), n in ATOMS.items())
    return f"(SELECT object_id, {cols} FROM ({BASES['orders']}))"


def _match(name: str, text: str, sql: str, method: str = "auto") -> None:
    @query(name, f"SELECT object_id, {sql} AS match_p FROM {_atoms_sql()}", "match_p")
    def _(spark, sf):
        e = parse_tag_expr(text)
        from ..functions.tagexpr import predicates

        probs = {p: F.col(ATOMS[p.type, p.tag]) if p.op == "=" else 1 - F.col(ATOMS[p.type, p.tag]) for p in predicates(e)}
        return _atoms(spark, sf).select("object_id", match_probability(e, probs, method).alias("match_p"))


_match("match_prob_single", "Status = 'F'", "sf")
_match("match_prob_and", "Status = 'F' AND Priority = '1-URGENT' AND Segment = 'BUILDING'", "sf * pu * gb")
_match("match_prob_or", "Status = 'F' OR Priority = '1-URGENT'", "sf + pu - sf * pu")
_match("match_prob_same_type_or", "Status IN ('F', 'P')", "least(1, sf + sp)")
_match("match_prob_same_type_and", "Status = 'F' AND Status = 'P'", "0 * sf")
_match("match_prob_nested", "(Status = 'F' AND Priority = '1-URGENT') OR (Status = 'P' AND NOT Segment = 'BUILDING')", "sf * pu * gb + sf * pu * (1 - gb) + sp * (1 - gb)")
_match("match_prob_intro", "(Status = 'F' OR Status = 'P') AND Priority != '5-LOW'", "(sf + sp) * (1 - pl)", "worlds")


@query("uncertainty", f"SELECT object_id, {h_sql('f0')} AS h0, {h_sql('f3')} AS h3 FROM {FOUR}", "h0 h3")
def _(spark, sf):
    return _four(spark, sf).select("object_id", entropy.entropy_bits(F.col("f0")).alias("h0"), entropy.entropy_bits(F.col("f3")).alias("h3"))


@query("entropy_multiclass", f"SELECT object_id, -(a * log2(a) + b * log2(b) + c * log2(c)) AS h FROM (SELECT object_id, (f0 + 0.01) / t AS a, (f1 + 0.01) / t AS b, (f2 + 0.01) / t AS c FROM (SELECT *, f0 + f1 + f2 + 0.03 AS t FROM {FOUR}))", "h")
def _(spark, sf):
    df = _four(spark, sf)
    t = sum((F.col(f"f{j}") + 0.01 for j in range(3)), F.lit(0.0))
    return df.select("object_id", entropy.entropy_of([(F.col(f"f{j}") + 0.01) / t for j in range(3)]).alias("h"))


def _roots_sql() -> str:
    """``object_id, h, root``: the uncertainty of the seed's output on each order, and its upper root by Newton steps."""
    clamp = lambda x: f"least(greatest({x}, 0.500000001), 1 - 1e-12)"
    x = f"SELECT object_id, h, {clamp('0.5 * (1 + sqrt(greatest(0.0, 1 - pow(h, 4.0::DOUBLE / 3))))')} AS x FROM (SELECT object_id, {h_sql('f0')} AS h FROM {FOUR})"
    for _ in range(4):
        x = f"SELECT object_id, h, {clamp(f'x - ({h_sql(chr(120))} - h) / log2((1 - x) / x)')} AS x FROM ({x})"
    return f"(SELECT object_id, h, CASE WHEN h >= 1 THEN 0.5 WHEN h <= 0 THEN 1.0 ELSE x END AS root FROM ({x}))"


def _uncertain(spark, sf) -> DataFrame:
    return _four(spark, sf).select("object_id", entropy.entropy_bits(F.col("f0")).alias("h"))


@query("inverse_entropy", f"SELECT object_id, h, root, {h_sql('root')} AS back FROM {_roots_sql()}", "h root back")
def _(spark, sf):
    df = _uncertain(spark, sf).withColumn("root", entropy.inverse_entropy(F.col("h")))
    return df.select("object_id", "h", "root", entropy.entropy_bits(F.col("root")).alias("back"))


@query("inverse_entropy_both", f"SELECT object_id, h, 1 - root AS low, root AS high FROM {_roots_sql()}", "h low high")
def _(spark, sf):
    return _uncertain(spark, sf).select("object_id", "h", entropy.inverse_entropy(F.col("h"), "both").alias("roots")).select("object_id", "h", "roots.low", "roots.high")


# --- state ----------------------------------------------------------------------------------------


@query("state_vector", upto(S3, 1, " UNION ALL ".join(f"SELECT object_id, {i} AS pred, m{i} AS mask, p{i} AS probability, {h_sql(f'p{i}')} AS uncertainty FROM st1" for i in range(2))), "probability uncertainty")
def _(spark, sf):
    run = w.run(spark, sf, replace(S3, epochs=1))
    *_, e = run.epochs(1)
    return state_vector(e.state, run.query)


@query("seed_state", upto(S3, 0, "SELECT object_id, m0 AS mask_0, p0 AS p_0, m1 AS mask_1, p1 AS p_1, P AS match_p FROM st0"), "p_0 p_1 match_p")
def _(spark, sf):
    _, _, _, st = seeded(spark, sf, S3)
    return st.select("object_id", F.col("m0").alias("mask_0"), F.col("p0").alias("p_0"), F.col("m1").alias("mask_1"), F.col("p1").alias("p_1"), "match_p")


@query("expected_quality", upto(S1, 0, "SELECT sum(P) FILTER (P > lam) / count(*) FILTER (P > lam) AS expected_precision, sum(P) FILTER (P > lam) / sum(P) AS expected_recall, 2 * sum(P) FILTER (P > lam) / (sum(P) + count(*) FILTER (P > lam)) AS expected_f FROM st0, lam0"), "expected_precision expected_recall expected_f")
def _(spark, sf):
    _, _, _, st = seeded(spark, sf)
    a = cutoff.choose_answer(st)
    return cutoff.expected_quality(st.withColumn("inside", F.col("match_p") > a.ratio), "inside")


ANSWER = "SELECT object_id, P AS match_p FROM st0, lam0 WHERE P > lam"


@query("answer_set", upto(S3, 0, ANSWER), "match_p")
def _(spark, sf):
    _, _, _, st = seeded(spark, sf, S3)
    return cutoff.choose_answer(st).members(st).select("object_id", "match_p")


for _method in ("sort", "rule", "ratio", "bins"):
    for _alpha in (1.0, 0.5) if _method in ("ratio", "bins") else (1.0,):

        def _answer(spark, sf, method=_method, alpha=_alpha):
            _, _, _, st = seeded(spark, sf)
            a = cutoff.choose_answer(st, alpha, method)
            return spark.createDataFrame([(float(a.ratio), int(a.size), float(a.expected_f))], "ratio double, size long, expected_f double")

        query(f"answer_by_{_method}" + ("" if _alpha == 1.0 else "_half"), upto(replace(S1, alpha=_alpha), 0, f"SELECT max(lam) AS ratio, count(*) FILTER (P > lam) AS size, {1 + _alpha} * max(lam) AS expected_f FROM st0, lam0"), "ratio expected_f")(_answer)

#: Match probabilities dealt over the customers by key: all of them, or the one of least key.
EDGE = [("zero", [0.0]), ("equal", [0.4]), ("one", [0.7]), ("five", [0.9, 0.8, 0.75, 0.3, 0.2]), ("rising", [1.0, 1.0, 0.9])]
EDGE_SQL = " UNION ALL ".join(
    f"SELECT '{n}' AS name, c_custkey AS object_id, CASE c_custkey % {len(ps)} {' '.join(f'WHEN {i} THEN {p}::DOUBLE' for i, p in enumerate(ps))} END AS p FROM customer" + (" WHERE c_custkey = (SELECT min(c_custkey) FROM customer)" if n == "one" else "")
    for n, ps in EDGE
)


@query(
    "answer_edge_cases",
    f"WITH v AS ({EDGE_SQL})," + """
    r AS (SELECT name, p, sum(p) OVER w AS s, row_number() OVER w AS k, sum(p) OVER (PARTITION BY name) AS tot FROM v WINDOW w AS (PARTITION BY name ORDER BY p DESC, object_id ROWS UNBOUNDED PRECEDING)),
    l AS (SELECT name, coalesce(max(CASE WHEN tot + k > 0 THEN s / (tot + k) END), 0) AS lam FROM r GROUP BY name)
    SELECT name, count(*) FILTER (p > lam) AS size, 2 * max(lam) AS expected_f FROM v JOIN l USING (name) GROUP BY name""",
    "expected_f",
)
def _(spark, sf):
    c, out = table(spark, sf, "customer", F.col("c_custkey").cast("long").alias("object_id")), []
    for name, ps in EDGE:
        who = c.where(F.col("object_id") == c.agg(F.min("object_id")).first()[0]) if name == "one" else c
        p = F.element_at(F.array(*[F.lit(x) for x in ps]), (F.col("object_id") % len(ps)).cast("int") + 1)
        st = who.select("object_id", p.alias("match_p"))
        found = {cutoff.choose_answer(st, 1.0, m).size for m in cutoff.METHODS}
        a = cutoff.choose_answer(st)
        out.append((name, a.size if len(found) == 1 else -1, float(a.expected_f)))
    return spark.createDataFrame(out, "name string, size long, expected_f double")


# --- planning -------------------------------------------------------------------------------------


def _planned(spark, sf, spec=S3, rule="outside"):
    _, q, t, st = seeded(spark, sf, spec)
    a = cutoff.choose_answer(st)
    return planning.make_items(planning.select_candidates(st, a, rule), q, t), st, a, q, t


for _rule in ("outside", "all"):

    def _candidates(spark, sf, rule=_rule):
        _, _, _, st = seeded(spark, sf, S3)
        return planning.select_candidates(st, cutoff.choose_answer(st), rule).select("object_id", "match_p")

    query(f"candidates_{_rule}", upto(S3, 0, "SELECT object_id, P AS match_p FROM st0, lam0" + (" WHERE P <= lam" if _rule == "outside" else "")), "match_p")(_candidates)


@query("candidates_gaining", upto(replace(S3, rule="gaining"), 0, "SELECT object_id, pred, scorer FROM i0a WHERE outside AND E > (SELECT lam FROM lam0) * (1 + (E - P))", items=True))
def _(spark, sf):
    items, _, a, _, _ = _planned(spark, sf)
    return planning.guard_gaining(items, a).select("object_id", "pred", "scorer")


@query("work_items", upto(S3, 0, "SELECT object_id, pred, scorer, cost FROM i0", items=True), "cost")
def _(spark, sf):
    return _planned(spark, sf)[0].select("object_id", "pred", "scorer", "cost")


@query("est_match_prob", upto(S3, 0, "SELECT object_id, pred, P AS match_p, E AS match_est FROM i0", items=True), "match_p match_est")
def _(spark, sf):
    return _planned(spark, sf)[0].select("object_id", "pred", "match_p", "match_est")


@query(
    "est_uncertainty",
    upto(S1, 0, f"SELECT t.object_id, h, least(1.0, greatest(0.0, h + coalesce(a.dh, b.dh, 0))) AS h_est FROM (SELECT *, {h_sql('p0')} AS h FROM st0, lam0 WHERE P <= lam) t LEFT JOIN cells a ON a.mask = m0 AND a.b = CAST(least(floor(h * 10), 9) AS INTEGER) LEFT JOIN cells b ON b.mask = m0 AND b.b = -1"),
    "h h_est",
)
def _(spark, sf):
    return _planned(spark, sf, S1)[0].select("object_id", "h", "h_est")


for _name, _benefit in (("benefit_relative", "relative"), ("benefit_exact", "exact"), ("benefit_exact_weighted", "weighted")):

    def _benefits(spark, sf, benefit=_benefit):
        items, st, a, _, _ = _planned(spark, sf, S1)
        out = planning.benefit_relative(items) if benefit == "relative" else planning.benefit_exact(items, st, a, benefit == "weighted")
        return out.select("object_id", "pred", "scorer", "rank_key")

    query(_name, upto(replace(S1, benefit=_benefit), 0, "SELECT object_id, pred, scorer, key AS rank_key FROM i0", items=True))(_benefits)


@query("benefit_prefix", upto(replace(S1, benefit="exact"), 0, "SELECT object_id, pred, scorer, key / 1e9 AS benefit FROM i0", items=True), "benefit")
def _(spark, sf):
    items, st, a, _, _ = _planned(spark, sf, S1)
    return planning.benefit_prefix(items, st, a, 8192).select("object_id", "pred", "scorer", (F.col("rank_key") / 1e9).alias("benefit"))


@query(
    "benefit_agreement",
    f"SELECT avg(CASE WHEN sign(round(x.a - y.a, 9)) = sign(round(x.b - y.b, 9)) THEN 1.0 ELSE 0.0 END) AS agreement, count(*) AS pairs FROM ({{0}}) x, ({{0}}) y WHERE x.object_id < y.object_id".replace(
        "{0}", f"SELECT r.object_id, r.key / 1e9 AS a, e.key / 1e9 AS b FROM ({upto(S1, 0, 'SELECT object_id, key FROM i0', items=True)}) r JOIN ({upto(replace(S1, benefit='exact'), 0, 'SELECT object_id, key FROM i0', items=True)}) e USING (object_id)"
    ),
    "agreement",
)
def _(spark, sf):
    items, st, a, _, _ = _planned(spark, sf, S1)
    rel = planning.benefit_relative(items).select("object_id", "pred", (F.col("rank_key") / 1e9).alias("a"))
    exact = planning.benefit_exact(items, st, a).select("object_id", "pred", (F.col("rank_key") / 1e9).alias("b"))
    return metrics.rank_agreement(rel.join(exact, ["object_id", "pred"]), "a", "b")


PLAN = "SELECT object_id, pred, scorer, cost FROM (SELECT *, sum(cost) OVER (ORDER BY key DESC, object_id, pred, scorer ROWS UNBOUNDED PRECEDING) AS run FROM i0) WHERE run - cost < 2000"


@query("plan_topk", upto(S3, 0, PLAN, items=True), "cost")
def _(spark, sf):
    return planning.select_by_sort(planning.benefit_relative(_planned(spark, sf)[0]), 2000).select("object_id", "pred", "scorer", "cost")


@query("plan_by_bins", upto(S3, 0, PLAN, items=True), "cost")
def _(spark, sf):
    return planning.select_plan(planning.benefit_relative(_planned(spark, sf)[0]), 2000).select("object_id", "pred", "scorer", "cost")


@query("plan_limit_k", upto(S3, 0, "SELECT object_id, pred, scorer, cost FROM i0 ORDER BY key DESC, object_id, pred, scorer LIMIT 50", items=True), "cost")
def _(spark, sf):
    return planning.select_limit(planning.benefit_relative(_planned(spark, sf)[0]), 50).select("object_id", "pred", "scorer", "cost")


@query("execute_plan", upto(S3, 1, "SELECT r.object_id, r.pred, r.scorer, o.prob, r.cost FROM plan0 r JOIN outs o ON o.object_id = r.object_id AND o.pred = r.pred AND o.scorer = r.scorer"), "prob cost")
def _(spark, sf):
    run = w.run(spark, sf, replace(S3, epochs=1))
    *_, e = run.epochs(1)
    return e.outputs


@query("state_update", upto(S3, 1, "SELECT object_id, m0 AS mask_0, p0 AS p_0, m1 AS mask_1, p1 AS p_1, P AS match_p FROM st1"), "p_0 p_1 match_p")
def _(spark, sf):
    run = w.run(spark, sf, replace(S3, epochs=1))
    *_, e = run.epochs(1)
    again = apply_outputs(run.state, e.outputs, run.query)
    return again.select("object_id", F.col("m0").alias("mask_0"), F.col("p0").alias("p_0"), F.col("m1").alias("mask_1"), F.col("p1").alias("p_1"), "match_p")


@query("queue_refresh", upto(S3, 1, "SELECT object_id, pred, scorer, key AS rank_key FROM i1a WHERE outside", items=True))
def _(spark, sf):
    run = w.run(spark, sf, replace(S3, epochs=1))
    first, e = run.epochs(1)
    before = run.items(first.state, first.answer, 1)
    # objects that left the answer because lambda rose have new items too
    fresh = e.outputs.select("object_id").union(first.answer.members(e.state).select("object_id")).distinct()
    again = run.items(e.state.join(fresh, "object_id", "left_semi"), e.answer, 2)
    return planning.refresh_items(before, fresh, again, e.answer).select("object_id", "pred", "scorer", "rank_key")


# --- learning -------------------------------------------------------------------------------------

for _pick in ("avg", "vote", "per_cost"):

    def _next(spark, sf, pick=_pick):
        _, q, _ = w.prepared(spark, sf, S3)
        rows = learning.reductions(objects(spark, sf, "orders").where(split_part() < 2), q)
        types = {p.type: i for i, p in enumerate(q.preds)}
        t = learning.next_scorer_table(rows, pick)
        pred = F.when(F.col("tag_type") == q.preds[0].type, 0).otherwise(types[q.preds[1].type])
        return t.select(pred.alias("pred"), "mask", "bin", "scorer", "delta_h", "n")

    query({"avg": "next_scorer_table", "vote": "next_scorer_vote", "per_cost": "next_scorer_per_cost"}[_pick], upto(replace(S3, pick=_pick), 0, "SELECT pred, mask, b AS bin, scorer, dh AS delta_h, n FROM cells WHERE b >= 0"), "delta_h")(_next)


@query("uncertainty_bins", upto(S3, 0, f"SELECT CAST(least(floor({h_sql('p0')} * 10), 9) AS INTEGER) AS bin, count(*) AS n FROM st0 GROUP BY 1"))
def _(spark, sf):
    _, _, _, st = seeded(spark, sf, S3)
    return st.groupBy(planning.uncertainty_bin(entropy.entropy_bits(F.col("p0")), 10).alias("bin")).agg(F.count("*").alias("n"))


def _log(spark, sf):
    q = Query(parse_tag_expr("Status = 'F' AND Priority = '1-URGENT'"), COLLECTIONS["orders"].catalog())
    return learning.validation_log(objects(spark, sf, "orders").where(split_part() < 2), q)


LOG_SPEC = replace(S1, expr="Status = 'F' AND Priority = '1-URGENT'")
LOG = f"(SELECT CASE pred WHEN 0 THEN 'Status' ELSE 'Priority' END AS tag_type, CASE pred WHEN 0 THEN 'F' ELSE '1-URGENT' END AS tag, CAST(scorer AS INTEGER) AS scorer, raw AS prob, truth, object_id FROM (WITH {', '.join(SpecSql(LOG_SPEC).base()[:3])} SELECT * FROM raws WHERE part < 2))"


AUC = f"SELECT tag_type, tag, scorer, (sum(r) FILTER (truth) - count(*) FILTER (truth) * (count(*) FILTER (truth) + 1) / 2.0) / (count(*) FILTER (truth) * count(*) FILTER (NOT truth)) AS auc FROM (SELECT *, rank() OVER (PARTITION BY tag_type, scorer ORDER BY prob) + (count(*) OVER (PARTITION BY tag_type, scorer, prob) - 1) / 2.0 AS r FROM {LOG}) GROUP BY ALL"


@query("scorer_auc", AUC, "auc")
def _(spark, sf):
    return learning.learn_quality(_log(spark, sf))


@query("blend_weights", f"SELECT tag_type, scorer, auc / sum(auc) OVER (PARTITION BY tag_type) AS weight FROM ({AUC})", "weight")
def _(spark, sf):
    """Shares of the quality learned from the validation orders, within the type."""
    from pyspark.sql import Window as W

    return learning.learn_quality(_log(spark, sf)).select("tag_type", "scorer", (F.col("auc") / F.sum("auc").over(W.partitionBy("tag_type"))).alias("weight"))


@query("roc_curve", f"SELECT tag_type, tag, scorer, prob AS threshold, sum(neg) OVER w / sum(neg) OVER (PARTITION BY tag_type, scorer) AS fpr, sum(pos) OVER w / sum(pos) OVER (PARTITION BY tag_type, scorer) AS tpr FROM (SELECT tag_type, tag, scorer, prob, count(*) FILTER (truth) AS pos, count(*) FILTER (NOT truth) AS neg FROM {LOG} GROUP BY ALL) WINDOW w AS (PARTITION BY tag_type, scorer ORDER BY prob DESC ROWS UNBOUNDED PRECEDING)", "threshold fpr tpr")
def _(spark, sf):
    return learning.roc_curve(_log(spark, sf))


_COSTS = " ".join(f"WHEN {j} THEN {c}" for j, (c, _, _) in enumerate(LADDER))


@query("scorer_cost", f"SELECT tag_type, scorer, CAST(avg(CASE scorer {_COSTS} END) AS DOUBLE) AS mean_cost, count(*) AS n FROM {LOG} GROUP BY ALL", "mean_cost")
def _(spark, sf):
    return learning.learn_cost(_log(spark, sf))


@query("seed_choice", f"SELECT tag_type, arg_max(scorer, q / c) AS seed FROM (VALUES {', '.join(f'({chr(39)}{t}{chr(39)}, {j}, {q}, {c})' for t in ('Status', 'Priority', 'Segment') for j, (c, _, q) in enumerate(LADDER))}) v(tag_type, scorer, q, c) GROUP BY tag_type")
def _(spark, sf):
    return learning.pick_seeds(COLLECTIONS["orders"].catalog().to_df(spark))


@query("online_cost", f"SELECT 'Status' AS tag_type, CAST(j AS INTEGER) AS scorer, CAST(CASE j {_COSTS} END AS DOUBLE) AS mean_cost, (SELECT count(*) FROM orders WHERE (o_orderkey // 11) % 100 < 5) AS n FROM range(4) t(j)", "mean_cost")
def _(spark, sf):
    q = Query(parse_tag_expr("Status = 'F'"), COLLECTIONS["orders"].catalog())
    return learning.learn_cost(learning.validation_log(learning.online_sample(objects(spark, sf, "orders"), 5), q))


@query("online_table")
def _(spark, sf):
    _, q, _ = w.prepared(spark, sf, S1)
    return learning.next_scorer_table(learning.reductions(learning.online_sample(objects(spark, sf, "orders"), 20), q))


@query("calib_bins", f"SELECT tag_type, tag, scorer, CAST(least(floor(prob * 20), 19) AS INTEGER) AS bin, count(*) AS n, avg(prob) AS mean_prob, avg(CASE WHEN truth THEN 1.0 ELSE 0.0 END) AS rate FROM {LOG} GROUP BY ALL", "mean_prob rate")
def _(spark, sf):
    return learning.reliability(_log(spark, sf))


@query("calib_error", f"SELECT tag_type, tag, scorer, brier, gap FROM (SELECT tag_type, tag, scorer, avg((prob - CASE WHEN truth THEN 1.0 ELSE 0.0 END) ** 2) AS brier FROM {LOG} GROUP BY ALL) JOIN (SELECT tag_type, tag, scorer, sum(n * abs(m - r)) / sum(n) AS gap FROM (SELECT tag_type, tag, scorer, least(floor(prob * 20), 19) AS b, count(*) AS n, avg(prob) AS m, avg(CASE WHEN truth THEN 1.0 ELSE 0.0 END) AS r FROM {LOG} GROUP BY ALL) GROUP BY ALL) USING (tag_type, tag, scorer)", "brier gap")
def _(spark, sf):
    return learning.calibration_error(_log(spark, sf))


@query("calib_fits")
def _(spark, sf):
    log = _log(spark, sf).where("scorer = 1 AND tag_type = 'Status'")
    iso, platt = learning.fit_calibration(log), learning.fit_calibration(log, "platt")
    rows = [("isotonic", float(b), float(p)) for b, p in zip(iso.boundaries.toArray(), iso.predictions.toArray())]
    rows.append(("platt", float(platt.coefficients[0]), float(platt.intercept)))
    return spark.createDataFrame(rows, "method string, x double, y double")


@query("split_counts", "SELECT CASE WHEN part < 2 THEN 'validation' ELSE 'query' END AS split, count(*) AS n FROM (SELECT (o_orderkey * 7919) % 10 AS part FROM orders) GROUP BY 1")
def _(spark, sf):
    o = table(spark, sf, "orders", F.col("o_orderkey").alias("object_id"))
    return o.groupBy(F.when(split_part() < 2, "validation").otherwise("query").alias("split")).agg(F.count("*").alias("n"))


# --- caching, blocks, joins -----------------------------------------------------------------------

for _percent in (10, 25, 50, 75):
    _spec = replace(S1, cached=_percent, epochs=2)

    def _cached(spark, sf, spec=_spec):
        return w.curves(spark, sf, [("cached", spec)])

    query(f"cache_{_percent}", curves_sql([("cached", _spec)]), CURVE)(_cached)

NB = 20
BLOCKS = f"(SELECT object_id, CAST(ntile({NB}) OVER (ORDER BY floor(P * 1e9) DESC, object_id) - 1 AS INTEGER) AS block_id FROM st0)"


def _blocks(spark, sf):
    items, st, a, q, t = _planned(spark, sf, S3)
    return blocks.make_blocks(st, NB), planning.benefit_relative(items)


@query("block_assign", upto(S3, 0, f"SELECT * FROM {BLOCKS}"))
def _(spark, sf):
    return _blocks(spark, sf)[0]


@query("block_assign_ranges")
def _(spark, sf):
    _, _, _, st = seeded(spark, sf, S3)
    return blocks.make_blocks(st, NB, exact=False).groupBy("block_id").agg(F.count("*").alias("n"))


BENEFIT = f"(SELECT block_id, coalesce(sum(v), 0) AS benefit, count(v) AS items FROM {BLOCKS} b LEFT JOIN (SELECT object_id, P * E / cost AS v FROM i0r, lam0 WHERE P <= lam) i USING (object_id) GROUP BY block_id)"


@query("block_benefit", upto(S3, 0, f"SELECT * FROM {BENEFIT}", items=True), "benefit")
def _(spark, sf):
    b, items = _blocks(spark, sf)
    return blocks.block_benefit(items, b)


@query("block_benefit_incr", upto(S3, 1, f"SELECT block_id, coalesce(sum(v), 0) AS benefit, count(v) AS items FROM {BLOCKS} b LEFT JOIN (SELECT object_id, P * E / cost AS v FROM i1r, lam1 WHERE P <= lam) i USING (object_id) GROUP BY block_id", items=True), "benefit")
def _(spark, sf):
    run = w.run(spark, sf, replace(S3, epochs=1))
    first, e = run.epochs(1)
    b = blocks.make_blocks(run.state, NB)
    before = blocks.block_benefit(run.items(first.state, first.answer, 1), b)
    items = run.items(e.state, e.answer, 2)
    # lambda may move objects in or out of the candidates: their blocks count as touched as well
    low, high = sorted((first.answer.ratio, e.answer.ratio))
    moved = e.state.where(F.col("match_p").between(low, high)).select("object_id")
    return blocks.refresh_block_benefit(before, e.outputs.select("object_id").union(moved), items, b)


RESIDENT = [3, 7, 11]


@query("block_queues", upto(S3, 0, f"SELECT queue, row_number() OVER (PARTITION BY queue ORDER BY CASE WHEN queue = 'memory' THEN floor(benefit * 1e9) ELSE -floor(benefit * 1e9) END, block_id) AS place, block_id, benefit FROM (SELECT *, CASE WHEN block_id IN (3, 7, 11) THEN 'memory' ELSE 'disk' END AS queue FROM {BENEFIT})", items=True), "benefit")
def _(spark, sf):
    b, items = _blocks(spark, sf)
    return blocks.block_queues(blocks.block_benefit(items, b), RESIDENT)


_Q = f"(SELECT queue, block_id, row_number() OVER (PARTITION BY queue ORDER BY CASE WHEN queue = 'memory' THEN floor(benefit * 1e9) ELSE -floor(benefit * 1e9) END, block_id) AS place FROM (SELECT *, CASE WHEN block_id IN (3, 7, 11) THEN 'memory' ELSE 'disk' END AS queue FROM {BENEFIT}))"


@query(
    "block_plan_alternatives",
    upto(S3, 0, f"""SELECT CAST(d AS INTEGER) AS d, sum(v) AS total, count(*) AS items FROM (
      SELECT d, v, cost, sum(cost) OVER (PARTITION BY d ORDER BY key DESC, object_id, pred, scorer ROWS UNBOUNDED PRECEDING) AS run
      FROM (SELECT i.object_id, i.pred, i.scorer, i.cost, floor(i.P * i.E / i.cost * 1e9) AS key, i.P * i.E / i.cost AS v, block_id FROM i0r i JOIN {BLOCKS} USING (object_id), lam0 WHERE i.P <= lam) x
      JOIN (SELECT d, block_id FROM range(4) t(d), {_Q} q WHERE (queue = 'memory' AND place > d) OR (queue = 'disk' AND place <= d)) r USING (block_id))
      WHERE run - cost < 3000 - d * 300 GROUP BY d""", items=True),
    "total",
)
def _(spark, sf):
    b, items = _blocks(spark, sf)
    queues = blocks.block_queues(blocks.block_benefit(items, b), RESIDENT)
    return blocks.plan_alternatives(items, b, queues, blocks.BlockSettings(NB, 3, 300.0), 3000.0)


@query(
    "tag_join_prob",
    f"""WITH d AS (SELECT object_id, o_custkey, tag, p / sum(p) OVER (PARTITION BY object_id) AS p FROM (
      SELECT o_orderkey AS object_id, o_custkey, tag, {raw_sql('o_orderkey', 'o_orderpriority = tag', 0, 3).replace('(7919 * o_orderkey + 314187', '(7919 * o_orderkey + 31337 * no + 314187').replace('613 *', '613 *')} AS p
      FROM orders, (VALUES ('1-URGENT', 0), ('2-HIGH', 1), ('3-MEDIUM', 2), ('4-NOT SPECIFIED', 3), ('5-LOW', 4)) v(tag, no)))
    SELECT a.object_id AS left_id, b.object_id AS right_id, sum(a.p * b.p) AS p FROM d a JOIN d b ON a.tag = b.tag AND a.o_custkey = b.o_custkey AND a.object_id % 2 = 0 AND b.object_id % 2 = 1 GROUP BY ALL HAVING sum(a.p * b.p) > 0.3""",
    "p",
)
def _(spark, sf):
    o = table(spark, sf, "orders", F.col("o_orderkey").alias("object_id"), "o_custkey", "o_orderpriority")
    tags = COLLECTIONS["orders"].types[1].domain
    mixed = lambda no: F.pmod(7919 * F.col("object_id") + 31337 * no + 104729 * 3 + 613 * 40 * F.floor(F.col("object_id") / 97), F.lit(10007)) / F.lit(10007.0)
    cells = F.array(*[F.struct(F.lit(t).alias("tag"), F.when(F.col("o_orderpriority") == t, 1 - 0.6 * mixed(i)).otherwise(0.6 * mixed(i)).alias("p")) for i, t in enumerate(tags)])
    probs = joins.tag_distribution(o.select("object_id", F.inline(cells))).join(o.select("object_id", "o_custkey"), "object_id")
    return joins.tag_join(probs.where("object_id % 2 = 0"), probs.where("object_id % 2 = 1"), ["o_custkey"], cutoff=0.3)


@query("tag_join_epochs")
def _(spark, sf):
    """Orders with even and odd keys of one customer that have the same priority: three epochs of the join form."""
    o = objects(spark, sf, "orders").select("object_id", "o_custkey", "t_priority")
    sides = [o.where(F.pmod("object_id", F.lit(2)) == i) for i in (0, 1)]
    made = pair_join.enrich_join(*sides, ["o_custkey"], "Priority", 0.03 * w.FULL_COST * 5 * o.count(), COLLECTIONS["orders"].catalog(), least=0.05)
    rows = [(e.number, float(e.spent), e.items, e.answer.size, float(e.answer.expected_f), float(e.f1)) for e in made.epochs(3)]
    return spark.createDataFrame(rows, "epoch int, spent double, items long, answer_size long, expected_f double, f1 double")


# --- baselines and measures -----------------------------------------------------------------------

for _approach in ("scorer_first", "object_first", "random"):

    def _baseline(spark, sf, approach=_approach):
        return w.curves(spark, sf, [(approach, S1.as_(approach))])

    query(f"baseline_{_approach}", curves_sql([(_approach, S1.as_(_approach))]), CURVE)(_baseline)

ALL = [("outside", S1), ("all", replace(S1, rule="all")), ("gaining", replace(S1, rule="gaining"))]
BEN = [("relative", S1), ("exact", replace(S1, benefit="exact")), ("weighted", replace(S1, benefit="weighted"))]


@query("ablate_candidates", curves_sql(ALL), CURVE)
def _(spark, sf):
    return w.curves(spark, sf, ALL)


@query("ablate_benefit", curves_sql(BEN), CURVE)
def _(spark, sf):
    return w.curves(spark, sf, BEN)


@query("full_enrichment", upto(S3, 0, f"SELECT object_id, {' * '.join(f'(sum(CASE WHEN pred = {i} THEN q * prob END) / {sum(QUALITY)!r})' for i in range(2))} AS match_p FROM (SELECT o.*, CASE scorer {' '.join(f'WHEN {j} THEN {q}' for j, q in enumerate(QUALITY))} END AS q FROM outs o JOIN chosen USING (object_id)) GROUP BY object_id"), "match_p")
def _(spark, sf):
    chosen, q, _ = w.prepared(spark, sf, S3)
    return full_enrichment(chosen, q).select("object_id", "match_p")


@query("seed_answer", curves_sql([("seed", replace(S1, epochs=0))]), CURVE)
def _(spark, sf):
    return w.curves(spark, sf, [("seed", replace(S1, epochs=0))])


for _n, _a in (("quality_precision", 1.0), ("quality_recall", 1.0), ("quality_f_alpha", 0.5)):
    _c = {"quality_precision": "precision", "quality_recall": "recall", "quality_f_alpha": "f_measure"}[_n]
    _v = {"precision": "count(*) FILTER (P > lam AND rel) / count(*) FILTER (P > lam)", "recall": "count(*) FILTER (P > lam AND rel) / count(*) FILTER (rel)", "f_measure": "1.5 * count(*) FILTER (P > lam AND rel) / (0.5 * count(*) FILTER (rel) + count(*) FILTER (P > lam))"}[_c]

    def _quality(spark, sf, column=_c, alpha=_a):
        chosen, q, _, st = seeded(spark, sf, replace(S3, alpha=alpha))
        from ..functions.tagexpr import holds_column

        truth = chosen.where(holds_column(q.expr, {t.name: t.truth for t in q.catalog.types}))
        return metrics.true_quality(cutoff.choose_answer(st, alpha).members(st), truth, alpha).select(column)

    query(_n, upto(replace(S3, alpha=_a), 0, f"SELECT {_v} AS {_c} FROM st0 JOIN truth USING (object_id), lam0"), _c)(_quality)

FOURS = w.all_approaches(S1)
FOURS_SQL = curves_sql(FOURS)
GAIN_SQL = f"SELECT *, CASE WHEN top > first THEN (f1 - first) / (top - first) ELSE 0 END AS gain FROM (SELECT *, max(f1) OVER (PARTITION BY approach) AS top, first_value(f1) OVER (PARTITION BY approach ORDER BY epoch) AS first FROM ({FOURS_SQL}))"


@query("gain_curve", f"SELECT approach, epoch, spent, f1, gain FROM ({GAIN_SQL})", "spent f1 gain")
def _(spark, sf):
    return metrics.gain_curve(w.curves(spark, sf, FOURS)).select("approach", "epoch", "spent", "f1", "gain")


POINTS_SQL = f"SELECT CAST(i AS INTEGER) AS i, horizon * i / 10 AS v, horizon FROM (SELECT min(e) AS horizon FROM (SELECT max(spent) AS e FROM ({FOURS_SQL}) GROUP BY approach)), range(1, 11) t(i)"


@query("sample_points", POINTS_SQL, "v horizon")
def _(spark, sf):
    return metrics.sample_points(w.curves(spark, sf, FOURS))


@query("progress_weights", f"SELECT i, greatest(0, 1 - (v - 1) / horizon) AS printed, greatest(0, 1 - (i - 1) / 10.0) AS previous FROM ({POINTS_SQL})", "printed previous")
def _(spark, sf):
    p = metrics.sample_points(w.curves(spark, sf, FOURS))
    i, v, h = F.col("i"), F.col("v"), F.col("horizon")
    return p.select("i", metrics.weight(i, v, h, weighting="printed").alias("printed"), metrics.weight(i, v, h).alias("previous"))


def progress_sql(curve: str, value: str = "gain") -> str:
    """Progressiveness of curves with approach, epoch, spent, f1 under both weightings."""
    return f"""WITH c AS ({curve}), g AS (SELECT *, CASE WHEN top > low THEN (f1 - low) / (top - low) ELSE 0 END AS gain FROM (SELECT *, max(f1) OVER (PARTITION BY approach) AS top, first_value(f1) OVER (PARTITION BY approach ORDER BY epoch) AS low FROM c)),
    z AS (SELECT min(e) AS horizon FROM (SELECT max(spent) AS e FROM c GROUP BY approach)),
    a AS (SELECT approach, i, horizon * i / 10 AS v, horizon, (SELECT arg_max({value}, epoch) FROM g WHERE g.approach = n.approach AND g.spent <= horizon * i / 10 + 1e-9) AS y FROM (SELECT DISTINCT approach FROM c) n, z, range(0, 11) t(i)),
    s AS (SELECT *, y - lag(y) OVER (PARTITION BY approach ORDER BY i) AS dy FROM a)
    SELECT approach, sum(greatest(0, 1 - (i - 1) / 10.0) * dy) AS previous, sum(greatest(0, 1 - (v - 1) / horizon) * dy) AS printed FROM s WHERE i > 0 GROUP BY approach"""


def progress(curve: DataFrame, value: str = "gain") -> DataFrame:
    c = metrics.gain_curve(curve)
    a = metrics.progressiveness(c, value).withColumnRenamed("progressiveness", "previous")
    return a.join(metrics.progressiveness(c, value, weighting="printed").withColumnRenamed("progressiveness", "printed"), "approach")


@query("progressiveness", progress_sql(FOURS_SQL), "previous printed")
def _(spark, sf):
    return progress(w.curves(spark, sf, FOURS))


@query("completion_cost", f"SELECT approach, max(spent) AS spent FROM ({FOURS_SQL}) GROUP BY approach", "spent")
def _(spark, sf):
    return w.curves(spark, sf, FOURS).groupBy("approach").agg(F.max("spent").alias("spent"))


# The measures above follow three epochs of 3 % of all cost, short enough for SQL. These run until nothing is left.
WHOLE_FOURS = w.all_approaches(w.whole(S1))


@query("gain_curve_whole")
def _(spark, sf):
    return metrics.gain_curve(w.curves(spark, sf, WHOLE_FOURS)).select("approach", "epoch", "spent", "f1", "gain")


@query("progressiveness_whole")
def _(spark, sf):
    return progress(w.curves(spark, sf, WHOLE_FOURS))


@query("completion_cost_whole")
def _(spark, sf):
    return w.curves(spark, sf, WHOLE_FOURS).groupBy("approach").agg(F.max("spent").alias("spent"))


@query("epoch_improvement", f"SELECT approach, epoch, f1 - coalesce(lag(f1) OVER (PARTITION BY approach ORDER BY epoch), f1) AS improvement FROM ({FOURS_SQL})", "improvement")
def _(spark, sf):
    return metrics.epoch_improvement(w.curves(spark, sf, FOURS)).select("approach", "epoch", "improvement")


@query("work_stats", upto(S3, 2, "SELECT epoch, pred, scorer, count(*) AS items, sum(cost) AS cost FROM (SELECT 1 AS epoch, pred, scorer, cost FROM plan0 UNION ALL SELECT 2, pred, scorer, cost FROM plan1) GROUP BY ROLLUP (epoch, pred, scorer)"), "cost")
def _(spark, sf):
    log = None
    for e in w.run(spark, sf, replace(S3, epochs=2)).epochs(2):
        if e.outputs is not None:
            part = e.outputs.withColumn("epoch", F.lit(e.number))
            log = part if log is None else log.unionByName(part)
    return metrics.work_stats(log)


RUNS = [(f"r{k}", replace(S1, approach="random", seed=k, epochs=2)) for k in (1, 2, 3)]


@query("repeat_summary", f"SELECT 'random' AS approach, avg(f1) AS mean, stddev_samp(f1) AS deviation, count(*) AS runs FROM ({curves_sql(RUNS)}) WHERE epoch = 2", "mean deviation")
def _(spark, sf):
    return metrics.repeat_summary(w.curves(spark, sf, RUNS).where("epoch = 2").withColumn("approach", F.lit("random")), "f1")


@query("selectivity", f"SELECT avg(CASE WHEN {w.ORDERS_100} THEN 1.0 ELSE 0.0 END) AS selectivity FROM orders", "selectivity")
def _(spark, sf):
    return metrics.selectivity(table(spark, sf, "orders", "o_orderdate"), w.ORDERS_100)


@query("monotone_report", f"SELECT approach, count(*) FILTER (d < -1e-9) AS falls, count(*) AS epochs FROM (SELECT approach, expected_f - coalesce(lag(expected_f) OVER (PARTITION BY approach ORDER BY epoch), expected_f) AS d FROM ({FOURS_SQL})) GROUP BY approach")
def _(spark, sf):
    return metrics.monotone_report(w.curves(spark, sf, FOURS))


# --- experiments ----------------------------------------------------------------------------------


def _experiment(name: str, specs, value: str = "gain") -> None:
    if value == "curve":
        query(name, curves_sql(specs), CURVE)(lambda spark, sf: w.curves(spark, sf, specs))
    elif value == "gain":
        sql = curves_sql(specs)
        query(name, f"SELECT approach, epoch, spent, CASE WHEN top > low THEN (f1 - low) / (top - low) ELSE 0 END AS gain FROM (SELECT *, max(f1) OVER (PARTITION BY approach) AS top, first_value(f1) OVER (PARTITION BY approach ORDER BY epoch) AS low FROM ({sql}))", "spent gain")(
            lambda spark, sf: metrics.gain_curve(w.curves(spark, sf, specs)).select("approach", "epoch", "spent", "gain")
        )


_experiment("exp1_gain_q1_small_075", w.all_approaches(w.SMALL_075))
_experiment("exp1_gain_q1_small_100", w.all_approaches(w.SMALL_100))
_experiment("exp1_f1_q1_small_075", w.all_approaches(w.SMALL_075), "curve")
_experiment("exp1_f1_q1_small_100", w.all_approaches(w.SMALL_100), "curve")
_experiment("exp1_gain_q1_large_1", w.all_approaches(w.LARGE_10))
_experiment("exp1_gain_q1_large_2", w.all_approaches(w.LARGE_20))
_experiment("exp1_gain_q2_10", w.all_approaches(w.TWEETS_10))
_experiment("exp1_gain_q2_20", w.all_approaches(w.TWEETS_20))
_experiment("exp1_gain_docs", w.all_approaches(w.DOCS))

EXP1 = {"q1_small_075": w.SMALL_075, "q1_small_100": w.SMALL_100, "q1_large_1": w.LARGE_10, "q1_large_2": w.LARGE_20, "q2_10": w.TWEETS_10, "q2_20": w.TWEETS_20, "docs": w.DOCS}
for _n, _s in EXP1.items():

    def _whole_gain(spark, sf, specs=w.all_approaches(w.whole(_s))):
        return metrics.gain_curve(w.curves(spark, sf, specs)).select("approach", "epoch", "spent", "f1", "gain")

    query(f"exp1_gain_{_n}_whole")(_whole_gain)


def _scores(spark, sf, specs):
    w.run_all(spark, sf, [x for s in specs.values() for _, x in w.all_approaches(s)])
    out = None
    for n, s in specs.items():
        part = progress(w.curves(spark, sf, w.all_approaches(s))).select(F.lit(n).alias("workload"), "approach", "previous", "printed")
        out = part if out is None else out.unionByName(part)
    return out


SCORED = {"small_075": w.SMALL_075, "small_100": w.SMALL_100, "large": w.LARGE_10, "tweets": w.TWEETS_10}


@query("exp1_scores", " UNION ALL ".join(f"SELECT '{n}' AS workload, * FROM ({progress_sql(curves_sql(w.all_approaches(s)))})" for n, s in SCORED.items()), "previous printed")
def _(spark, sf):
    return _scores(spark, sf, SCORED)


@query("exp1_scores_whole")
def _(spark, sf):
    return _scores(spark, sf, {n: w.whole(s) for n, s in SCORED.items()})


TUNED = w.SELECTIVITIES["orders"]


@query("epoch_tuning")
def _(spark, sf):
    """Least completion over ten epoch sizes, then epochs of ten shares of it; planning is paid for, so rows only."""
    return w.tuned(spark, sf, w.SMALL_075)


@query("exp2_epoch_size")
def _(spark, sf):
    """The epoch size at each selectivity: total cost, epochs until nothing is left, and scores."""
    out = None
    for name, where in TUNED.items():
        part = w.tuned(spark, sf, replace(w.SMALL_075, where=where), shares=(*w.EPOCH_SHARES, 0.2)).select(F.lit(name).alias("selectivity"), "*")
        out = part if out is None else out.unionByName(part)
    return out


KINDS = {"orders": S1, "lineitem": w.LARGE_10, "events": w.TWEETS_10}
PLANNED = {f"{c}_{n}": replace(KINDS[c], where=where, epochs=0) for c, many in w.SELECTIVITIES.items() for n, where in many.items()}


@query("exp3_plan_counts", " UNION ALL ".join(f"SELECT '{n}' AS selectivity, * FROM ({upto(s, 0, 'SELECT (SELECT count(*) FROM st0) AS objects, (SELECT count(*) FROM st0, lam0 WHERE P <= lam) AS candidates, (SELECT count(*) FROM i0a WHERE outside) AS items', items=True)})" for n, s in PLANNED.items()))
def _(spark, sf):
    rows = []
    for n, s in PLANNED.items():
        _, q, t, st = seeded(spark, sf, s)
        st = st.cache()
        a = cutoff.choose_answer(st)
        c = planning.select_candidates(st, a)
        rows.append((n, st.count(), c.count(), planning.make_items(c, q, t).count()))
        st.unpersist()
    return spark.createDataFrame(rows, "selectivity string, objects long, candidates long, items long")


STEPS = ("candidates", "items", "benefit", "choose", "plan", "execute", "answer")


@query("exp3_plan_times")
def _(spark, sf):
    """Seconds of each step of planning, of execution and of the answer, at twelve selectivities: wall clock, so rows only."""
    rows = [(n, e.number, *[float(e.times.get(k, 0)) for k in STEPS]) for n, s in PLANNED.items() for e in w.run(spark, sf, replace(s, steps=True)).epochs(1) if e.number]
    return spark.createDataFrame(rows, "selectivity string, epoch int, " + ", ".join(f"{k} double" for k in STEPS))


EXP4 = [(f"{r}_{n}", replace(S1, where=TUNED[n], rule=r, epochs=2)) for n in TUNED for r in ("outside", "all", "gaining")]
EXP5 = [(f"{b}_{n}", replace(S1, where=TUNED[n], benefit=b, epochs=2)) for n in TUNED for b in ("relative", "exact", "weighted")]
_experiment("exp4_candidates", EXP4, "curve")
_experiment("exp5_benefit", EXP5, "curve")


def _paid(name: str, specs) -> None:
    """The same runs when planning is paid for, which is where the variants differ: wall clock, so rows only."""
    query(name)(lambda spark, sf: w.curves(spark, sf, [(label, replace(s, clock="wall", share=0.1)) for label, s in specs]))


_paid("exp4_candidates_paid", EXP4)
_paid("exp5_benefit_paid", EXP5)
_experiment("exp6_q3", w.all_approaches(replace(w.Q3, epochs=2)), "curve")
_experiment("exp6_q4", w.all_approaches(replace(w.Q4, epochs=2)), "curve")
_experiment("exp6_q5", w.all_approaches(replace(w.Q5, epochs=2)), "curve")
for _percent in (10, 25, 50, 75):
    _experiment(f"exp7_cache_{_percent}", w.all_approaches(replace(S1, cached=_percent, epochs=2)), "curve")


for _part, _where in (("50", w.ORDERS_500), ("75", w.ORDERS_750)):

    def _blocked(spark, sf, where=_where):
        spec = replace(S1, where=where, blocks=20, capacity=5, epochs=3)
        return w.curves(spark, sf, w.all_approaches(spec))

    query(f"exp8_blocks_{_part}")(_blocked)

for _name in ("scorer_first", "object_first", "random"):

    def _block_baseline(spark, sf, approach=_name):
        return w.curves(spark, sf, [(approach, replace(S1, blocks=20, capacity=5, epochs=2, approach=approach))])

    query(f"block_{_name}")(_block_baseline)


@query("exp9_init_counts", " UNION ALL ".join(f"SELECT '{n}' AS selectivity, count(*) AS objects, count(*) AS seeded FROM orders WHERE (o_orderkey * 7919) % 10 >= 2 AND {c}" for n, c in TUNED.items()))
def _(spark, sf):
    out = None
    for n, c in TUNED.items():
        chosen, q, _ = w.prepared(spark, sf, replace(S1, where=c))
        part = seed_state(chosen, q).agg(F.count("*").alias("objects"), F.count(F.when(F.col("m0") == 1, 1)).alias("seeded")).select(F.lit(n).alias("selectivity"), "objects", "seeded")
        out = part if out is None else out.unionByName(part)
    return out


@query("exp9_init_times")
def _(spark, sf):
    """Seconds of loading, seeding and building structures at twelve selectivities: wall clock, so rows only."""
    runs = [(n, a, w.run(spark, sf, replace(s, approach=a)).init_times) for n, s in PLANNED.items() for a in ("progressive", "object_first")]
    return spark.createDataFrame([(n, a, *[float(x[k]) for k in ("load", "seed", "structures")]) for n, a, x in runs], "selectivity string, approach string, load double, seed double, structures double")
