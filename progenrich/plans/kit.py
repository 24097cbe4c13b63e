"""Queries for the relational operators and functions that users of the methods need around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import joins
from ..sources import sinks
from ..sources.objects import objects
from ..sources.tables import TABLES, register, table
from .epoch_sql import BASES
from .registry import query

# --- scans, sources and sinks ---------------------------------------------------------------------

SCANS = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_name, n_regionkey", "customer": "c_custkey, c_nationkey, c_mktsegment", "supplier": "s_suppkey, s_nationkey, s_acctbal",
    "part": "p_partkey, p_brand, p_size", "orders": "o_orderkey, o_custkey, o_orderstatus", "lineitem": "l_orderkey, l_linenumber, l_returnflag", "events": "event_id, user_id, event_type",
    "documents": "doc_id, lang, source", "embeddings": "vec_id, label", "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role",
}
for _t in TABLES:

    def _scan(spark, sf, name=_t):
        return table(spark, sf, name, *SCANS[name].split(", "))

    query(f"scan_{_t}", f"SELECT {SCANS[_t]} FROM {_t}")(_scan)

for _f in ("csv", "json", "orc"):

    def _trip(spark, sf, fmt=_f):
        return sinks.round_trip(table(spark, sf, "nation"), fmt)

    query(f"roundtrip_{_f}", "SELECT * FROM nation")(_trip)


@query("roundtrip_text", "SELECT n_name AS value FROM nation")
def _(spark, sf):
    return sinks.round_trip(table(spark, sf, "nation").select(F.col("n_name").alias("value")), "text")


@query("log_partitioned", "SELECT 'Status' AS tag_type, CAST(o_orderkey % 3 AS INTEGER) AS scorer, count(*) AS n FROM orders GROUP BY 1, 2")
def _(spark, sf):
    log = table(spark, sf, "orders").select(F.col("o_orderkey").alias("object_id"), F.lit("Status").alias("tag_type"), F.lit("F").alias("tag"), (F.col("o_orderkey") % 3).cast("int").alias("scorer"), F.lit(0.5).alias("prob"), F.lit(1.0).alias("cost"), F.lit(1).alias("epoch"), F.lit("q").alias("query_id"))
    path = sinks.write_log(log.where("scorer <> 2"))
    sinks.write_log(log.where("scorer = 2"), path)  # append
    sinks.write_log(log.where("scorer = 1"), path, overwrite_partitions=True)
    return spark.read.parquet(path).groupBy("tag_type", F.col("scorer").cast("int").alias("scorer")).agg(F.count("*").alias("n"))


def _sql(name: str, text: str, *views: str, doubles: str = "", duck: str | None = None) -> None:
    @query(name, duck or text, doubles)
    def _(spark, sf):
        register(spark, sf, *views)
        return spark.sql(text)


_sql("sql_view", "SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderstatus", "orders")

# --- projections and filters ----------------------------------------------------------------------


@query("precise_filter_orders", f"SELECT object_id, o_totalprice FROM ({BASES['orders']}) WHERE o_orderdate < date '1996-01-01' AND c_nationkey = 3 AND o_totalprice > 100000", "o_totalprice")
def _(spark, sf):
    return objects(spark, sf, "orders").where("o_orderdate < date '1996-01-01' AND c_nationkey = 3 AND o_totalprice > 100000").select("object_id", "o_totalprice")


@query("precise_in_between", f"SELECT object_id, n_name FROM ({BASES['orders']}) WHERE n_name IN ('NATION_1', 'NATION_2') AND o_orderdate BETWEEN date '1996-01-01' AND date '1996-06-30'")
def _(spark, sf):
    o = objects(spark, sf, "orders")
    return o.where(F.col("n_name").isin("NATION_1", "NATION_2") & F.col("o_orderdate").between(F.expr("date '1996-01-01'"), F.expr("date '1996-06-30'"))).select("object_id", "n_name")


@query("filter_like", "SELECT c_custkey, c_name FROM customer WHERE c_name LIKE '%00001_' AND regexp_matches(c_mktsegment, '^(B|F)')")
def _(spark, sf):
    return table(spark, sf, "customer").where(F.col("c_name").like("%00001_") & F.col("c_mktsegment").rlike("^(B|F)")).select("c_custkey", "c_name")


@query("filter_null_safe", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 0")
def _(spark, sf):
    d = table(spark, sf, "documents", "doc_id").join(table(spark, sf, "labels", "doc_id", "quality"), "doc_id", "left")
    return d.where(F.col("quality").eqNullSafe(F.lit(None).cast("int")) | (F.col("quality") == 0))


@query("project_case", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, CAST(year(o_orderdate) AS INTEGER) AS y FROM orders")
def _(spark, sf):
    p = F.col("o_totalprice")
    return table(spark, sf, "orders").select("o_orderkey", F.when(p > 300000, "high").when(p > 100000, "mid").otherwise("low").alias("band"), F.year("o_orderdate").alias("y"))


@query("project_struct", "SELECT n_nationkey, n_name AS a, n_regionkey + 1 AS b FROM nation")
def _(spark, sf):
    return table(spark, sf, "nation").select("n_nationkey", F.struct(F.col("n_name").alias("a"), (F.col("n_regionkey") + 1).alias("b")).alias("s")).select("n_nationkey", "s.a", "s.b")


@query("distinct_tags", "SELECT DISTINCT o_orderstatus, o_orderpriority FROM orders")
def _(spark, sf):
    return table(spark, sf, "orders", "o_orderstatus", "o_orderpriority").dropDuplicates()


# --- joins ----------------------------------------------------------------------------------------


@query("join_objects_dims", "SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(spark, sf):
    o = objects(spark, sf, "orders").select("object_id", "n_regionkey")
    return o.join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


#: Most rows of a plan that is broadcast, once counted.
PLAN_ROWS = 100_000


def _planned_lines(spark, sf):
    plan = table(spark, sf, "orders", F.col("o_orderkey").alias("object_id"))
    if plan.limit(PLAN_ROWS + 1).count() <= PLAN_ROWS:
        plan = F.broadcast(plan)
    return table(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_partkey").join(plan, F.col("l_orderkey") == F.col("object_id")).drop("object_id")


@query("join_broadcast_plan", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def _(spark, sf):
    return _planned_lines(spark, sf)

@query("join_sort_merge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
def _(spark, sf):
    li, o = table(spark, sf, "lineitem", "l_orderkey"), table(spark, sf, "orders", "o_orderkey", "o_orderpriority")
    return li.join(o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(spark, sf):
    return table(spark, sf, "orders", "o_custkey").join(table(spark, sf, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("semi_plan_payload", f"SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def _(spark, sf):
    return table(spark, sf, "documents", "doc_id", "n_chars").join(table(spark, sf, "labels").where("toxic = 1"), "doc_id", "left_semi")


@query("anti_unlabelled", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(spark, sf):
    return table(spark, sf, "documents", "doc_id").join(table(spark, sf, "labels", "doc_id"), "doc_id", "left_anti")


@query("join_outer", "SELECT coalesce(a.n_nationkey, b.s_nationkey) AS k, a.n_name, b.n AS n FROM nation a FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier GROUP BY 1) b ON a.n_nationkey = b.s_nationkey")
def _(spark, sf):
    b = table(spark, sf, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("n"))
    a = table(spark, sf, "nation", "n_nationkey", "n_name")
    return a.join(b, F.col("n_nationkey") == F.col("s_nationkey"), "full").select(F.coalesce("n_nationkey", "s_nationkey").alias("k"), "n_name", "n")


BANDS = [(0, 50000.0, "a"), (50000.0, 150000.0, "b"), (150000.0, 300000.0, "c"), (300000.0, 1e9, "d")]


@query("join_range_bins", "SELECT name, count(*) AS n FROM orders JOIN (VALUES (0::DOUBLE, 50000::DOUBLE, 'a'), (50000, 150000, 'b'), (150000, 300000, 'c'), (300000, 1e9, 'd')) v(lo, hi, name) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY name")
def _(spark, sf):
    bands = spark.createDataFrame([(float(a), b, c) for a, b, c in BANDS], "lo double, hi double, name string")
    o = table(spark, sf, "orders", "o_totalprice")
    return o.join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("name").agg(F.count("*").alias("n"))


@query("asof_curve", "SELECT e.event_id, e.user_id, (SELECT arg_max(p.event_id, p.ts) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS last_purchase FROM events e WHERE e.event_type = 'error'")
def _(spark, sf):
    return _last_purchases(spark, sf)


def _last_purchases(spark, sf):
    ev = table(spark, sf, "events", "event_id", "user_id", "event_type", "ts")
    points = ev.where("event_type = 'error'")
    facts = ev.where("event_type = 'purchase'").withColumnRenamed("event_id", "last_purchase")
    asof = joins.as_of(points, facts, "user_id", "ts", "last_purchase")
    return asof.join(points.select("event_id", "user_id", "ts"), ["user_id", "ts"]).select("event_id", "user_id", "last_purchase")


@query("interval_join_events", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def _(spark, sf):
    e = table(spark, sf, "events", "event_id", "user_id", "event_type", "ts")
    a = e.where("event_type = 'view'").select(F.col("event_id").alias("a_id"), "user_id", F.col("ts").alias("a_ts"))
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b_id"), "user_id", F.col("ts").alias("b_ts"))
    return a.join(b, "user_id").where((F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("INTERVAL 1 HOUR"))).select("a_id", "b_id")


@query("join_salted", "SELECT event_type, count(*) AS n FROM events e JOIN (SELECT user_id, count(*) AS c FROM events GROUP BY user_id) u ON e.user_id = u.user_id WHERE c > 5 GROUP BY event_type")
def _(spark, sf):
    e = table(spark, sf, "events", "user_id", "event_id", "event_type")
    u = e.groupBy("user_id").agg(F.count("*").alias("c"))
    return joins.salted_join(e, u, "user_id").where("c > 5").groupBy("event_type").agg(F.count("*").alias("n"))


# --- aggregates -----------------------------------------------------------------------------------

_sql("agg_tag_counts", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, sum(o_totalprice) AS total FROM orders GROUP BY o_orderstatus, o_orderpriority", "orders", doubles="total")
_sql("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderpriority) AS priorities FROM orders GROUP BY o_orderstatus", "orders")
_sql("agg_conditional", "SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS n, count_if(l_quantity > 25) AS big, sum(CASE WHEN l_linestatus = 'F' THEN l_extendedprice ELSE 0 END) AS f FROM lineitem GROUP BY l_returnflag", "lineitem", doubles="f", duck="SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS n, CAST(count_if(l_quantity > 25) AS BIGINT) AS big, sum(CASE WHEN l_linestatus = 'F' THEN l_extendedprice ELSE 0 END) AS f FROM lineitem GROUP BY l_returnflag")
for _n, _g in (("agg_rollup", "ROLLUP (o_orderstatus, o_orderpriority)"), ("agg_cube", "CUBE (o_orderstatus, o_orderpriority)"), ("agg_grouping_sets", "GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")):
    _sql(_n, f"SELECT o_orderstatus, o_orderpriority, CAST(grouping_id(o_orderstatus, o_orderpriority) AS BIGINT) AS gid, count(*) AS n FROM orders GROUP BY {_g}", "orders")


@query("agg_max_by", "SELECT o_custkey, arg_max(o_orderkey, o_totalprice) AS top, arg_min(o_orderkey, o_totalprice) AS low FROM orders GROUP BY o_custkey")
def _(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", "o_totalprice").alias("top"), F.min_by("o_orderkey", "o_totalprice").alias("low"))


@query("agg_mode", "SELECT o_custkey % 7 AS g, mode(o_orderstatus) AS m FROM orders GROUP BY 1")
def _(spark, sf):
    return _modes(spark, sf)


def _modes(spark, sf):
    return table(spark, sf, "orders").groupBy((F.col("o_custkey") % 7).alias("g")).agg(F.mode("o_orderstatus").alias("m"))


@query("agg_collect", "SELECT o_custkey, list_sort(list(DISTINCT o_orderstatus)) AS tags FROM orders GROUP BY o_custkey")
def _(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.array_sort(F.collect_set("o_orderstatus")).alias("tags"))


_sql("agg_percentile", "SELECT l_returnflag, percentile(l_quantity, 0.5) AS med, percentile(l_extendedprice, 0.9) AS p90 FROM lineitem GROUP BY l_returnflag", "lineitem", doubles="med p90", duck="SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS med, quantile_cont(l_extendedprice, 0.9) AS p90 FROM lineitem GROUP BY l_returnflag")
_sql("agg_stats", "SELECT l_returnflag, corr(l_quantity, l_extendedprice) AS c, stddev_samp(l_discount) AS sd, var_pop(l_tax) AS v FROM lineitem GROUP BY l_returnflag", "lineitem", doubles="c sd v")


@query("approx_distinct")
def _(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("med"))


@query("pivot_work", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY o_orderpriority")
def _(spark, sf):
    return table(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).na.fill(0)


@query("unpivot_work", "SELECT n_nationkey, 'n_regionkey' AS name, CAST(n_regionkey AS BIGINT) AS value FROM nation UNION ALL SELECT n_nationkey, 'twice', CAST(n_regionkey * 2 AS BIGINT) FROM nation")
def _(spark, sf):
    n = table(spark, sf, "nation").select("n_nationkey", F.col("n_regionkey").cast("long").alias("n_regionkey"), (F.col("n_regionkey") * 2).cast("long").alias("twice"))
    return n.unpivot("n_nationkey", ["n_regionkey", "twice"], "name", "value")


@query("expected_aggregate", f"SELECT n_regionkey, sum(p) AS expected_count, sum(p * o_totalprice) AS expected_sum, sum(p * o_totalprice) / sum(p) AS expected_avg FROM (SELECT *, (object_id % 101) / 101.0 AS p FROM ({BASES['orders']})) GROUP BY n_regionkey", "expected_count expected_sum expected_avg")
def _(spark, sf):
    o = objects(spark, sf, "orders").withColumn("p", (F.col("object_id") % 101) / 101.0)
    s, t = F.sum("p"), F.sum(F.col("p") * F.col("o_totalprice"))
    return o.groupBy("n_regionkey").agg(s.alias("expected_count"), t.alias("expected_sum"), (t / s).alias("expected_avg"))


# --- windows, order, sets -------------------------------------------------------------------------

_sql("win_rank_family", "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd, ntile(4) OVER w AS nt FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)", "supplier", doubles="pr cd")
_sql("win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type, 2) OVER w AS after, first_value(event_type) OVER w AS first, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
_sql("win_running_cost", "SELECT o_orderkey, sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running FROM orders", "orders", doubles="running")
_sql("win_sliding", "SELECT o_orderkey, avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS slide FROM orders", "orders", doubles="slide")
_sql("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY k RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM (SELECT event_id, user_id, event_id AS k FROM events) e", "events")


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", "o_totalprice")
def _(spark, sf):
    return table(spark, sf, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("topk_per_group", "SELECT o_orderstatus, o_orderkey FROM (SELECT o_orderstatus, o_orderkey, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 5")
def _(spark, sf):
    k = F.row_number().over(W.partitionBy("o_orderstatus").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return table(spark, sf, "orders", "o_orderstatus", "o_orderkey", "o_totalprice").withColumn("k", k).where("k <= 5").select("o_orderstatus", "o_orderkey")


@query("sort_offset", "SELECT c_custkey FROM customer ORDER BY c_acctbal DESC NULLS LAST, c_custkey LIMIT 20 OFFSET 30")
def _(spark, sf):
    return table(spark, sf, "customer", "c_custkey", "c_acctbal").orderBy(F.desc_nulls_last("c_acctbal"), "c_custkey").offset(30).limit(20).select("c_custkey")


@query("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def _(spark, sf):
    return table(spark, sf, "customer", F.col("c_nationkey").alias("k")).unionByName(table(spark, sf, "supplier", F.col("s_nationkey").alias("k"))).distinct()


@query("set_intersect", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'P'")
def _(spark, sf):
    o = table(spark, sf, "orders", F.col("o_custkey").alias("k"), "o_orderstatus")
    return o.where("o_orderstatus = 'F'").select("k").intersect(o.where("o_orderstatus = 'P'").select("k"))


@query("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
def _(spark, sf):
    return table(spark, sf, "customer", F.col("c_custkey").alias("k")).subtract(table(spark, sf, "orders", F.col("o_custkey").alias("k")))


# --- scalar functions -----------------------------------------------------------------------------

_sql("fn_string", "SELECT c_custkey, lower(c_mktsegment) AS a, regexp_extract(c_name, '0*([1-9][0-9]*)$', 1) AS b, length(c_name) AS c, translate(c_name, '#', '-') AS d, concat_ws('|', c_name, c_mktsegment) AS e, levenshtein(c_mktsegment, 'BUILDING') AS f, split(c_name, '#')[0] AS g, substring(c_name, 1, 4) AS h FROM customer", "customer",
     duck="SELECT c_custkey, lower(c_mktsegment) AS a, regexp_extract(c_name, '0*([1-9][0-9]*)$', 1) AS b, CAST(length(c_name) AS INTEGER) AS c, translate(c_name, '#', '-') AS d, concat_ws('|', c_name, c_mktsegment) AS e, CAST(levenshtein(c_mktsegment, 'BUILDING') AS INTEGER) AS f, split(c_name, '#')[1] AS g, substring(c_name, 1, 4) AS h FROM customer")
_sql("fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, year(o_orderdate) AS y, datediff(o_orderdate, date '1995-01-01') AS d, CAST(add_months(o_orderdate, 3) AS DATE) AS a FROM orders", "orders", duck="SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(datediff('day', DATE '1995-01-01', o_orderdate) AS INTEGER) AS d, CAST(o_orderdate + INTERVAL 3 MONTH AS DATE) AS a FROM orders")
_sql("fn_math", "SELECT o_orderkey, log2(o_totalprice) AS a, sqrt(o_totalprice) AS b, pow(o_totalprice / 1e6, 2) AS c, floor(o_totalprice / 1000) AS d, round(o_totalprice, 1) AS e, greatest(o_totalprice, 2e5) AS f, least(o_totalprice, 2e5) AS g, exp(-o_totalprice / 1e6) AS h, CAST(width_bucket(o_totalprice, 0, 500000, 10) AS BIGINT) AS i FROM orders", "orders", doubles="a b c e f g h",
     duck="SELECT o_orderkey, log2(o_totalprice) AS a, sqrt(o_totalprice) AS b, pow(o_totalprice / 1e6, 2) AS c, CAST(floor(o_totalprice / 1000) AS BIGINT) AS d, round(o_totalprice, 1) AS e, greatest(o_totalprice, 2e5) AS f, least(o_totalprice, 2e5) AS g, exp(-o_totalprice / 1e6) AS h, CAST(floor(o_totalprice / 50000) AS BIGINT) + 1 AS i FROM orders")
VEC = "CAST(embedding AS array<double>)"
_sql("fn_array", f"SELECT vec_id, aggregate({VEC}, 0D, (a, x) -> a + x) AS s, array_max({VEC}) AS m, size(filter({VEC}, x -> x > 0)) AS pos, exists({VEC}, x -> x > 0.3) AS any_big FROM embeddings", "embeddings", doubles="s m", duck="SELECT vec_id, list_sum(embedding::DOUBLE[]) AS s, list_max(embedding::DOUBLE[]) AS m, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, len(list_filter(embedding, lambda x: x::DOUBLE > 0.3)) > 0 AS any_big FROM embeddings")
_sql("vector_dot", f"SELECT a.vec_id, aggregate(zip_with(CAST(a.embedding AS array<double>), CAST(b.embedding AS array<double>), (x, y) -> x * y), 0D, (s, x) -> s + x) AS dot FROM embeddings a JOIN (SELECT embedding FROM embeddings WHERE vec_id = 0) b", "embeddings", doubles="dot", duck="SELECT a.vec_id, list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS dot FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id = 0) b")


@query("fn_map", "SELECT n_nationkey, n_regionkey + 10 AS v, CAST(CASE WHEN n_regionkey > 1 THEN 2 ELSE 1 END AS INTEGER) AS big FROM nation")
def _(spark, sf):
    m = F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array(F.col("n_regionkey"), F.col("n_regionkey") + 10))
    n = table(spark, sf, "nation").withColumn("m", m)
    return n.select("n_nationkey", F.element_at("m", "b").alias("v"), F.size(F.map_filter("m", lambda k, v: v > 1)).alias("big"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def _(spark, sf):
    return table(spark, sf, "events", "event_id", "props").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("fn_bits", "SELECT o_orderkey, CAST(1 << (o_orderkey % 8) AS INTEGER) AS s, CAST(bit_count(CAST(o_orderkey AS BIGINT)) AS INTEGER) AS c, o_orderkey & 6 AS a FROM orders")
def _(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", F.expr("shiftleft(1, CAST(o_orderkey % 8 AS INT))").alias("s"), F.bit_count("o_orderkey").alias("c"), F.col("o_orderkey").bitwiseAND(6).alias("a"))


@query("page_url_parts", r"SELECT page_id, regexp_extract(url, '^https?://([^/?]+)', 1) AS host, regexp_extract(url, '^https?://[^/]+(/[^?]*)', 1) AS path FROM pages")
def _(spark, sf):
    return table(spark, sf, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", r"^https?://([^/?]+)", 1).alias("host"), F.regexp_extract("url", r"^https?://[^/]+(/[^?]*)", 1).alias("path"))


@query("page_text", r"SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS text_chars FROM pages")
def _(spark, sf):
    h = F.col("html")
    return table(spark, sf, "pages", "page_id", "html").select("page_id", F.regexp_extract(h, '<html lang="([a-z]+)"', 1).alias("lang"), F.length(F.regexp_replace(h, "<[^>]*>", "")).cast("long").alias("text_chars"))


@query("doc_features", r"SELECT doc_id, n_chars, len(regexp_extract_all(text, '[^ \t\n\r]+')) AS words, length(regexp_replace(text, '[A-Za-z]', '', 'g')) / length(text)::DOUBLE AS other_share, regexp_matches(lower(text), '(idiot|moron|clown)') AS rude FROM documents WHERE length(text) > 0", "other_share")
def _(spark, sf):
    from ..operators.text_scorers import extract_features

    return extract_features(table(spark, sf, "documents", "doc_id", "text", "n_chars").where(F.length("text") > 0)).select("doc_id", "n_chars", "words", "other_share", "rude")


_sql("sql_subquery", "SELECT c_custkey, (SELECT max(o_totalprice) FROM orders WHERE o_custkey = c_custkey) AS top FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P') AND c_acctbal > (SELECT avg(c_acctbal) FROM customer)", "customer", "orders", doubles="top")
_sql("sql_cte", "WITH t AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY o_custkey), u AS (SELECT avg(s) AS m FROM t) SELECT count(*) AS n FROM t, u WHERE s > m", "orders")
_sql("sql_recursive", "WITH RECURSIVE r(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 10) SELECT n, f FROM r")


@query("join_bucketed", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(spark, sf):
    """Both sides bucketed on the key: the join itself needs no shuffle."""
    a = sinks.write_bucketed(table(spark, sf, "orders", F.col("o_custkey").alias("k")), "bucketed_orders", "k", 8)
    b = sinks.write_bucketed(table(spark, sf, "customer", F.col("c_custkey").alias("k"), "c_mktsegment"), "bucketed_customer", "k", 8)
    return a.join(b.hint("merge"), "k").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("explain_costs")
def _(spark, sf):
    """Costly operators in the physical plan of one planning step and of one cutoff round."""
    from ..operators import cutoff, metrics, planning
    from . import workloads as w

    chosen, q, t = w.prepared(spark, sf, w.SMALL_100)
    from ..operators.state import seed_state

    st = seed_state(chosen, q)
    plans = {"items": planning.benefit_relative(planning.make_items(st, q, t)), "cutoff": st.agg(F.sum("match_p")), "answer": st.where(F.col("match_p") > cutoff.choose_answer(st).ratio)}
    return spark.createDataFrame([(name, k, n) for name, df in plans.items() for k, n in metrics.plan_report(df).items()], "step string, operator string, n int")
