"""Registered streaming queries; where a batch query gives the same rows, its SQL is the oracle."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.tagexpr import parse_tag_expr
from ..operators.state import Query
from ..plans import workloads as w
from ..plans.epoch_sql import raw_sql
from ..plans.registry import query
from ..sources.objects import COLLECTIONS
from ..sources.tables import table
from . import ingest

P = raw_sql("event_id", "event_type = 'purchase'", 2, 0)


@query("stream_seed_state", f"SELECT event_id AS object_id, CAST(1 AS INTEGER) AS mask, {P} AS match_p FROM events", "match_p")
def _(spark, sf):
    q = Query(parse_tag_expr("Kind = 'purchase'"), COLLECTIONS["events"].catalog())
    return ingest.stream_seed_state(ingest.event_stream(spark, sf), q).select("object_id", F.col("m0").alias("mask"), "match_p")


@query("stream_tumbling", f"SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, sum({P}) AS expected, count(*) AS n FROM events GROUP BY 1", "expected")
def _(spark, sf):
    out = ingest.finished(ingest.expected_counts(ingest.event_stream(spark, sf), F.window("ts", "1 day")), "complete")
    return out.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "expected", "n")


@query("stream_sliding", f"SELECT strftime(s, '%Y-%m-%d %H') AS start, sum({P}) AS expected, count(*) AS n FROM (SELECT *, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1", "expected")
def _(spark, sf):
    out = ingest.finished(ingest.expected_counts(ingest.event_stream(spark, sf), F.window("ts", "1 day", "12 hours")), "complete")
    return out.select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "expected", "n")


@query("stream_session", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) WHERE gap IS NULL OR gap >= INTERVAL 6 HOUR GROUP BY user_id")
def _(spark, sf):
    return _sessions(spark, sf)


def _sessions(spark, sf):
    s = ingest.event_stream(spark, sf, 1).withWatermark("ts", "1 hour")
    out = ingest.finished(s.groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n")), "complete")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"))


@query("stream_watermark")
def _(spark, sf):
    out = ingest.finished(ingest.expected_counts(ingest.event_stream(spark, sf), F.window("ts", "1 day"), "1 hour"))
    return out.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "expected", "n")


@query("stream_dedup", "SELECT DISTINCT user_id FROM events")
def _(spark, sf):
    return _users(spark, sf)


def _users(spark, sf):
    s = ingest.event_stream(spark, sf).withWatermark("ts", "40 days")
    return ingest.finished(s.dropDuplicatesWithinWatermark(["user_id"]).select("user_id"))


@query("stream_static_join", "SELECT e.event_id, c.c_mktsegment FROM events e JOIN customer c ON e.user_id = c.c_custkey WHERE e.event_type = 'error'")
def _(spark, sf):
    c = table(spark, sf, "customer", "c_custkey", "c_mktsegment")
    s = ingest.event_stream(spark, sf).where("event_type = 'error'")
    return ingest.finished(s.join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("stream_interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def _(spark, sf):
    s = ingest.event_stream(spark, sf)
    a = s.where("event_type = 'view'").select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", "1 day")
    t = ingest.event_stream(spark, sf)
    b = t.where("event_type = 'purchase'").select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", "1 day")
    j = a.join(b, (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("INTERVAL 1 HOUR")))
    return ingest.finished(j.select("a_id", "b_id"))


@query("stream_keyed_state", "SELECT user_id, CAST(bit_or(1 << (list_position(['view', 'signup', 'purchase', 'error', 'click'], event_type) - 1)) AS INTEGER) AS mask FROM events GROUP BY user_id")
def _(spark, sf):
    out = ingest.finished(ingest.keyed_masks(ingest.event_stream(spark, sf)), "update")
    return out.groupBy("user_id").agg(F.max("mask").alias("mask"))  # masks only grow: the last is the greatest


@query("stream_epochs")
def _(spark, sf):
    _, q, t = w.prepared(spark, sf, w.TWEETS_10)
    return ingest.stream_epochs(ingest.event_stream(spark, sf, 3), q, t, 500.0)
