"""Streaming queries over the events file; each has the batch result as its twin."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..registry import query
from ..session import shared_folder
from ..streaming import frames as S


def streamed(f, mode):
    return lambda spark, sf: S.finished(f(S.source(spark, f"{sf}/events.parquet")), mode, shared_folder(spark, "stream"))


def text(d, *times):
    return d.withColumns({c: F.date_format(c, "yyyy-MM-dd HH:mm:ss") for c in times})


@query("st2_tumbling", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, sum((event_type = 'click')::INT)::BIGINT AS clicks FROM events GROUP BY 1")
def st2(spark, sf):
    return text(streamed(S.counts, "complete")(spark, sf), "start")


@query("st3_sliding", "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, sum((event_type = 'click')::INT)::BIGINT AS clicks FROM (SELECT event_type, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 15 MINUTE * k for k in range(4)]) AS s FROM events) GROUP BY 1")
def st3(spark, sf):
    return text(streamed(lambda e: S.counts(e, "1 hour", "15 minutes"), "complete")(spark, sf), "start")


MOMENTS = "SELECT event_type, count(*) AS n, round(sum(value), 4) AS sx, round(sum(user_id % 16)::DOUBLE, 4) AS sy, round(sum(value * (user_id % 16)), 3) AS sxy FROM events GROUP BY 1"


def rounded(d):
    return d.select("event_type", "n", F.round("sx", 4).alias("sx"), F.round("sy", 4).alias("sy"), F.round("sxy", 3).alias("sxy"))


@query("st6_running_moments", MOMENTS)
def st6(spark, sf):
    return rounded(streamed(S.moments, "complete")(spark, sf))


@query("st6_stateful_moments", MOMENTS)
def st6b(spark, sf):
    """The same by an operator with state of its own, in update mode: the last report of each key."""
    d = streamed(S.running_moments, "update")(spark, sf)
    return rounded(d.groupBy("event_type").agg(F.max_by(F.struct("n", "sx", "sy", "sxy"), "n").alias("m")).select("event_type", "m.*"))


@query("st8_stream_static", "SELECT plan, count(*) AS n FROM events JOIN (VALUES ('click', 'res50/full'), ('view', 'res18/half_png'), ('purchase', 'res50/full')) p(event_type, plan) USING (event_type) GROUP BY 1")
def st8(spark, sf):
    """Frames joined with the plan that each kind is to be run by."""
    plans = spark.createDataFrame([("click", "res50/full"), ("view", "res18/half_png"), ("purchase", "res50/full")], "event_type string, plan string")
    return streamed(lambda e: S.enriched(e.select("event_type"), plans).select("plan"), "append")(spark, sf).groupBy("plan").agg(F.count("*").alias("n"))


@query("st7_stream_stream_join", "SELECT p.user_id, count(*) AS n FROM events p JOIN events e ON p.event_type = 'purchase' AND e.event_type = 'error' AND e.user_id = p.user_id AND p.ts BETWEEN e.ts AND e.ts + INTERVAL 10 MINUTE GROUP BY 1")
def st7(spark, sf):
    return streamed(S.scored_pairs, "append")(spark, sf).groupBy("user_id").agg(F.count("*").alias("n"))


@query("st9_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def st9(spark, sf):
    return streamed(lambda e: S.distinct(e).select("event_id"), "append")(spark, sf).agg(F.count("*").alias("n"))


@query("st12_adaptive_plan", "SELECT a::DOUBLE AS arriving, p AS plan FROM (VALUES (100.0, 'res50/full'), (1000.0, 'res50/png161'), (9000.0, 'res50/png161')) x(a, p)")
def st12(spark, sf):
    front = [("res50/full", 75.16, 527.0), ("res50/png161", 75.0, 1995.0)]
    return spark.createDataFrame([(a, S.adaptive_plan(front, a)) for a in (100.0, 1000.0, 9000.0)], "arriving double, plan string")
