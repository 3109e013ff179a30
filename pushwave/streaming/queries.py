"""Streaming queries; each twin is the plain query over the static table."""

from __future__ import annotations

from pyspark.sql import functions as F

from pushwave.plans.durable import ship
from pushwave.streaming import arcs as A
from pushwave.workloads import register


@register("q_stream_daily", "SELECT date_trunc('day', ts)::TIMESTAMP AS day, user_id, count(*) AS n FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1, 2")
def q_stream_daily(spark, d):
    return A.run(A.daily_counts(A.source(spark, d)))


@register("q_stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def q_stream_dedup(spark, d):
    return A.run(A.distinct_pairs(A.source(spark, d)))


@register("q_stream_interval_join", "SELECT a.event_id AS click, b.event_id AS purchase, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def q_stream_interval_join(spark, d):
    return A.run(A.click_then_purchase(A.source(spark, d)))


@register("q_stream_successive", "SELECT user_id, src, dst, count(*) AS n FROM (SELECT user_id, event_type AS src, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL GROUP BY 1, 2, 3")
def q_stream_successive(spark, d):
    ship(spark)
    return A.run(A.successive_types(A.source(spark, d))).groupBy("user_id", "src", "dst").agg(F.count(F.lit(1)).alias("n"))


#: What a watermark of an hour behind the last event has closed.
_CLOSED = "(SELECT max(ts) FROM events) - INTERVAL 1 HOUR"


@register("q_stream_sessions", f"SELECT user_id, min(ts) AS begin, max(ts) + INTERVAL 30 MINUTE AS finish, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WHERE user_id IS NOT NULL)) GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= {_CLOSED}")
def q_stream_sessions(spark, d):
    return A.run(A.sessions(A.source(spark, d)))


@register("q_stream_sliding", f"SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - i * INTERVAL 6 HOUR AS start FROM events, range(4) t(i)) WHERE start + INTERVAL 1 DAY <= {_CLOSED} GROUP BY 1")
def q_stream_sliding(spark, d):
    return A.run(A.sliding_counts(A.source(spark, d)))
