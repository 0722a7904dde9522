"""Streaming queries over the replayed events; each equals its batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.plans.registry import query
from tablemill.streaming import windows as S


@query("stream_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(t):
    return S.drained(S.tumbling(S.replayed(t.events)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding", "SELECT date_trunc('hour', ts) - to_hours(k::INT) AS start, event_type, count(*)::BIGINT AS n FROM events, range(6) r(k) GROUP BY 1, 2")
def stream_sliding(t):
    return S.drained(S.sliding(S.replayed(t.events)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_session", """WITH g AS (SELECT user_id, ts, coalesce(ts >= lag(ts) OVER w + INTERVAL 6 HOURS, TRUE)::INT AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), r AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS run FROM g)
SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOURS AS "end", count(*)::BIGINT AS n FROM r GROUP BY user_id, run HAVING max(ts) + INTERVAL 6 HOURS <= (SELECT max(ts) - INTERVAL 2 HOURS FROM events)""")
def stream_session(t):
    """Sessions that the watermark (two hours behind the last event) has closed."""
    out = S.drained(S.sessions(S.replayed(t.events)))
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


@query("stream_dedup", "SELECT count(*)::BIGINT AS n, count(DISTINCT event_id)::BIGINT AS kinds FROM events")
def stream_dedup(t):
    """Every third event is sent twice."""
    twice = t.events.unionByName(t.events.where("event_id % 3 = 0"))
    return S.drained(S.deduplicated(S.replayed(twice))).agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("kinds"))


@query("stream_static_join", "SELECT c_mktsegment, count(*)::BIGINT AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(t):
    joined = S.replayed(t.events).join(t.customer, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")
    return S.drained(joined).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("stream_interval_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOURS")
def stream_interval_join(t):
    """A click and a purchase of the same user within six hours; both sides are streams."""
    side = lambda kind, p: S.replayed(t.events.where(F.col("event_type") == kind)).select(F.col("user_id").alias(f"{p}_user"), F.col("ts").alias(f"{p}_ts"), F.col("event_id").alias(f"{p}_id")).withWatermark(f"{p}_ts", "400 days")
    a, b = side("click", "a"), side("purchase", "b")
    on = F.expr("a_user = b_user AND b_ts >= a_ts AND b_ts <= a_ts + interval 6 hours")
    return S.drained(a.join(b, on)).select(F.col("a_id").alias("click"), F.col("b_id").alias("purchase"))


@query("stream_late_drop")
def stream_late_drop(t):
    """A tenth of the events arrive up to 200 places late; windows past the watermark do not take them any more."""
    from tablemill.functions import det

    k = F.col("event_id")
    late = t.events.withColumn("arrival", k + F.when(det.unit("late", k) < 0.1, F.floor(det.unit("by", k) * 200)).otherwise(0))
    out = S.drained(S.tumbling(S.replayed(late, 12, "arrival"), delay="10 minutes"))
    return out.agg(F.count("*").alias("windows"), F.sum("n").alias("counted"))


@query("stream_expiry")
def stream_expiry(t):
    """Idle sandboxes by event-time timers; the last run of each session is still open."""
    out = S.drained(S.expired(S.replayed(t.events)))
    return out.groupBy("session").agg(F.count("*").alias("expired"))
