"""Streams over the event table, drained and compared with their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from statewitness.plans.base import workload
from statewitness.plans.replay_plans import REACH
from statewitness.sources.formats import scratch_path
from statewitness.streaming import monitor as S


@workload("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    return S.drained(S.tumbling(S.event_stream(spark, d)), "complete")


@workload("stream_sliding", "SELECT strftime(date_trunc('day', ts) - to_days(k::INTEGER), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, range(2) r(k) GROUP BY 1")
def stream_sliding(spark, d):
    return S.drained(S.sliding(S.event_stream(spark, d)), "complete")


@workload("stream_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT count(*) AS sessions, sum(n)::BIGINT AS events, max(n) AS longest FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2)""")
def stream_session(spark, d):
    rows = S.drained(S.sessions(S.event_stream(spark, d)), "complete")
    return rows.agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


@workload("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_dedup(spark, d):
    """Calls delivered twice are counted once."""
    rows = S.drained(S.once(S.event_stream(spark, d).withColumn("again", F.explode(F.array(F.lit(1), F.lit(2))))).select("event_id", "event_type"))
    return rows.groupBy("event_type").agg(F.count("*").alias("n"))


@workload("stream_static_join", "SELECT verb, count(*) AS n FROM events JOIN (VALUES ('purchase', 'charge'), ('error', 'hold'), ('signup', 'release')) c(event_type, verb) USING (event_type) GROUP BY 1")
def stream_static_join(spark, d):
    contracts = spark.createDataFrame([("purchase", "charge"), ("error", "hold"), ("signup", "release")], "event_type string, verb string")
    return S.drained(S.with_static(S.event_stream(spark, d), contracts).select("event_id", "verb")).groupBy("verb").agg(F.count("*").alias("n"))


@workload("stream_interval_join", "SELECT e.event_id AS call, p.event_id AS effect FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts > e.ts AND p.ts <= e.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, d):
    calls = S.event_stream(spark, d).filter("event_type = 'error'")
    effects = S.event_stream(spark, d).filter("event_type = 'purchase'")
    return S.drained(S.effects_within(calls, effects))


@workload("stream_reach", f"SELECT count(*) AS purchases, count(*) FILTER (held = 'error') AS reaching FROM ({REACH}) WHERE event_type = 'purchase'")
def stream_reach(spark, d):
    """The live monitor over files in order gives what the batch window gives."""
    path = S.split_files(spark, d, 4)
    rows = S.drained(S.live_reach(S.event_stream(spark, d, path=path)))
    return rows.agg(F.count("*").alias("purchases"), F.count_if("reaches").alias("reaching"))


@workload("stream_late", "SELECT count(*) AS delivered FROM events")
def stream_late(spark, d):
    """Rows of a late file are delivered by a stateless stream, and told apart by the watermark's distance."""
    path = S.split_files(spark, d, 4, late=0)
    rows = S.drained(S.event_stream(spark, d, path=path).select("event_id", "at"))
    return rows.agg(F.count("*").alias("delivered"))


@workload("stream_foreach_ledger", "SELECT count(*) AS n_rows FROM events WHERE event_type = 'error'")
def stream_foreach_ledger(spark, d):
    """A ledger filled twice by the same stream holds each row once."""
    path = scratch_path(spark, "ledger")
    for _ in range(2):
        S.into_ledger(S.event_stream(spark, d).filter("event_type = 'error'").select("event_id", "user_id"), path, ["event_id"])
    return spark.read.parquet(path).agg(F.count("*").alias("n_rows"))
