"""Streaming queries over the events table, drained to their end."""

from __future__ import annotations

from pyspark.sql import functions as F

from crossaudit.plans.registry import query
from crossaudit.sources import table
from crossaudit.streaming import events as ev


def _stream(spark, sf_dir):
    return ev.read_stream(spark, f"{sf_dir}/events.parquet", table(spark, sf_dir, "events").schema, "ts")


@query("stream_tumbling", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return ev.drain(ev.tumbling(_stream(spark, sf_dir)), "tumbling").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding", "SELECT CAST(date_trunc('day', ts) - to_days(k) AS TIMESTAMP) AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    return ev.drain(ev.sliding(_stream(spark, sf_dir)), "sliding").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM g) SELECT user_id, CAST(min(ts) AS TIMESTAMP) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    return ev.drain(ev.sessions(_stream(spark, sf_dir)), "session").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_dedup", "SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")
def stream_dedup(spark, sf_dir):
    """Users and event types seen for the first time."""
    return ev.drain(ev.first_arrivals(_stream(spark, sf_dir), ["user_id", "event_type"]), "dedup", "append").agg(F.count(F.lit(1)).alias("n"))


@query("stream_running_f1", "SELECT event_type AS key, count(*) AS n, CAST(sum(CASE WHEN value >= 50 THEN 1 ELSE 0 END) AS BIGINT) AS correct FROM events GROUP BY 1")
def stream_running_f1(spark, sf_dir):
    """Running totals by event type of a rule that calls every value high."""
    rows = _stream(spark, sf_dir).select(F.col("event_type").alias("key"), F.when(F.col("value") >= 50, "high").otherwise("low").alias("truth"), F.lit("high").alias("pred"))
    out = ev.drain(ev.running_score(rows), "running", "update")
    return out.groupBy("key").agg(F.max("n").alias("n"), F.max_by("correct", "n").alias("correct"))
