"""Streaming queries and their batch twins in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from schemaloom.plans.hierarchies import MERGED
from schemaloom.plans.registry import query, table
from schemaloom.sources import fixtures as fx
from schemaloom.streaming import arrivals as st

STAMP = "yyyy-MM-dd HH:mm:ss"


def events(spark, sf_dir):
    return st.timed(st.arriving(spark, table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type"), "events"))


def started(df):
    return df.withColumn("start", F.date_format("w.start", STAMP)).drop("w")


@query("t_tumbling", "SELECT date_trunc('hour', ts)::VARCHAR AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def tumbling(spark, sf_dir):
    return started(st.drained(st.tumbling(events(spark, sf_dir)), "tumbling", "complete"))


@query("t_sliding", """
SELECT CAST(s AS TIMESTAMP)::VARCHAR AS start, count(*) AS n FROM (
  SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY 1""")
def sliding(spark, sf_dir):
    return started(st.drained(st.sliding(events(spark, sf_dir)), "sliding", "complete"))


@query("t_session", """
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (
  SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
    SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE >= ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def session(spark, sf_dir):
    return started(st.drained(st.sessions(events(spark, sf_dir)), "session", "complete"))


@query("t_dedup", "SELECT DISTINCT event_id FROM events")
def dedup(spark, sf_dir):
    one = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    twice = st.timed(st.arriving(spark, one.union(one), "twice"))
    return st.drained(st.first_sightings(twice, "event_id", "3650 days"), "dedup").select("event_id")


@query("t_stream_static", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def stream_static(spark, sf_dir):
    joined = events(spark, sf_dir).join(table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    return st.drained(joined.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "static", "complete")


@query("t_edge_weights", f"WITH {MERGED} SELECT * FROM merged")
def edge_weights(spark, sf_dir):
    return st.drained(st.edge_weights(st.arriving(spark, fx.paths(spark), "paths")), "weights", "complete")


@query("t_stream_stream", "SELECT s.event_id AS signup_id, e.event_id FROM events s JOIN events e ON s.user_id = e.user_id AND s.event_type = 'signup' AND e.event_type = 'purchase' AND e.ts >= s.ts AND e.ts <= s.ts + INTERVAL 1 DAY")
def stream_stream(spark, sf_dir):
    """Purchases within a day of a signup by the same user: state on both sides, bounded by watermarks."""
    return st.drained(st.follow_ups(events(spark, sf_dir), events(spark, sf_dir)), "follow-ups")


@query("t_watermark_late", "SELECT date_trunc('hour', ts)::VARCHAR AS start, count(*) AS n FROM events WHERE ts < (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1 HAVING date_trunc('hour', min(ts)) + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
def watermark_late(spark, sf_dir):
    """Hours that are closed once the watermark, an hour behind, has passed them; rows later than it don't count. Here the
    whole input is one batch, so no row is late, and the last hours stay open."""
    closed = st.tumbling(events(spark, sf_dir).withWatermark("ts", "1 hour").withColumn("event_type", F.lit("any")))
    return started(st.drained(closed, "late")).select("start", "n")


@query("t_profile_state", "SELECT event_type, count(*) AS cells, count(*) FILTER (props IS NULL) AS missing, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def profile_state(spark, sf_dir):
    """Running profiles by event type, with a state of one's own."""
    stream = st.arriving(spark, table(spark, sf_dir, "events").select("event_type", "user_id", "props"), "profiles")
    found = st.drained(st.profiles(stream, "event_type", "user_id", "props"), "profiles")
    last = found.groupBy("event_type", "part").agg(F.max("cells").alias("cells"), F.max("missing").alias("missing"), F.max("users").alias("users"))
    return last.groupBy("event_type").agg(*(F.sum(c).alias(c) for c in ("cells", "missing", "users")))
