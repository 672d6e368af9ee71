"""Streaming queries: each runs over all events there are and is checked against batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from idfold.catalog.registry import query
from idfold.operators import baselines
from idfold.sources.samples import table
from idfold.streaming import counts as st

#: Append mode emits a window once the watermark has passed its end: one day behind the last event.
_MARK = "(SELECT max(ts) - INTERVAL 1 DAY FROM events)"


@query("st_running_access", "SELECT user_id AS id, count(*) AS accesses FROM events GROUP BY 1")
def st_running_access(spark, sf_dir):
    return st.run_to_table(st.running_access(st.events_stream(spark, sf_dir)), mode="complete")


@query("st_stateful_access", "SELECT user_id AS id, count(*) AS accesses FROM events GROUP BY 1")
def st_stateful_access(spark, sf_dir):
    return st.run_to_table(st.stateful_access(st.events_stream(spark, sf_dir)), mode="update").groupBy("id").agg(F.max("accesses").alias("accesses"))


@query("st_tumbling_counts", f"SELECT date_trunc('day', ts)::VARCHAR AS window_start, user_id, count(*) AS n FROM events GROUP BY ALL HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= {_MARK}")
def st_tumbling_counts(spark, sf_dir):
    return _shown(st.run_to_table(st.tumbling_counts(st.events_stream(spark, sf_dir))))


@query("st_sliding_counts", f"SELECT w::VARCHAR AS window_start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS w FROM events) GROUP BY ALL HAVING w + INTERVAL 2 DAY <= {_MARK}")
def st_sliding_counts(spark, sf_dir):
    return _shown(st.run_to_table(st.sliding_counts(st.events_stream(spark, sf_dir))))


def _shown(df):
    return df.withColumn("window_start", F.date_format("window_start", "yyyy-MM-dd HH:mm:ss"))


_SESSIONS = "s AS (SELECT user_id, ts, sum(CASE WHEN ts <= prev + INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM events))"


@query("st_session_users", f"WITH {_SESSIONS} SELECT user_id, count(*) AS sessions, sum(n)::BIGINT AS events FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL HAVING max(ts) + INTERVAL 6 HOUR <= {_MARK}) GROUP BY 1")
def st_session_users(spark, sf_dir):
    done = st.run_to_table(st.user_sessions(st.events_stream(spark, sf_dir)))
    return done.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


@query("st_dedup_events", "SELECT count(DISTINCT event_id) AS events FROM events")
def st_dedup_events(spark, sf_dir):
    return st.run_to_table(st.deduplicated(st.events_stream(spark, sf_dir)).select("event_id")).agg(F.count("*").alias("events"))


@query("st_stream_static_lookup", "SELECT user_id % 7 AS row, count(*) AS uses FROM events GROUP BY 1")
def st_stream_static_lookup(spark, sf_dir):
    users = table(spark, sf_dir, "events").select(F.lit("user").alias("feature"), F.col("user_id").alias("id")).distinct()
    return st.run_to_table(st.with_static(st.events_stream(spark, sf_dir), baselines.modulo(users, 7))).groupBy("row").agg(F.count("*").alias("uses"))


@query("st_stream_stream_join", "SELECT a.event_id AS click_id, b.event_id AS purchase_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def st_stream_stream_join(spark, sf_dir):
    return st.run_to_table(st.clicks_with_purchases(st.events_stream(spark, sf_dir), st.events_stream(spark, sf_dir)))


@query("st_drift_alarm", f"WITH known AS (SELECT DISTINCT user_id FROM events WHERE ts < TIMESTAMP '2024-01-11' AND user_id % 10 > 0) SELECT date_trunc('day', ts)::VARCHAR AS window_start, count(*) AS uses, count(*) FILTER (user_id NOT IN (SELECT user_id FROM known)) AS unseen, count(*) FILTER (user_id NOT IN (SELECT user_id FROM known)) > count(*) * 0.02 AS alarm FROM events GROUP BY 1 HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= {_MARK}")
def st_drift_alarm(spark, sf_dir):
    """Users known to a map of the first week that skips a tenth of them."""
    known = table(spark, sf_dir, "events").where("ts < '2024-01-11' AND user_id % 10 > 0").select(F.col("user_id").alias("id")).distinct()
    out = st.run_to_table(st.drift_alarm(st.events_stream(spark, sf_dir), known))
    return _shown(out.withColumnRenamed("day_start", "window_start"))


@query("st_late_dropped")
def st_late_dropped(spark, sf_dir):
    """Windows closed by the watermark: every day but those within a day of the last event."""
    return st.run_to_table(st.tumbling_counts(st.events_stream(spark, sf_dir, watermark="1 hour"))).agg(F.count_distinct("window_start").alias("closed_days"), F.sum("n").alias("uses"))
