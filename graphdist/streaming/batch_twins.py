"""Window counts of event edges; the same functions serve a stream (with a watermark) and a table."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def _late(events: DataFrame) -> DataFrame:
    """Streams get the watermark, for which ``ts`` must carry a time zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "10 minutes") if events.isStreaming else events


def tumbling(events: DataFrame) -> DataFrame:
    w = F.window("ts", "1 hour")
    return _late(events).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame) -> DataFrame:
    w = F.window("ts", "1 hour", "15 minutes")
    return _late(events).filter("event_type = 'error'").groupBy(w).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def session(events: DataFrame) -> DataFrame:
    w = F.session_window("ts", "30 minutes")
    return _late(events).groupBy(w, "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


SQL = {
    "tumbling": "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "sliding": """SELECT time_bucket(INTERVAL 15 MINUTES, ts) - to_minutes(15 * k) AS start, count(*) AS n FROM events, (SELECT unnest([0, 1, 2, 3]) AS k)
      WHERE event_type = 'error' GROUP BY 1""",
    "session": """SELECT user_id, min(ts) AS start, count(*) AS n FROM (
        SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (
          SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS fresh FROM events))
      GROUP BY user_id, k""",
}
