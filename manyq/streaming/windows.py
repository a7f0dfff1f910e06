"""Windows over events, the same expressions on streams and on tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manyq.sources.tables import load
from manyq.streaming import requests


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"))


def sliding(events: DataFrame, size: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", size, slide)).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def _events(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events", "event_id", "user_id", "event_type", "ts").withColumn("ts", F.col("ts").cast("timestamp"))


def _co_active(s: SparkSession, d: str) -> DataFrame:
    return requests.co_activity_counts(_events(s, d))


_us = lambda c: F.unix_micros(c)
QUERIES = {
    "stream_co_activity": (_co_active, "WITH e AS (SELECT user_id, event_type, epoch_us(ts) // 3600000000 AS h FROM events) SELECT a.user_id AS src, b.user_id AS dst, count(DISTINCT a.h) AS windows, count(*) AS n FROM e a JOIN e b ON a.h = b.h AND a.event_type = b.event_type AND a.user_id <> b.user_id GROUP BY 1, 2"),
    "stream_matched": (
        lambda s, d: requests.matched_requests(_events(s, d).where("event_id % 7 = 0").select(F.col("user_id").alias("src"), "ts"), _events(s, d)).select("src", _us("asked").alias("asked"), "event_id"),
        "SELECT r.user_id AS src, epoch_us(r.ts) AS asked, e.event_id FROM events r JOIN events e ON e.user_id = r.user_id AND epoch_us(e.ts) <= epoch_us(r.ts) AND epoch_us(e.ts) >= epoch_us(r.ts) - 300000000 WHERE r.event_id % 7 = 0",
    ),
    "stream_tumbling": (lambda s, d: tumbling(_events(s, d)).select(_us("window.start").alias("start"), "event_type", "n"), "SELECT (epoch_us(ts) // 3600000000) * 3600000000 AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "stream_sliding": (lambda s, d: sliding(_events(s, d)).select(_us("window.start").alias("start"), "n"), "SELECT (epoch_us(ts) // 3600000000 - k) * 3600000000 AS start, count(*) AS n FROM events, range(2) r(k) GROUP BY 1"),
    "stream_session": (
        lambda s, d: sessions(_events(s, d)).select("user_id", _us("session_window.start").alias("start"), "n"),
        """WITH e AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t RANGE UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, min(t) AS start, count(*) AS n FROM s GROUP BY user_id, k""",
    ),
}
