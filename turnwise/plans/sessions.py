"""Batch forms of the live harness over the event log."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.io import table
from ..streaming import live
from .common import r6


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.acts(table(spark, sf_dir, "events"))


def session_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = live.session_runs(turns(spark, sf_dir))
    return s.select(F.col("run_id").alias("user_id"), F.unix_micros("session_start").alias("session_start_us"), "n_turns", "has_drift", "has_sql")


def live_ask_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = live.live_metrics(turns(spark, sf_dir))
    return m.select(F.unix_micros("window_start").alias("window_start_us"), "n", r6(F.col("asks") / F.col("n")).alias("ar"))


def live_ask_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = live.live_metrics(turns(spark, sf_dir), "2 days", "1 day")
    return m.select(F.unix_micros("window_start").alias("window_start_us"), "n", "asks")


_E = """
WITH e AS (SELECT user_id, ts, event_type, epoch_us(ts) AS us, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
s AS (SELECT *, sum(CASE WHEN before IS NULL OR us - before > 43200000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e)
"""
QUERIES = {f.__name__: f for f in (session_runs, live_ask_rate, live_ask_sliding)}
ORACLES = {
    "session_runs": _E + "SELECT user_id, min(us) AS session_start_us, count(*) AS n_turns, bool_or(event_type = 'signup') AS has_drift, bool_or(event_type = 'click') AS has_sql FROM s GROUP BY user_id, k",
    "live_ask_rate": "SELECT epoch_us(date_trunc('day', ts)) AS window_start_us, count(*) AS n, round(avg(CAST(event_type = 'view' AS INT)), 6) AS ar FROM events GROUP BY 1",
    "live_ask_sliding": "SELECT epoch_us(date_trunc('day', ts)) - d * 86400000000 AS window_start_us, count(*) AS n, count_if(event_type = 'view') AS asks FROM events, (VALUES (0), (1)) AS t(d) GROUP BY 1",
}
