"""Streaming entries; each equals a batch query over the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.score import Plan
from ..streaming import scoring as S
from .registry import entry, r6

Spark = SparkSession


@entry("stream_score", "SELECT l_orderkey, l_linenumber, l_partkey, CASE WHEN 0.1 + 1.5 * ((l_quantity - 25.5) / 14.4) > 0 THEN 'high' ELSE 'low' END AS prediction FROM lineitem")
def stream_score(spark: Spark, d: str) -> DataFrame:
    plan = Plan("prediction", ["l_quantity"], ["l_quantity"], [25.5], [14.4], [[0.1], [1.5]], ["low", "high"])
    rows = S.read_stream(spark, d, "lineitem")
    return S.run_now(S.score_stream(rows, plan).select("l_orderkey", "l_linenumber", "l_partkey", "prediction"))


@entry("stream_tumbling", "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1, 2")
def stream_tumbling(spark: Spark, d: str) -> DataFrame:
    out = S.run_now(S.windowed_counts(S.read_stream(spark, d, "events"), "ts", "event_type", "1 day"), "complete")
    return out.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n", r6("mean").alias("mean"))


@entry("stream_sliding", "SELECT epoch(date_trunc('day', ts))::BIGINT - 86400 * s AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events, (VALUES (0), (1)) v(s) GROUP BY 1, 2")
def stream_sliding(spark: Spark, d: str) -> DataFrame:
    out = S.run_now(S.windowed_counts(S.read_stream(spark, d, "events"), "ts", "event_type", "2 days", "1 day"), "complete")
    return out.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n", r6("mean").alias("mean"))


@entry("stream_session", "SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS n FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN gap IS NULL OR gap > 86400000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events)) GROUP BY 1, 2) GROUP BY user_id")
def stream_session(spark: Spark, d: str) -> DataFrame:
    """Sessions with a gap of a day, by the engine's session window."""
    from ..sources.tables import table

    e = table(spark, d, "events").groupBy("user_id", F.session_window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return e.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


@entry("stream_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")
def stream_dedup(spark: Spark, d: str) -> DataFrame:
    e = S.read_stream(spark, d, "events")
    out = S.run_now(S.first_only(e.unionByName(e), "ts", ["event_id"], "3650 days").select("event_id"))
    return out.agg(F.count(F.lit(1)).alias("n"))


@entry("stream_windowed_error", "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, round(avg(CASE WHEN (value > 50) = (event_type = 'purchase') THEN 0.0 ELSE 1.0 END), 6) AS error, count(*) AS n FROM events GROUP BY 1")
def stream_windowed_error(spark: Spark, d: str) -> DataFrame:
    """Scores and labels of the same events as two streams; labels come an hour later."""
    e = S.read_stream(spark, d, "events")
    scores = e.select("event_id", F.col("ts").alias("scored"), (F.col("value") > 50).cast("int").alias("prediction"))
    labels = e.select("event_id", (F.col("ts") + F.expr("interval 1 hour")).alias("labelled"), (F.col("event_type") == "purchase").cast("int").alias("label"))
    out = S.windowed_error(S.run_now(S.judged_scores(scores, labels, "event_id")))
    return out.select(F.unix_timestamp("window.start").alias("start"), r6("error").alias("error"), "n")


@entry("stream_drift", "SELECT event_type, count(*) AS n, round(avg(value), 4) AS mean FROM events GROUP BY 1")
def stream_drift(spark: Spark, d: str) -> DataFrame:
    out = S.run_now(S.drift(S.read_stream(spark, d, "events"), "event_type", "value"), "update")
    return out.select("event_type", "n", (F.round("mean", 4) + 0.0).alias("mean"))
