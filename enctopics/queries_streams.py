"""Queries that read a table as a stream; their SQL is what the same rows give at once."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from enctopics.registry import OCC, query
from enctopics.sources.tables import table
from enctopics.streaming import events as ev
from enctopics.streaming import stream

_HOUR = "epoch_us(ts) // 3600000000"


def _events(spark: SparkSession, d: str) -> DataFrame:
    return ev.timed(ev.arriving(spark, f"{d}/events.parquet"))


@query("stream_windows", f"SELECT CAST({_HOUR} AS BIGINT) AS hour, event_type, count(*) AS n FROM events WHERE ({_HOUR} + 1) * 3600000 <= (SELECT max(epoch_us(ts)) // 1000 - 3600000 FROM events) GROUP BY ALL")
def stream_windows(spark: SparkSession, d: str) -> DataFrame:
    """Hours that the watermark has passed."""
    w = ev.appended(ev.closed_windows(_events(spark, d), "event_type"))
    return w.select(F.floor(F.unix_micros("start") / 3_600_000_000).cast("long").alias("hour"), "event_type", "n")


@query("stream_once", "SELECT DISTINCT user_id, event_type FROM events")
def stream_once(spark: SparkSession, d: str) -> DataFrame:
    return ev.appended(ev.once(_events(spark, d), "user_id", "event_type").select("user_id", "event_type"))


@query("stream_static_join", "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark: SparkSession, d: str) -> DataFrame:
    side = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return ev.appended(_events(spark, d).select("event_id", "user_id").join(side, "user_id").select("event_id", "user_id", "c_mktsegment"))


@query("stream_stream_join", "SELECT a.user_id, a.event_id AS first, b.event_id AS next FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def stream_stream_join(spark: SparkSession, d: str) -> DataFrame:
    return ev.appended(ev.followed(_events(spark, d), _events(spark, d), "user_id", "event_id", "30 minutes"))


@query("stream_token_stats", f"WITH {OCC} SELECT tok, count(*) AS tf FROM occ GROUP BY tok")
def stream_token_stats(spark: SparkSession, d: str) -> DataFrame:
    return ev.complete(stream.token_stats(ev.arriving(spark, f"{d}/documents.parquet")))
