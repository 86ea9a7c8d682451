"""Structured Streaming: retrieval, incremental vectors, windows behind an exact K gate, sessions, conversions, new users."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.campaigns import retrieve


def timed(events: DataFrame, watermark: str) -> DataFrame:
    """Watermarks take timestamps with a zone only; the tables' have none and are read in the session's."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def stream_retrieve(impressions: DataFrame, assign: DataFrame, cohorts: DataFrame) -> DataFrame:
    """Stream-static: each impression's candidate campaigns."""
    return retrieve(impressions, assign, cohorts)


def stream_vectors(events: DataFrame, watermark: str = "10 minutes") -> DataFrame:
    """Running user vectors (update mode) of events that are not repeated within the watermark."""
    e = timed(events, watermark).dropDuplicatesWithinWatermark(["event_id"])
    return e.groupBy("user_id", F.col("event_type").alias("feature")).agg(F.sum(F.col("value").cast("decimal(18,4)")).cast("double").alias("weight"))


def cohort_windows(events: DataFrame, assign: DataFrame, k: int, length: str = "1 hour", slide: str | None = None, watermark: str = "10 minutes") -> DataFrame:
    """Counts by cohort in tumbling (or, with ``slide``, sliding) windows, released only if exactly counted ``k`` or more distinct users are in the window.

    Two aggregations (append mode): by user, then by cohort, so distinct users are counted and not
    estimated; the watermark bounds what is kept.
    """
    e = timed(events, watermark).join(assign, "user_id")
    each = e.groupBy(F.window("ts", length, slide or length).alias("w"), "cohort_id", "user_id").agg(F.count("*").alias("n"))
    n = each.groupBy("w", "cohort_id").agg(F.sum("n").alias("events"), F.count("*").alias("users"))
    return n.where(F.col("users") >= k).select(F.col("w.start").alias("start"), "cohort_id", "events", "users")


def user_sessions(events: DataFrame, gap: str = "30 minutes", watermark: str = "10 minutes") -> DataFrame:
    """user_id, start, end, events: runs of a user's events with no gap of ``gap``."""
    s = timed(events, watermark).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("events"))
    return s.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "events")


def converted_impressions(impressions: DataFrame, conversions: DataFrame, within: str = "1 hour", watermark: str = "10 minutes") -> DataFrame:
    """impression_id, conversion_id of one user, the conversion at most ``within`` after the impression: a stream-stream interval join."""
    i = timed(impressions, watermark).select(F.col("event_id").alias("impression_id"), F.col("user_id").alias("iu"), F.col("ts").alias("it"))
    c = timed(conversions, watermark).select(F.col("event_id").alias("conversion_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    near = (F.col("iu") == F.col("cu")) & (F.col("ct") >= F.col("it")) & (F.col("ct") <= F.col("it") + F.expr(f"interval {within}"))
    return i.join(c, near).select("impression_id", "conversion_id")


def assign_batches(assign: Callable[[DataFrame], DataFrame], path: str) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: each micro-batch's new vectors (user_id, feature, weight) to cohorts, one folder a batch, so a repeated batch overwrites its own rows."""
    def run(batch: DataFrame, number: int) -> None:
        assign(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return run


def late_rows(query) -> int:
    """Rows a finished streaming query dropped as later than its watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
