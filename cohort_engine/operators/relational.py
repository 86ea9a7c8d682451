"""Joins and reports around cohorts: assignments as of a time, conversions in an interval, changes between snapshots, grouped recalls."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(events: DataFrame, versions: DataFrame, key: str, time: str, valid_from: str, value: str) -> DataFrame:
    """``events`` plus ``value`` of the latest of ``versions`` (key, valid_from, value) at or before their time, null if there is none.

    One union and one window by key: no range join, and every event stays one row.
    """
    names = events.columns
    e = events.select(F.col(key).alias("_key"), F.col(time).alias("_time"), F.lit(1).alias("_side"), F.struct(*names).alias("_row"), F.lit(None).cast(dict(versions.dtypes)[value]).alias("_value"))
    row = e.schema["_row"].dataType
    v = versions.select(F.col(key).alias("_key"), F.col(valid_from).alias("_time"), F.lit(0).alias("_side"), F.lit(None).cast(row).alias("_row"), F.col(value).alias("_value"))
    w = Window.partitionBy("_key").orderBy("_time", "_side").rowsBetween(Window.unboundedPreceding, 0)
    # versions are wrapped, so that a version whose value is null still hides the one before
    last = F.last(F.when(F.col("_side") == 0, F.struct("_value")), ignorenulls=True).over(w)
    return e.unionByName(v).withColumn("_last", last).where("_side = 1").select("_row.*", F.col("_last._value").alias(value))


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs (left columns as l_*, right as r_*) of one key with right in [left, left + seconds].

    Both sides meet on (key, slot of ``seconds``), a left row in its own slot and the next, so a key's
    whole history never meets itself.
    """
    slot = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)
    a = left.select(*[F.col(c).alias(f"l_{c}") for c in left.columns]).withColumn("_slot", F.explode(F.array(slot(f"l_{time}"), slot(f"l_{time}") + 1)))
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("_slot", slot(f"r_{time}"))
    near = (F.col(f"r_{time}") >= F.col(f"l_{time}")) & (F.col(f"r_{time}") <= F.col(f"l_{time}") + F.expr(f"interval {seconds} seconds"))
    return a.join(b, (F.col(f"l_{key}") == F.col(f"r_{key}")) & (a["_slot"] == b["_slot"]) & near).drop("_slot")


def snapshot_changes(old: DataFrame, new: DataFrame) -> DataFrame:
    """change, users: how many users joined, left, moved or stayed between two assignments."""
    j = old.select("user_id", F.col("cohort_id").alias("a")).join(new.select("user_id", F.col("cohort_id").alias("b")), "user_id", "full")
    change = F.when(F.col("a").isNull(), "joined").when(F.col("b").isNull(), "left").when(F.col("a") == F.col("b"), "stayed").otherwise("moved")
    return j.groupBy(change.alias("change")).agg(F.count("*").alias("users"))


def recall_rollup(counts: DataFrame, kind) -> DataFrame:
    """kind, campaign_id, recall, campaigns by campaign, by kind of campaign and over all: pooled recall at every level."""
    g = counts.withColumn("kind", kind).rollup("kind", "campaign_id")
    return g.agg((F.sum("tp") / F.nullif(F.sum(F.col("tp") + F.col("fn")), F.lit(0))).alias("recall"), F.count("*").alias("campaigns"), F.grouping_id().alias("level"))


def method_pivot(table: DataFrame, measure: str = "macro_recall") -> DataFrame:
    """A row a method, a column a length."""
    lengths = sorted(r[0] for r in table.select("length").distinct().collect())  # a handful
    return table.groupBy("method").pivot("length", lengths).agg(F.max(measure)).withColumnsRenamed({str(x): f"length_{x}" for x in lengths})
