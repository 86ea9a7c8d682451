"""Streams run to their end, against the same rows in batch."""

from datetime import timedelta

import pytest
from pyspark.sql import functions as F

from cohort_engine.operators import features, mode_split, relational
from cohort_engine.sources.tables import read_table
from cohort_engine.streaming import serving

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    """The events as a table, and as a stream of several files in which every event comes twice."""
    table = read_table(spark, SF, "events")
    path = str(tmp_path_factory.mktemp("stream") / "events")
    table.union(table).repartition(3).write.parquet(path)
    return table, lambda: spark.readStream.schema(table.schema).parquet(path)


def finished(spark, df, name, mode):
    df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return sorted(tuple(r) for r in spark.table(name).collect())


def cohorts(spark):
    return spark.range(2000).select(F.col("id").alias("user_id"), (F.col("id") % 3).cast("string").alias("cohort_id"))


def test_vectors_count_a_repeated_event_once(spark, events):
    table, stream = events
    want = table.groupBy("user_id", "event_type").agg(F.sum(F.col("value").cast("decimal(18,4)")).cast("double"))
    assert finished(spark, serving.stream_vectors(stream()), "vectors", "complete") == sorted(tuple(r) for r in want.collect())


def closed(rows, events, length, watermark):
    """Those windows that a watermark over all events has passed: (start, ...) with an end at or before it."""
    last = events.agg(F.max(F.col("ts").cast("timestamp"))).collect()[0][0]
    return sorted(r for r in rows if r[0] + length <= last - watermark)


@pytest.mark.parametrize("slide", [None, "30 minutes"])
def test_windows_count_users_exactly_and_hold_back_those_below_k(spark, events, slide):
    table, stream = events
    twice, assign, hour = table.union(table), cohorts(spark), timedelta(hours=1)
    got = finished(spark, serving.cohort_windows(stream(), assign, 3, slide=slide), f"windows_{bool(slide)}", "append")
    exact = twice.join(assign, "user_id").groupBy(F.window(F.col("ts").cast("timestamp"), "1 hour", slide or "1 hour").alias("w"), "cohort_id").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("u"))
    every = [(r["w"]["start"], r["cohort_id"], r["n"], r["u"]) for r in exact.collect()]
    want = closed([r for r in every if r[3] >= 3], table, hour, timedelta(minutes=10))
    assert set(got) <= {r for r in every if r[3] >= 3} and set(want) <= set(got) and got and any(r[3] < 3 for r in every)


def test_sessions_equal_batch(spark, events):
    table, stream = events
    got = finished(spark, serving.user_sessions(stream(), "6 hours"), "sessions", "complete")
    want = table.union(table).groupBy(F.session_window(F.col("ts").cast("timestamp"), "6 hours").alias("s"), "user_id").count()
    assert got == sorted((r["user_id"], r["s"]["start"], r["s"]["end"], r["count"]) for r in want.collect())


def test_conversions_in_an_interval_equal_batch(spark, events):
    table, stream = events
    view, buy = F.col("event_type") == "view", F.col("event_type") == "purchase"
    pairs = serving.converted_impressions(stream().where(view), stream().where(buy), "12 hours").distinct()
    got = finished(spark, serving.converted_impressions(stream().where(view), stream().where(buy), "12 hours"), "conversions", "append")
    want = relational.interval_join(table.where(view), table.where(buy), "user_id", "ts", 12 * 3600).select("l_event_id", "r_event_id")
    assert sorted(set(got)) == sorted(tuple(r) for r in want.collect()) and got and len(got) == 4 * len(set(got)) and pairs.isStreaming


def test_new_users_of_a_stream_join_their_cohorts(spark, events, tmp_path):
    v = features.baskets(spark, SF)
    u = v.select("user_id").distinct()
    c = mode_split.mode_split(v, u, k=5, rounds=6)
    src, out = str(tmp_path / "vectors"), str(tmp_path / "out")
    v.write.parquet(src)
    assign = lambda batch: mode_split.assign_new(batch, batch.select("user_id").distinct(), c.split_log)
    q = spark.readStream.schema(v.schema).parquet(src).writeStream.foreachBatch(serving.assign_batches(assign, out)).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.read.parquet(out).select("user_id", "cohort_id").exceptAll(c.assignments).count() == 0 and spark.read.parquet(out).count() == u.count()


def test_late_rows_are_counted(spark, tmp_path):
    path = str(tmp_path / "late")
    row = lambda i, t: spark.createDataFrame([(i, t, 1, "view", 1.0)], "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    schema = row(1, "2024-01-01 00:00:00").schema
    q = None
    for i, t in enumerate(["2024-01-01 12:00:00", "2024-01-01 12:30:00", "2024-01-01 01:00:00", "2024-01-01 13:00:00"]):
        row(i, t).write.mode("append").parquet(path)
        q = serving.user_sessions(spark.readStream.schema(schema).parquet(path), "10 minutes").writeStream.format("noop").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
        q.awaitTermination()
        if i == 2:
            late = serving.late_rows(q)
    assert late == 1 and serving.late_rows(q) == 0


def test_retrieval_equals_batch(spark, events):
    table, stream = events
    hits = spark.createDataFrame([("a", "0", True), ("b", "0", True), ("c", "1", False)], "campaign_id string, cohort_id string, hit boolean")
    shown = lambda e: e.select(F.col("event_id").alias("impression_id"), "user_id")
    got = finished(spark, serving.stream_retrieve(shown(stream()), cohorts(spark), hits), "retrieved", "append")
    assert got == sorted(tuple(r) for r in serving.retrieve(shown(table.union(table)), cohorts(spark), hits).collect()) and got
