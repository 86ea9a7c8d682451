"""Sources and sinks, joins by time, SQL functions."""

import pytest
from pyspark.sql import functions as F

from cohort_engine.functions import sql
from cohort_engine.operators import campaigns, features, hashing, relational
from cohort_engine.sources import tables

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv", "text"])
def test_vectors_of_every_format(spark, tmp_path, fmt):
    v = spark.createDataFrame([(1, "a:b", 0.5), (1, "c", 2.0), (7, "d", 1e-3)], "user_id long, feature string, weight double")
    path = str(tmp_path / fmt)
    if fmt == "text":
        line = F.concat_ws(" ", F.col("user_id").cast("string"), F.array_join(F.collect_list(F.concat_ws(":", "feature", F.col("weight").cast("string"))), " "))
        v.groupBy("user_id").agg(line.alias("value")).select("value").write.text(path)
    else:
        (v.write.option("header", "true").csv(path) if fmt == "csv" else v.write.format(fmt).save(path))
    assert tables.read_vectors(spark, path, fmt).exceptAll(v).count() == 0 and tables.read_vectors(spark, path, fmt).count() == 3


def test_snapshots_are_written_once(spark, tmp_path):
    a = spark.createDataFrame([(1, 5)], "user_id long, cohort_id long")
    tables.write_assignments(a, str(tmp_path), "one")
    with pytest.raises(Exception):
        tables.write_assignments(a, str(tmp_path), "one")
    assert spark.read.parquet(str(tmp_path)).where("snapshot = 'one'").count() == 1


def test_scan_reads_only_what_is_asked(spark):
    plan = tables.read_table(spark, SF, "lineitem").where("l_quantity > 40").select("l_orderkey")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(l_quantity,40.0)" in plan and "l_comment" not in plan and "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in plan


def test_asof_takes_the_latest_and_keeps_null_versions(spark):
    e = spark.createDataFrame([(1, 5, "x"), (1, 10, "y"), (1, 1, "w"), (2, 9, "z")], "u long, t long, tag string")
    v = spark.createDataFrame([(1, 2, "a"), (1, 10, None)], "u long, since long, c string")
    got = {r["tag"]: r["c"] for r in relational.asof_join(e, v, "u", "t", "since", "c").collect()}
    assert got == {"x": "a", "y": None, "w": None, "z": None}


def test_changes_between_snapshots(spark):
    a = spark.createDataFrame([(1, "x"), (2, "x"), (3, "y")], "user_id long, cohort_id string")
    b = spark.createDataFrame([(1, "x"), (2, "y"), (4, "y")], "user_id long, cohort_id string")
    assert {r["change"]: r["users"] for r in relational.snapshot_changes(a, b).collect()} == {"stayed": 1, "moved": 1, "left": 1, "joined": 1}


def test_sql_functions_without_python(spark):
    names = sql.register(spark)
    assert "minmax_kernel" in names
    one = spark.sql("select jaccard_sets(array('a','b'), array('b','c')) as j, minmax_kernel(map('a',1D,'b',2D), map('b',1D,'c',3D), 1D) as m, minmax_kernel(map('a',1D), map('a',1D), 2D) as s")
    r = one.collect()[0]
    assert abs(r["j"] - 1 / 3) < 1e-12 and abs(r["m"] - 1 / 6) < 1e-12 and r["s"] == 1.0
    assert "Python" not in one._jdf.queryExecution().executedPlan().toString()
    v = features.baskets(spark, SF)
    s = sql.CohortSession(spark, spark.createDataFrame([(1, 2)], "user_id long, cohort_id long"), campaigns.identity_by(spark.createDataFrame([(1, 2)], "user_id long, cohort_id long"), v, "share"))
    assert s.sql("select count(*) from cohort_identity join cohorts using (cohort_id)").collect()[0][0] == v.where("user_id = 1").count()


def test_table_function_equals_the_signature(spark):
    sql.register(spark)
    v = features.baskets(spark, SF).where("user_id < 5")
    hashing.packed(v).createOrReplaceTempView("some_packed")
    got = spark.sql("select user_id, s.slot, s.code from some_packed, lateral signature_slots(code, weight, 4, 1.2D, 7) s")
    want = hashing.signatures(v, "weighted", 4, 1.2, 7).select("user_id", F.posexplode("sig").alias("p", "code")).selectExpr("user_id", "p + 1 as slot", "code")
    assert got.exceptAll(want).count() == 0 and got.count() == want.count() > 0
