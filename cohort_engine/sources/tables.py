"""Tables in, assignments out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Long vectors (user_id, feature, weight) from parquet, orc, csv, json or ``id feature:weight ...`` text."""
    schema = "user_id long, feature string, weight double"
    if fmt == "text":
        lines = spark.read.text(path).selectExpr("split(trim(value), ' +') as p")
        items = lines.selectExpr("cast(p[0] as long) as user_id", "explode(slice(p, 2, greatest(size(p) - 1, 0))) as x")
        return items.selectExpr("user_id", "regexp_extract(x, '^(.*):([^:]*)$', 1) as feature", "cast(regexp_extract(x, '^(.*):([^:]*)$', 2) as double) as weight")
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_assignments(df: DataFrame, path: str, snapshot: str) -> None:
    """One directory a snapshot; an existing snapshot is an error, so a write is all or nothing."""
    df.write.parquet(f"{path}/snapshot={snapshot}")


def save_bucketed(df: DataFrame, table: str, buckets: int, key: str = "user_id") -> None:
    """A table bucketed by user, so that later joins on it need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
