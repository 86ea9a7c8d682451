"""Intermediate tables in the folder that the driver and all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a temporary folder on a local master and an error on a cluster."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.conf.get("spark.master", "")
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        folder = shared_folder.own = getattr(shared_folder, "own", None) or "file://" + tempfile.mkdtemp(prefix="cohort_engine_")
    return folder.rstrip("/")


def shared_write(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: a short lineage that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cohorts/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what ``shared_write`` wrote, once nothing reads it any more."""
    path = getattr(df, "written_at", None)
    if path:
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def fits(df: DataFrame, most: int) -> bool:
    """Whether ``df`` has at most ``most`` rows; reads no more than that."""
    return df.limit(most + 1).count() <= most


def spread(df: DataFrame) -> DataFrame:
    """``df`` dealt over the cores if it has fewer partitions than they are (one small file is one task); a large input stays as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df
