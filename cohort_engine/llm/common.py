"""Shared helpers: tables, shared-folder materialisation, broadcast checks, components."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but the six ASCII blanks.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share (spark.checkpoint.dir). Where none is set, a temporary one on a local master and an error on a cluster."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.conf.get("spark.master", "")
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        folder = getattr(shared_dir, "own", None)
        if folder is None:
            folder = shared_dir.own = "file://" + tempfile.mkdtemp(prefix="cohort_engine_")
    return folder.rstrip("/")


def work_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/work/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: short lineage, survives lost executors."""
    spark = df.sparkSession
    path = work_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cohort_path = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what ``materialise`` wrote, once nothing reads it any more."""
    path = getattr(df, "_cohort_path", None)
    if path:
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def small(df: DataFrame, max_rows: int) -> bool:
    """Whether ``df`` has at most ``max_rows`` rows; reads no more than that."""
    return df.limit(max_rows + 1).count() <= max_rows


def join_small(big: DataFrame, side: DataFrame, on, how: str, max_rows: int) -> DataFrame:
    """Broadcast ``side`` only if its counted rows are within ``max_rows``; else an ordinary shuffle join."""
    return big.join(F.broadcast(side) if small(side, max_rows) else side, on, how)


def keyed(docs: DataFrame, name: str = "_key") -> DataFrame:
    """``docs`` plus a long column ``name`` that is another for every row: the doc_id where it is not null and on one row only.

    Other rows, if there are any (``.odd`` of the result), are written once and get numbers below all ids.
    """
    d = docs.withColumn(name, F.col("doc_id").cast("long"))
    odd = materialise(d.groupBy(name).count().where(F.col(name).isNull() | (F.col("count") > 1)).select(F.col(name).alias("_odd")), "odd_ids")
    d.odd = bool(odd.limit(1).count())
    if not d.odd:
        return d
    low = F.lit(min(0, d.agg(F.min(name)).collect()[0][0] or 0))
    same = F.col(name).eqNullSafe(F.col("_odd"))
    own = materialise(d.join(odd, same, "left_semi").withColumn(name, low - 1 - F.monotonically_increasing_id()), "odd_rows")
    out = d.join(odd, same, "left_anti").unionByName(own)
    out.odd = True
    return out


def give_back() -> None:
    """Return this Python worker's freed memory to the system: workers outlive their tasks and share the executor's memory."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def lean(f: Callable) -> Callable:
    """``f`` on one group, then ``give_back``."""

    @wraps(f)
    def run(g: pd.DataFrame) -> pd.DataFrame:
        out = f(g)
        give_back()
        return out

    return run


_KINDS = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string(), "binary": pa.binary(), "array<int>": pa.list_(pa.int32())}


def over_texts(docs: DataFrame, run: Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]], schema: str, rows: int = 1000) -> DataFrame:
    """``run`` over slices of few documents: the texts and results of one slice are in a worker's memory together."""
    arrow = pa.schema([(name, _KINDS[kind]) for name, kind in (c.split() for c in schema.split(", "))])

    def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for a in range(0, b.num_rows, rows):
                yield b.slice(a, rows).to_pandas(integer_object_nulls=True)
            give_back()

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for out in run(slices(batches)):
            yield pa.RecordBatch.from_pandas(out, schema=arrow, preserve_index=False)
        give_back()

    return docs.mapInArrow(go, schema)


def hash_longs(x: np.ndarray, salt=0) -> np.ndarray:
    """A 64-bit mix of int64 keys with a salt; the same in ``BitFilter.of`` and in Python scans."""
    h = (x.view(np.uint64) ^ (np.asarray(salt, np.uint64) * np.uint64(0x9E3779B97F4A7C15))) * np.uint64(0xC2B2AE3D27D4EB4F)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0x165667B19E3779F9)
    return (h ^ (h >> np.uint64(32))).view(np.int64)


class BitFilter:
    """A bit for each hash bucket of a set of 64-bit keys; never misses one, may pass others."""

    def __init__(self, words: np.ndarray):
        self.words = words

    @classmethod
    def of(cls, keys: DataFrame, columns, max_bits: int = 1 << 30, per_key: int = 16) -> BitFilter:
        """A filter of one long column, or of (salt, long); its size follows the keys up to ``max_bits``, whatever the data.

        Filled on the executors in blocks of 64 Ki bits.
        """
        names = [columns] if isinstance(columns, str) else list(columns)
        n = max(keys.count(), 1)
        bits = 1 << min(max_bits.bit_length() - 1, max(16, (per_key * n - 1).bit_length()))

        def places(batches):
            for b in batches:
                salt = b[names[0]].to_numpy(np.int64).view(np.uint64) if len(names) > 1 else 0
                at = hash_longs(b[names[-1]].to_numpy(np.int64), salt) & np.int64(bits - 1)
                yield pd.DataFrame({"at": (at & 0xFFFF).astype(np.int32), "block": (at >> 16).astype(np.int32)})

        def fill(g: pd.DataFrame) -> pd.DataFrame:
            x = np.zeros(1 << 16, dtype=np.uint8)
            x[g["at"].to_numpy()] = 1
            return pd.DataFrame({"block": [g["block"].iloc[0]], "bits": [np.packbits(x, bitorder="little").tobytes()]})

        out = np.zeros(bits // 8, dtype=np.uint8).reshape(-1, 8192)
        filled = keys.select(*names).mapInPandas(places, "at int, block int").groupBy("block").applyInPandas(fill, "block int, bits binary")
        for r in filled.toLocalIterator():
            out[r["block"]] = np.frombuffer(r["bits"], dtype=np.uint8)
        return cls(out.ravel())

    def has(self, hashed: np.ndarray) -> np.ndarray:
        """For ``hash_longs`` of keys."""
        at = hashed & np.int64(8 * len(self.words) - 1)
        return (self.words[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1

    def keep(self, df: DataFrame, column: str) -> DataFrame:
        """Rows of ``df`` whose key may be in the set."""
        shared = df.sparkSession.sparkContext.broadcast(self.words)

        def run(batches):
            f = BitFilter(shared.value)
            for b in batches:
                yield b.filter(_mask(f.has(hash_longs(b.column(column).to_numpy()))))

        return df.mapInArrow(run, df.schema)


def _mask(ok):
    return pa.array(ok)


def hex_order(seed: int, *cols):
    """A seeded pseudo-random order that other SQL engines can repeat."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in cols]))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable id of each vertex of ``edges(a, b)``: columns ``id, component``.

    Alternating large-star and small-star contraction; each round is a few grouped minima, so a
    vertex with very many neighbours is aggregated map-side and never gathered. Empty edges give
    no rows. Raises if it has not settled after ``max_rounds`` (it halves depths, so 60 is far off).
    """
    def tidy(df):
        return df.where("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()

    now = materialise(tidy(edges), "edges")
    for _ in range(max_rounds):
        both = now.union(now.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = tidy(large)
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small_star = tidy(large.join(low, "a").select("b", "m").toDF("a", "b").union(low.toDF("a", "b")))
        after = materialise(small_star, "edges")
        moved = after.exceptAll(now).limit(1).count() + (0 if after.count() == now.count() else 1)
        discard(now)
        now = after
        if not moved:
            out = now.groupBy("a").agg(F.min("b").alias("component")).withColumnRenamed("a", "id")
            roots = now.select(F.col("b").alias("id")).distinct().withColumn("component", F.col("id"))
            return out.unionByName(roots.join(out, "id", "left_anti"))
    raise RuntimeError("components did not settle")
