"""Sparse user vectors in long form: user_id, feature, weight > 0."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def clean(v: DataFrame) -> DataFrame:
    """Drop null, NaN and non-positive weights; infinite ones are an error; repeated features are summed."""
    w = F.col("weight").cast("double")
    w = F.when(w == float("inf"), F.raise_error(F.lit("infinite weight"))).otherwise(w)
    v = v.select("user_id", F.col("feature").cast("string").alias("feature"), w.alias("weight")).where("weight > 0 and not isnan(weight)")
    return v.groupBy("user_id", "feature").agg(F.sum("weight").alias("weight"))


def sparse_vectors(rows: DataFrame, user: str, feature, weight, how: str = "sum") -> DataFrame:
    """Vectors from fact rows: ``weight`` (a column or number) by user and feature, 'sum', 'max' or 'count'; then cleaned."""
    f = feature if isinstance(feature, Column) else F.col(feature)
    w = (weight if isinstance(weight, Column) else F.col(weight) if isinstance(weight, str) else F.lit(weight)).cast("double")
    out = {"sum": F.sum("w"), "max": F.max("w"), "count": F.count("w").cast("double")}[how].alias("weight")
    d = rows.select(F.col(user).alias("user_id"), f.cast("string").alias("feature"), w.alias("w")).where("w is not null and feature is not null")
    return clean(d.groupBy("user_id", "feature").agg(out))


def planted(v: DataFrame, groups: int, own: float = 0.2) -> DataFrame:
    """Vectors with similar users by construction: user u gets the vector of user u mod ``groups``, plus ``own`` times its own."""
    users = v.select("user_id").distinct()
    base = users.join(v.withColumnRenamed("user_id", "from"), F.col("from") == F.col("user_id") % groups).select("user_id", "feature", "weight")
    return base.unionByName(v.withColumn("weight", F.col("weight") * own)).groupBy("user_id", "feature").agg(F.sum("weight").alias("weight"))


def pack(v: DataFrame) -> DataFrame:
    """user_id, vec: array of (feature, weight) in feature order."""
    return v.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("feature", "weight"))).alias("vec"))


def unpack(p: DataFrame) -> DataFrame:
    return p.select("user_id", F.inline("vec"))


def split_signs(df: DataFrame, key: str, values: str) -> DataFrame:
    """Signed dense vectors to doubled non-negative ones: 2j for positive, 2j + 1 for negative coordinates."""
    x = df.select(F.col(key).alias("user_id"), F.posexplode(values).alias("j", "x")).withColumn("x", F.col("x").cast("double"))
    return x.where("x <> 0 and not isnan(x)").select("user_id", (2 * F.col("j") + F.when(F.col("x") < 0, 1).otherwise(0)).cast("string").alias("feature"), F.abs("x").alias("weight"))


def binarise(v: DataFrame) -> DataFrame:
    return v.withColumn("weight", F.lit(1.0))


def power(v: DataFrame, p: float) -> DataFrame:
    return v.withColumn("weight", F.pow("weight", F.lit(p)))


def reweight(v: DataFrame, importance: DataFrame, default: float = 1.0, max_broadcast: int = 1_000_000) -> DataFrame:
    """Multiply by feature importance (0 drops a feature, below 0 is an error); the table is broadcast only if its counted rows allow."""
    imp = importance.select("feature", F.when(F.col("importance") < 0, F.raise_error(F.lit("negative importance"))).otherwise(F.col("importance")).alias("importance"))
    side = F.broadcast(imp) if imp.limit(max_broadcast + 1).count() <= max_broadcast else imp
    return v.join(side, "feature", "left").select("user_id", "feature", (F.col("weight") * F.coalesce("importance", F.lit(default))).alias("weight")).where("weight > 0")


def top_features(v: DataFrame, k: int) -> DataFrame:
    """Each user's k heaviest features; ties to the smaller feature. Only k rows a user are kept before the shuffle and after it."""
    w = Window.partitionBy("user_id").orderBy(F.desc("weight"), "feature")
    return v.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select("user_id", "feature", "weight")


def feature_ids(v: DataFrame) -> DataFrame:
    """feature, feature_id: numbers 0, 1, ... in order of the names.

    Names are range-partitioned and sorted, the partitions' counts shift the numbers inside: no window over all names.
    """
    from .storage import shared_write

    names = v.select("feature").distinct().repartitionByRange("feature").sortWithinPartitions("feature").withColumn("part", F.spark_partition_id())
    names = shared_write(names, "names")
    total, starts = 0, []
    for r in names.groupBy("part").count().orderBy("part").collect():  # a row a partition
        starts.append((r["part"], total))
        total += r["count"]
    side = v.sparkSession.createDataFrame(starts, "part int, start long")
    place = F.row_number().over(Window.partitionBy("part").orderBy("feature")) - 1
    return names.withColumn("place", place).join(F.broadcast(side), "part").select("feature", (F.col("place") + F.col("start")).alias("feature_id"))


def shingles(df: DataFrame, key: str, text: str, n: int) -> DataFrame:
    """Term frequencies of n-word shingles in lower case."""
    from .storage import spread

    words = spread(df.select(key, text)).select(F.col(key).alias("user_id"), F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "").alias("w")).where(F.size("w") >= n)
    parts = F.transform(F.sequence(F.lit(1), F.size("w") - (n - 1)), lambda i: F.array_join(F.slice("w", i, n), " "))
    return words.select("user_id", F.explode(parts).alias("feature")).groupBy("user_id", "feature").agg(F.count("*").cast("double").alias("weight"))


def term_sets(df: DataFrame, key: str, text: str) -> DataFrame:
    """user_id, code: the sorted codes of a text's different words. One narrow pass; only where keys repeat are whole sets shuffled and united."""
    from ..functions.randomness import code
    from .storage import spread

    words = F.array_distinct(F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != ""))
    sets = spread(df.select(key, text)).select(F.col(key).alias("user_id"), F.transform(words, code).alias("code")).where(F.size("code") > 0)
    if not df.groupBy(key).count().where("count > 1").limit(1).count():
        return sets.withColumn("code", F.array_sort(F.array_distinct("code")))
    return sets.groupBy("user_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("code")))).alias("code"))


def packed_terms(df: DataFrame, key: str, text: str) -> DataFrame:
    """``hashing.packed`` of ``shingles`` of one word (without the names): user_id, code, weight. One narrow pass; only where keys repeat are words shuffled and counted."""
    import numpy as np
    import pyarrow as pa

    from ..functions.randomness import code_of
    from .hashing import packed
    from .storage import spread

    if df.groupBy(key).count().where("count > 1").limit(1).count():
        return packed(shingles(df, key, text, 1)).select("user_id", "code", "weight")

    def run(batches):
        for b in batches:
            words = b.column("w")
            ptr = words.offsets.to_numpy().astype(np.int64)
            names = words.flatten().dictionary_encode()
            codes = np.array([code_of(x) for x in names.dictionary.to_pylist()], np.int64)
            by = np.argsort(codes, kind="stable")
            rank = np.empty(len(by), np.int64)
            rank[by] = np.arange(len(by))
            row = np.repeat(np.arange(b.num_rows), np.diff(ptr))
            cell, n = np.unique(row * max(len(by), 1) + rank[names.indices.to_numpy()], return_counts=True)
            ends = np.concatenate(([0], np.cumsum(np.bincount(cell // max(len(by), 1), minlength=b.num_rows)))).astype(np.int32)
            lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(x)) for x in (codes[by][cell % max(len(by), 1)], n.astype(np.float64))]
            yield pa.RecordBatch.from_arrays([b.column("user_id"), *lists], ["user_id", "code", "weight"])

    words = F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    rows = spread(df.select(key, text)).select(F.col(key).alias("user_id"), words.alias("w")).where(F.size("w") > 0)
    return rows.mapInArrow(run, "user_id long, code array<long>, weight array<double>")


def vector_stats(v: DataFrame) -> DataFrame:
    a = v.agg(F.countDistinct("user_id").alias("n"), F.countDistinct("feature").alias("d"), F.count("*").alias("nnz"), F.max("weight").alias("max_weight"))
    return a.withColumn("density", F.round(F.col("nnz") / F.col("n") / F.col("d"), 9))


def baskets(spark, sf_dir: str, wide: bool = False) -> DataFrame:
    """Customers by quantity per brand (or brand and type), nation and segment."""
    from ..sources.tables import read_table as t

    lines = t(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = t(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("user_id"))
    name = F.concat(F.lit("b:"), "p_brand", F.lit("/"), "p_type") if wide else F.concat(F.lit("b:"), "p_brand")
    parts = t(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), name.alias("feature"))
    bought = lines.join(orders, "l_orderkey").join(parts, "l_partkey").groupBy("user_id", "feature").agg(F.sum("l_quantity").alias("weight"))
    if wide:
        return bought
    c = t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey", "c_mktsegment")
    nation = c.select("user_id", F.concat(F.lit("n:"), F.col("c_nationkey").cast("string")).alias("feature"), F.lit(100.0).alias("weight"))
    segment = c.select("user_id", F.concat(F.lit("s:"), "c_mktsegment").alias("feature"), F.lit(200.0).alias("weight"))
    return bought.unionByName(nation).unionByName(segment)


def baskets_part(spark, sf_dir: str) -> DataFrame:
    """Customers by quantity per part: sparse, little overlap."""
    from ..sources.tables import read_table as t

    lines = t(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = t(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("user_id"))
    return sparse_vectors(lines.join(orders, "l_orderkey"), "user_id", "l_partkey", "l_quantity")


BASKETS_SQL = """
    select o_custkey as user_id, 'b:' || p_brand as feature, sum(l_quantity) as weight
    from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey group by 1, 2
    union all select c_custkey, 'n:' || c_nationkey, 100.0 from customer
    union all select c_custkey, 's:' || c_mktsegment, 200.0 from customer"""
DOCS_SQL = """
    select doc_id as user_id, w as feature, count(*)::double as weight
    from (select doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+')) as w from documents) where w <> '' group by 1, 2"""
EMBED_SQL = """
    select vec_id as user_id, (2 * (j - 1) + case when x < 0 then 1 else 0 end)::varchar as feature, abs(x) as weight
    from (select vec_id, unnest(embedding)::double as x, generate_subscripts(embedding, 1) as j from embeddings) where x <> 0"""


def doc_terms(spark, sf_dir: str) -> DataFrame:
    from ..sources.tables import read_table

    return shingles(read_table(spark, sf_dir, "documents"), "doc_id", "text", 1)
