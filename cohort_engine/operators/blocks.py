"""Baselines: sorted blocks of hash vectors, raw buckets, random groups, classic clusterers, repair."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .hashing import packed
from .storage import shared_write


def sorted_blocks(h: DataFrame, k: int = 20, tail: str = "merge") -> DataFrame:
    """Users of ``h`` (user_id, sig) in lexicographic order, cut every ``k``.

    A range-partitioned sort, the partitions' counts on the driver, then ranks inside partitions:
    no window over all rows. ``tail``: 'merge' gives the last block the rest, 'short' leaves it short.
    """
    s = shared_write(h.repartitionByRange("sig", "user_id").sortWithinPartitions("sig", "user_id").withColumn("part", F.spark_partition_id()), "sorted")
    counts = s.groupBy("part").count().orderBy("part").collect()
    total, starts, n = sum(r["count"] for r in counts), [], 0
    for r in counts:
        starts.append((r["part"], n))
        n += r["count"]
    if not total:
        return s.select("user_id", F.lit("").alias("cohort_id")).limit(0)
    side = h.sparkSession.createDataFrame(starts, "part int, start long")
    w = Window.partitionBy("part").orderBy("sig", "user_id")
    ranked = s.withColumn("row", F.row_number().over(w) - 1).join(F.broadcast(side), "part")
    block = F.floor((F.col("row") + F.col("start")) / k)
    if tail == "merge":
        block = F.least(block, F.lit(max(total // k, 1) - 1))
    return ranked.select("user_id", block.cast("string").alias("cohort_id"))


def raw_buckets(h: DataFrame, slots: int = 1) -> DataFrame:
    """The hash itself as the cohort; sizes are not controlled."""
    return h.select("user_id", F.array_join(F.transform(F.slice("sig", 1, slots), lambda x: x.cast("string")), ",").alias("cohort_id"))


def random_groups(users: DataFrame, groups: int, seed: int = 7) -> DataFrame:
    """Seeded uniform groups; sizes are Poisson, so K is not kept."""
    x = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("user_id").cast("string"))), 1, 12), 16, 10).cast("long")
    return users.select("user_id", (x % groups).cast("string").alias("cohort_id"))


def balanced_groups(users: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """Random groups of ``k`` (the last takes the rest): users cut in a seeded order, so K is kept."""
    order = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("user_id").cast("string")))
    return sorted_blocks(users.select("user_id", F.array(order).alias("sig")), k)


def best_length(table: DataFrame, measure: str = "macro_recall") -> DataFrame:
    """The row of the best length of each method of a comparison (ties to the shorter)."""
    best = table.groupBy("method").agg(F.max_by(F.struct(*table.columns), F.struct(measure, -F.col("length"))).alias("b"))
    return best.select("b.*")


def kmeans_cohorts(v: DataFrame, k: int, dimensions: int = 256, iterations: int = 10, seed: int = 7, max_users: int = 200_000) -> DataFrame:
    """Lloyd's algorithm on hashed features; no size floor. Its cost grows with users x centres, so more than ``max_users`` is refused."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    n = v.select("user_id").distinct().limit(max_users + 1).count()
    if n > max_users:
        raise ValueError(f"k-means is refused above {max_users} users")
    d = v.select("user_id", F.pmod(F.xxhash64("feature"), F.lit(dimensions)).cast("int").alias("j"), "weight").groupBy("user_id", "j").agg(F.sum("weight").alias("w"))
    m = d.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("j", "w"))).alias("m"))
    x = m.select("user_id", array_to_vector(F.transform(F.sequence(F.lit(0), F.lit(dimensions - 1)), lambda j: F.coalesce(F.element_at("m", j), F.lit(0.0)))).alias("features"))
    fitted = KMeans(k=k, maxIter=iterations, seed=seed).fit(x)
    return fitted.transform(x).select("user_id", F.col("prediction").cast("string").alias("cohort_id"))


def density_cohorts(pairs: DataFrame, users: DataFrame, threshold: float, min_points: int, neighbours: DataFrame | None = None) -> DataFrame:
    """Density clusters from ``pairs`` (a, b, similarity): cores have ``min_points`` neighbours (themselves included), clusters are their components, borders join the smallest.

    Where ``pairs`` are not all links (``similarity.near_forest``), ``neighbours`` (user_id, neighbours) counts those.

    Labels only fall and also jump to the label of their label, so the loop ends, in few rounds on long chains.
    """
    near = pairs.where(F.col("similarity") >= threshold).where("a <> b").select("a", "b")
    ways = F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))
    both = shared_write(near.select(F.inline(ways)).distinct(), "near")  # a union would make the pairs twice
    count = both.groupBy("a").agg(F.count("*").alias("neighbours")) if neighbours is None else neighbours.withColumnRenamed("user_id", "a")
    core = count.where(F.col("neighbours") >= min_points - 1).select("a")
    inner = both.join(core, "a", "left_semi").join(core.withColumnRenamed("a", "b"), "b", "left_semi").select("a", "b")
    label = shared_write(core.select("a", F.col("a").alias("c")), "label")
    while True:
        least = inner.join(label.withColumnRenamed("a", "b"), "b").groupBy("a").agg(F.min("c").alias("m"))
        low = label.join(least, "a", "left").select("a", F.least("c", F.coalesce("m", "c")).alias("c"))
        new = shared_write(low.join(label.toDF("c", "up"), "c").select("a", F.least("c", "up").alias("c")), "label")
        if not new.join(label.withColumnRenamed("c", "old"), "a").where("c <> old").limit(1).count():
            break
        label = new
    border = both.join(label.select(F.col("a").alias("b"), "c"), "b").groupBy("a").agg(F.min("c").alias("c"))
    return users.withColumnRenamed("user_id", "a").join(label, "a", "left").join(border.withColumnRenamed("c", "d"), "a", "left").select(F.col("a").alias("user_id"), F.coalesce(F.coalesce("c", "d").cast("string"), F.lit("noise")).alias("cohort_id"))


def agglomerative_cohorts(v: DataFrame, k: int, max_users: int | None = None) -> DataFrame:
    """Average-linkage merging of clusters below ``k``: the smallest cluster (ties to its first user) joins the one most like it.

    Merges follow each other, so one task holds the vectors (users x features doubles) and makes
    users x users x features steps; ``max_users`` refuses more users.
    """
    if max_users is not None and v.select("user_id").distinct().limit(max_users + 1).count() > max_users:
        raise ValueError(f"agglomerative clustering is refused above {max_users} users")

    def one(t: pa.Table) -> pa.Table:
        t = t.combine_chunks().sort_by("user_id").combine_chunks()
        ids, code, weight = t.column("user_id").to_numpy(), t.column("code").chunk(0), t.column("weight").chunk(0)
        ptr = code.offsets.to_numpy().astype(np.int64)
        names, col = np.unique(code.values.to_numpy()[ptr[0] : ptr[-1]], return_inverse=True)
        sums = np.zeros((len(ids), len(names)))
        np.add.at(sums, (np.repeat(np.arange(len(ids)), np.diff(ptr)), col), weight.values.to_numpy()[ptr[0] : ptr[-1]])
        sums /= np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-12)
        head = merged(sums, k)
        return pa.table({"user_id": pa.array(ids), "cohort_id": pa.array([str(i) for i in ids[head].tolist()])})

    return packed(v).select("user_id", "code", "weight", F.lit(1).alias("g")).groupBy("g").applyInArrow(one, "user_id long, cohort_id string")


def merged(sums: np.ndarray, k: int, cells: int = 8_000_000) -> np.ndarray:
    """Each row's first row of its cluster; ``sums`` is changed.

    A merge makes a cluster larger than the smallest, so the smallest clusters of one size have their turns in
    order: a batch of them takes its products with all clusters at once, and a merge renews one column of those.
    """
    n = len(sums)
    size, members, live = np.ones(n, np.int64), [[i] for i in range(n)], np.arange(n)
    while len(live) > 1 and size[live].min() < k:
        batch = live[size[live] == size[live].min()][: max(16, min(256, cells // len(live)))]
        link = (sums[batch] @ sums[live].T) / size[live]
        column = {c: i for i, c in enumerate(live.tolist())}
        left, now = len(live), size[batch[0]]
        for i, small in enumerate(batch.tolist()):
            if size[small] != now or left == 1:  # an earlier one of the batch joined it
                continue
            link[i, column[small]] = -np.inf
            at = int(link[i].argmax())
            to = int(live[at])
            sums[to] += sums[small]
            size[to] += size[small]
            members[to] += members[small]
            size[small], members[small], left = 0, [], left - 1
            link[i + 1 :, at] = (sums[batch[i + 1 :]] @ sums[to]) / size[to]
            link[i + 1 :, column[small]] = -np.inf
        live = live[size[live] > 0]
    head = np.empty(n, np.int64)
    for c in live.tolist():
        head[members[c]] = min(members[c])
    return head


def enforce_floor(assign: DataFrame, k: int, how: str = "suppress") -> DataFrame:
    """Drop the users of cohorts below ``k``, or merge those cohorts into one."""
    sizes = assign.groupBy("cohort_id").count()
    small = sizes.where(F.col("count") < k).select("cohort_id")
    if how == "suppress":
        return assign.join(small, "cohort_id", "left_anti").select("user_id", "cohort_id")
    return assign.join(small.withColumn("s", F.lit(True)), "cohort_id", "left").select("user_id", F.when(F.col("s"), "merged").otherwise(F.col("cohort_id")).alias("cohort_id"))
