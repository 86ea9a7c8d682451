"""Mixing sources to target weights by Sainte-Lague apportionment. DataFrame functions only.

``targets`` shares a token budget by weight under per-source caps (water-filling over the ordered
cap ratios, one pass). ``apportion`` hands out integer block quotas by highest quotients: the
divisors V/(N - m/2) and V/(N + m/2) bracket every seat count, so only about 2m quotients around
the cut are compared instead of all N. ``mix`` applies it to sources and then down a tree of each
source's shards, and takes blocks in a seeded order inside every (source, shard).

Edge cases: null or empty text has size 0 and takes 0; a null source is one ordinary source, last
in order; a source of size 0 gets target 0; an empty table gives an empty result; repeated rows are
treated alike (order within equal doc_id is by size); extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, hex_order, join_small, keyed, materialise


def sizes(docs: DataFrame) -> DataFrame:
    """doc_id, source, size: words of the whole text."""
    return docs.select("doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))


def targets(by_source: DataFrame, weights=(1, 2, 3), max_repeat: int = 3) -> DataFrame:
    """by_source(source, source_size, ...) plus rank, weight and target.

    Sources are a dimension table (one row each), so a single ordered window over them is bounded
    by the number of sources, never by documents.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    t = by_source.withColumn("source_rank", F.row_number().over(order) - 1)
    pick = F.array(*[F.lit(float(w)) for w in weights])
    t = t.withColumn("weight", F.element_at(pick, (F.col("source_rank") % len(weights) + 1).cast("int")))
    t = t.withColumn("cap", F.col("source_size") * max_repeat)
    ordered = Window.orderBy(F.col("cap") / F.col("weight"), "source_rank")
    before, all_rows = ordered.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    t = t.withColumn("left_size", F.sum("source_size").over(all_rows) - F.coalesce(F.sum("cap").over(before), F.lit(0)))
    t = t.withColumn("left_weight", F.sum("weight").over(all_rows) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    t = t.withColumn("fits", F.col("cap") * F.col("left_weight") >= F.col("left_size") * F.col("weight"))
    t = t.withColumn("first_fit", F.min(F.when(F.col("fits"), F.struct(F.col("cap") / F.col("weight"), "source_rank", "left_size", "left_weight"))).over(all_rows))
    share = F.col("weight") * F.col("first_fit.left_size") / F.col("first_fit.left_weight")
    t = t.withColumn("target", F.coalesce(F.least(share, F.col("cap").cast("double")), F.col("cap").cast("double")))
    return t.drop("left_size", "left_weight", "fits", "first_fit", "cap")


def apportion(votes: DataFrame, seats, group: list[str], key: str, vote: str, out: str = "quota") -> DataFrame:
    """Sainte-Lague seats for the rows of ``votes`` inside each ``group``; ``seats`` is a column of the group.

    Ties of quotients go to the smaller ``key``. Rows without votes get none.
    """
    w = Window.partitionBy(*group)
    v = votes.withColumn("_v", F.col(vote).cast("double")).withColumn("_n", seats.cast("double"))
    v = v.withColumn("_all", F.sum("_v").over(w)).withColumn("_m", F.sum(F.when(F.col("_v") > 0, 1.0).otherwise(0.0)).over(w))
    low = F.when(F.col("_v") > 0, F.greatest(F.lit(0.0), F.floor(F.col("_v") * (F.col("_n") - F.col("_m") / 2) / F.col("_all") + 0.5 - 1e-9))).otherwise(0.0)
    high = F.when(F.col("_v") > 0, F.ceil(F.col("_v") * (F.col("_n") + F.col("_m") / 2) / F.col("_all") + 0.5)).otherwise(0.0)
    v = v.withColumn("_low", low.cast("long")).withColumn("_high", high.cast("long"))
    v = v.withColumn("_rest", F.col("_n").cast("long") - F.sum("_low").over(w))
    near = v.where("_high > _low").select(*group, key, "_v", "_rest", F.explode(F.sequence("_low", F.col("_high") - 1)).alias("_k"))
    best = Window.partitionBy(*group).orderBy((F.col("_v") / (2 * F.col("_k") + 1)).desc(), F.col(key), F.col("_k"))
    won = near.withColumn("_place", F.row_number().over(best)).where("_place <= _rest").groupBy(*group, key).agg(F.count("*").alias("_won"))
    keys = [*group, key]
    same = [F.col(f"v.{c}").eqNullSafe(F.col(f"w.{c}")) for c in keys]
    cond = same[0]
    for c in same[1:]:
        cond = cond & c
    joined = v.alias("v").join(won.alias("w"), cond, "left")
    return joined.select("v.*", (F.col("_low") + F.coalesce("_won", F.lit(0))).alias(out)).drop("_v", "_n", "_all", "_m", "_low", "_high", "_rest")


def shard_quotas(shards: DataFrame, fanout: int) -> DataFrame:
    """source_rank, shard, shard_size, quota of ``shards``, whose quota is their source's.

    Quotas go down a tree: at each level a group's seats are apportioned to at most ``fanout`` parts,
    so that no task holds all shards of a large source.
    """
    levels = [materialise(shards.withColumn("node", F.col("shard")), "mix_shards")]
    while (levels[-1].agg(F.max("node")).collect()[0][0] or 0) >= fanout:
        up = levels[-1].groupBy("source_rank", F.floor(F.col("node") / fanout).alias("node"))
        levels.append(materialise(up.agg(F.sum("shard_size").alias("shard_size"), F.max("quota").alias("quota")), "mix_nodes"))
    out = None
    for level in reversed(levels):
        if out is None:  # the top: one group a source
            own = level.withColumnRenamed("quota", "seats").withColumn("group", F.lit(0).cast("long"))
        else:
            seats = out.select("source_rank", F.col("node").alias("group"), F.col("quota").alias("seats"))
            own = level.drop("quota").withColumn("group", F.floor(F.col("node") / fanout)).join(seats, ["source_rank", "group"])
        out = materialise(apportion(own, F.col("seats"), ["source_rank", "group"], "node", "shard_size", "quota").drop("seats", "group"), "mix_quota")
    return out.drop("node")


def mix(docs: DataFrame, weights=(1, 2, 3), max_repeat: int = 3, block: int = 16, shard_rows: int = 4096, fanout: int = 4096, seed: int = 7) -> DataFrame:
    """doc_id, size, source_size, target, taken, source, source_rank, shard.

    ``block``: words in a block; ``shard_rows``: documents aimed at in a shard, so that a source
    holding a third of all rows is spread over as many shards as its rows need; ``fanout``: shards
    (or groups of them) that share out quotas in one task. Windows over the sources hold one row a source.
    """
    spark = docs.sparkSession
    size = materialise(sizes(docs), "mix_sizes")
    by_source = size.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("_docs"))
    t = targets(by_source, weights, max_repeat).withColumn("_all_words", F.sum("source_size").over(Window.partitionBy()))
    t = t.withColumn("_one", F.lit(1)).withColumn("_shards", F.ceil(F.col("_docs") / shard_rows).cast("long"))
    t = apportion(t, F.round(F.col("_all_words") / block), ["_one"], "source_rank", "target", "source_quota").drop("_one", "_all_words", "_docs")
    t = materialise(t, "mix_sources")
    t = F.broadcast(t) if t.limit(100_001).count() <= 100_000 else t
    s = size.alias("s").join(t.alias("t"), F.col("s.source").eqNullSafe(F.col("t.source"))).select("s.*", "source_size", "target", "source_rank", "source_quota", "_shards")
    s = s.withColumn("_order", hex_order(seed, "doc_id"))
    s = s.withColumn("shard", F.conv(F.substring("_order", 1, 8), 16, 10).cast("long") % F.col("_shards"))
    quota = shard_quotas(s.groupBy("source_rank", "shard").agg(F.sum("size").alias("shard_size"), F.max("source_quota").alias("quota")), fanout)
    s = s.join(F.broadcast(quota) if quota.limit(100_001).count() <= 100_000 else quota, ["source_rank", "shard"])
    words = F.least(F.col("quota") * block, F.col("shard_size") * max_repeat)
    s = s.withColumn("_words", words).withColumn("_passes", F.when(F.col("shard_size") > 0, F.expr("_words div shard_size")).otherwise(F.lit(0)))
    run = Window.partitionBy("source_rank", "shard").orderBy("_order", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumn("_before", F.coalesce(F.sum("size").over(run), F.lit(0)))
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("_words") - F.col("_passes") * F.col("shard_size") - F.col("_before")))
    return s.select("doc_id", "size", "source_size", "target", (F.col("_passes") * F.col("size") + part).cast("long").alias("taken"), "source", "source_rank", "shard")


def mixed_documents(docs: DataFrame, max_broadcast: int = 2_000_000, **options) -> DataFrame:
    """The documents the mix takes, whole, one row per repetition, with the columns of ``docs``.

    At most one document of a (source, shard) is taken in part; it is rounded to the nearer whole.
    Every row counts for itself, whatever its id.
    """
    rows = keyed(docs, "_row")
    m = mix(rows.select(F.col("_row").alias("doc_id"), "source", "text"), **options).where("taken > 0")
    m = m.select(F.col("doc_id").alias("_row"), F.expr("cast(round(taken / size) as int)").alias("_copies")).where("_copies > 0")
    out = join_small(rows, materialise(m, "mix_copies"), "_row", "inner", max_broadcast).withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
    return out.select(*docs.columns)
