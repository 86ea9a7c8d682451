"""The experiments on the given tables."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.randomness import code
from ..operators import blocks, campaigns, hashing, mode_split
from ..operators.storage import shared_write

CAMPAIGNS = 400


def word_campaigns(v: DataFrame, k: int, top: int = CAMPAIGNS) -> DataFrame:
    """A campaign per feature that K to 60 % of users have (the commonest ``top``), at its median weight."""
    n = v.select("user_id").distinct().count()
    d = v.groupBy("feature").agg(F.count("*").alias("df"), F.percentile("weight", F.lit(0.5)).alias("min_weight"))
    d = d.where((F.col("df") >= k) & (F.col("df") <= 0.6 * n)).orderBy(F.desc("df"), "feature").limit(top)
    return d.select(F.col("feature").alias("campaign_id"), "feature", "min_weight")


def packed_campaigns(docs: DataFrame, vectors: DataFrame, key: str, text: str, k: int, top: int = CAMPAIGNS) -> DataFrame:
    """``word_campaigns`` of documents ``docs`` with packed ``vectors``: weights are counted for the words that are chosen, not for all."""
    n = vectors.count()
    d = vectors.select(F.explode("code").alias("code")).groupBy("code").agg(F.count("*").alias("df"))
    d = shared_write(d.where((F.col("df") >= k) & (F.col("df") <= 0.6 * n)), "frequencies")
    least = d.orderBy(F.desc("df")).limit(top).agg(F.min("df")).collect()[0][0] or 0  # ties of the last one are named too
    some = shared_write(d.where(F.col("df") >= least), "frequent")
    w = F.explode(F.array_distinct(F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")))
    names = docs.select(w.alias("feature")).groupBy("feature").agg(F.lit(1)).select("feature", code(F.col("feature")).alias("code"))
    chosen = shared_write(names.join(some, "code").orderBy(F.desc("df"), "feature").limit(top), "campaigns")
    x = vectors.select(F.explode(F.arrays_zip("code", "weight")).alias("e")).select("e.code", "e.weight").join(F.broadcast(chosen), "code")
    x = x.groupBy("feature", "weight").agg(F.count("*").alias("n"))
    d = x.groupBy("feature").agg(F.percentile("weight", F.lit(0.5), F.col("n")).alias("min_weight"))
    return d.select(F.col("feature").alias("campaign_id"), "feature", "min_weight")


def basket_campaigns(spark: SparkSession) -> DataFrame:
    """Nations, segments, brands (at 100) and their crosses with segments."""
    nations, segments = [f"n:{i}" for i in range(25)], ["s:" + s for s in ("AUTOMOBILE", "BUILDING", "FURNITURE", "MACHINERY", "HOUSEHOLD")]
    brands = [f"b:Brand#{i}{j}" for i in range(1, 6) for j in range(1, 6)]
    rows = [(x, x, 100.0 if x[0] == "b" else 1.0) for x in nations + segments + brands]
    rows += [(f"{s}&{x}", y, 100.0 if y[0] == "b" else 1.0) for s in segments for x in nations + brands for y in (s, x)]
    return spark.createDataFrame(rows, "campaign_id string, feature string, min_weight double")


def evaluate(assign: DataFrame, matches: DataFrame, theta: float = 0.5) -> DataFrame:
    return campaigns.recalls(campaigns.campaign_counts(campaigns.match_cohorts(matches, assign, theta=theta)))


def compare(v: DataFrame, camps: DataFrame, k: int = 20, rounds: int = 1000, lengths=(50, 75, 100), p: float = 1.2, seed: int = 7) -> DataFrame:
    """method, length, micro_recall, macro_recall, ...: the table of all five methods; every length is a row (``blocks.best_length`` keeps the best).

    Vectors are packed once (``v`` may be packed). A family's signature is made once, at the longest length and only
    for users whose first slots do not tell their place; shorter ones are its prefixes.
    """
    vectors = shared_write(hashing.packed(v).select("user_id", "code", "weight"), "vectors")
    users = vectors.select("user_id")
    n = users.count()
    runs = [("random", 0, blocks.random_groups(users, max(1, int(n / 23.33)), seed)), ("mode_split", 0, mode_split.mode_split(vectors, users, k, rounds, p, seed).assignments)]
    for family in ("minwise", "sign", "weighted"):
        longest = hashing.ordering_signatures(vectors, family, max(lengths), p, seed, min(32 if family == "sign" else 8, *lengths))
        longest = shared_write(longest, "signature")
        runs += [(f"sorted_{family}", m, blocks.sorted_blocks(longest.withColumn("sig", F.slice("sig", 1, m)), k)) for m in lengths]
    return evaluate_bits([(F.lit(name).alias("method"), F.lit(m).alias("length"), assign) for name, m, assign in runs], camps, vectors, n)


def evaluate_bits(runs: list, camps: DataFrame, vectors: DataFrame, users: int, theta: float = 0.5, each: int = 50_000) -> DataFrame:
    """``evaluate_all`` with the matches of ``camps`` as bits of each user of the packed ``vectors``."""
    bits, n = campaigns.match_bits(camps, vectors)
    out = names = None
    for i, (*keys, assign) in enumerate(runs):
        a = assign.select(F.lit(i).alias("run"), "user_id", F.col("cohort_id").cast("string").alias("cohort_id"))
        name = vectors.sparkSession.range(1).select(F.lit(i).alias("run"), *keys)
        out, names = (a, name) if out is None else (out.unionByName(a), names.unionByName(name))
    c = campaigns.counts_by_bits(out, bits, n, theta, max(1, -(-users // each)))
    agg = c.groupBy("run").agg(F.avg(F.col("tp") / F.col("wanted")).alias("micro_recall"), (F.sum("tp") / F.sum("wanted")).alias("macro_recall"), (F.sum("tp") / F.nullif(F.sum("audience"), F.lit(0))).alias("precision"), F.count("*").alias("campaigns"))
    return agg.join(F.broadcast(names), "run").select(*[x for x in names.columns if x != "run"], "micro_recall", "macro_recall", "precision", "campaigns")


def evaluate_all(runs: list, matches: DataFrame, theta: float = 0.5) -> DataFrame:
    """Recalls of many assignments, each with its naming columns, in one aggregation."""
    out = None
    for *names, assign in runs:
        a = assign.select("user_id", F.col("cohort_id").cast("string").alias("cohort_id"), *names)
        out = a if out is None else out.unionByName(a)
    keys = [c for c in out.columns if c not in ("user_id", "cohort_id")]
    out = shared_write(out, "runs")
    size = out.groupBy(*keys, "cohort_id").agg(F.count("*").alias("members"))
    m = matches.join(out, "user_id").groupBy(*keys, "campaign_id", "cohort_id").agg(F.count("*").alias("matched")).join(size, [*keys, "cohort_id"])
    m = m.withColumn("hit", F.col("matched") >= theta * F.col("members"))
    on = lambda x: F.sum(F.when(F.col("hit"), x).otherwise(0))
    c = m.groupBy(*keys, "campaign_id").agg(on(F.col("matched")).alias("tp"), on(F.col("members")).alias("audience"), F.sum("matched").alias("wanted"))
    agg = c.groupBy(*keys).agg(F.avg(F.col("tp") / F.col("wanted")).alias("micro_recall"), (F.sum("tp") / F.sum("wanted")).alias("macro_recall"), (F.sum("tp") / F.nullif(F.sum("audience"), F.lit(0))).alias("precision"), F.count("*").alias("campaigns"))
    return agg


def p_sweep(v: DataFrame, users: DataFrame, camps: DataFrame, grid, k: int = 20, rounds: int = 1000, seed: int = 7, together: int = 3) -> DataFrame:
    """p, micro_recall, macro_recall, ... of consecutive splitting. Vectors are packed once; ``together`` powers run at a time, so that short jobs of one fill the pauses of others."""
    vectors = shared_write(hashing.packed(v, users).select("user_id", "code", "weight"), "vectors")
    with ThreadPoolExecutor(together) as pool:
        runs = list(pool.map(lambda p: (F.lit(float(p)).alias("p"), mode_split.mode_split(vectors, users, k, rounds, p, seed).assignments), grid))
    return evaluate_bits(runs, camps, vectors, vectors.count())


def k_sweep(v: DataFrame, users: DataFrame, sizes=(5, 10, 20, 50), rounds: int = 1000, p: float = 1.2, seed: int = 7) -> DataFrame:
    """k and the anonymity audit of consecutive splitting at it."""
    v, out = shared_write(v, "vectors"), None
    for k in sizes:
        row = campaigns.anonymity_audit(mode_split.mode_split(v, users, k, rounds, p, seed).assignments, users, k).select(F.lit(k).alias("k"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def cost_runs(v: DataFrame, users: DataFrame, shares=(1, 2, 4), rounds=(8, 16, 32), k: int = 20, p: float = 1.2, seed: int = 7) -> DataFrame:
    """users, entries, rounds, seconds of consecutive splitting over every n-th user and over several numbers of rounds."""
    rows = []
    for n in shares:
        some = shared_write(v.where(F.col("user_id") % n == 0), "vectors")
        who = users.where(F.col("user_id") % n == 0)
        size, entries = who.count(), some.count()
        for t in rounds:
            began = time.time()
            mode_split.mode_split(some, who, k, t, p, seed).assignments.count()
            rows.append((size, entries, t, time.time() - began))
    return users.sparkSession.createDataFrame(rows, "users long, entries long, rounds int, seconds double")


def scaling_fit(runs: DataFrame, by: str = "users") -> DataFrame:
    """slope: the exponent of seconds in ``by`` (least squares on logarithms)."""
    return runs.agg(F.regr_slope(F.log("seconds"), F.log(by)).alias("slope"), F.count("*").alias("runs"))
