"""Cohort identities, campaign matching, retrieval, and the accuracy, size and privacy measures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.randomness import code
from .hashing import Sparse, _slices


def content_ids(assign: DataFrame) -> DataFrame:
    """cohort_id, content_id: SHA-256 of the members in numeric order."""
    ids = F.array_join(F.transform(F.sort_array(F.collect_list("user_id")), lambda x: x.cast("string")), ",")
    return assign.groupBy("cohort_id").agg(F.sha2(ids, 256).alias("content_id"))


def sizes(assign: DataFrame) -> DataFrame:
    return assign.groupBy("cohort_id").agg(F.count("*").alias("members"))


def cohort_identity(assign: DataFrame, v: DataFrame, k: int = 1) -> DataFrame:
    """cohort_id, feature, share, mean_weight, members; cohorts below ``k`` are left out."""
    j = v.join(assign, "user_id").groupBy("cohort_id", "feature").agg(F.count("*").alias("n"), F.sum("weight").alias("w"))
    j = j.join(sizes(assign).where(F.col("members") >= k), "cohort_id")
    return j.select("cohort_id", "feature", (F.col("n") / F.col("members")).alias("share"), (F.col("w") / F.col("members")).alias("mean_weight"), "members")


def identity_by(assign: DataFrame, v: DataFrame, kind: str, k: int = 1) -> DataFrame:
    """cohort_id, feature, value, members: identity vectors by 'share', 'mean', 'sum' or 'max' of the members' weights."""
    value = {"share": F.count("*") / F.max("members"), "mean": F.sum("weight") / F.max("members"), "sum": F.sum("weight"), "max": F.max("weight")}[kind]
    j = v.join(assign, "user_id").join(sizes(assign).where(F.col("members") >= k), "cohort_id")
    return j.groupBy("cohort_id", "feature").agg(value.cast("double").alias("value"), F.max("members").alias("members"))


def audience(cohorts: DataFrame) -> DataFrame:
    """campaign_id, cohorts, audience: the matched cohorts of ``match_cohorts`` and their users."""
    return cohorts.where("hit").groupBy("campaign_id").agg(F.count("*").alias("cohorts"), F.sum("members").alias("audience"))


def precisions(counts: DataFrame) -> DataFrame:
    """Pooled and mean precision and F1 of ``campaign_counts``; campaigns without an audience have no precision."""
    p, r = F.col("tp") / F.nullif(F.col("audience"), F.lit(0)), F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0))
    f1 = 2 * F.col("tp") / F.nullif(F.col("audience") + F.col("tp") + F.col("fn"), F.lit(0))
    pooled = 2 * F.sum("tp") / F.nullif(F.sum(F.col("audience") + F.col("tp") + F.col("fn")), F.lit(0))
    return counts.agg((F.sum("tp") / F.nullif(F.sum("audience"), F.lit(0))).alias("precision"), F.avg(p).alias("mean_precision"), pooled.alias("f1"), F.avg(f1).alias("mean_f1"), F.avg(r).alias("mean_recall"))


def match_users(campaigns: DataFrame, v: DataFrame, max_broadcast: int = 1_000_000) -> DataFrame:
    """campaign_id, user_id: users having all of a campaign's features at its least weights (relational division)."""
    n = campaigns.groupBy("campaign_id").agg(F.count("*").alias("need"))
    c = campaigns.join(n, "campaign_id")
    c = F.broadcast(c) if c.limit(max_broadcast + 1).count() <= max_broadcast else c
    hits = v.join(c, "feature").where("weight >= min_weight").groupBy("campaign_id", "user_id").agg(F.count("*").alias("hits"), F.max("need").alias("need"))
    return hits.where("hits = need").select("campaign_id", "user_id")


def match_bits(campaigns: DataFrame, vectors: DataFrame) -> tuple[DataFrame, int]:
    """user_id, bits: ``match_users`` of packed ``vectors`` as a bit for each campaign (the driver holds the campaigns), and the number of campaigns."""
    c = campaigns.select("campaign_id", code(F.col("feature")).alias("code"), "min_weight").toPandas().sort_values(["code", "campaign_id"])
    names, which = np.unique(c["campaign_id"].astype(str).to_numpy(), return_inverse=True)
    need = np.bincount(which, minlength=len(names))
    feature, least, n = c["code"].to_numpy(np.int64), c["min_weight"].to_numpy(np.float64), max(len(names), 1)

    def run(batches):
        for whole in batches:
            for b in _slices(whole, 200_000):
                s = Sparse.of(b.column("code"), b.column("weight"))
                low = np.searchsorted(feature, s.code)
                count = np.searchsorted(feature, s.code, side="right") - low
                entry = np.repeat(np.arange(len(s.code)), count)
                asked = np.arange(len(entry)) - np.repeat(np.cumsum(count) - count, count) + np.repeat(low, count)
                enough = s.weight[entry] >= least[asked]
                row = np.repeat(np.arange(b.num_rows), np.diff(s.ptr))[entry[enough]]
                out = []
                for a in range(0, b.num_rows, step := max(1, 4_000_000 // n)):
                    here = (row >= a) & (row < a + step)
                    size = min(step, b.num_rows - a)
                    hits = np.bincount((row[here] - a) * n + which[asked[enough][here]], minlength=size * n).reshape(size, n)
                    out += [x.tobytes() for x in np.packbits((hits[:, : len(need)] == need) & (hits[:, : len(need)] > 0), axis=1)]
                yield pa.RecordBatch.from_pydict({"user_id": b.column("user_id"), "bits": pa.array(out, pa.binary())})

    return vectors.select("user_id", "code", "weight").mapInArrow(run, "user_id long, bits binary"), len(names)


def counts_by_bits(assign: DataFrame, bits: DataFrame, campaigns: int, theta: float = 0.5, buckets: int = 1) -> DataFrame:
    """run, campaign, tp, audience, wanted of many assignments (run, user_id, cohort_id) by the 'share' rule; ``bits``: see ``match_bits``.

    Cohorts are dealt to ``buckets`` of a run, whose members' bits are summed in a task, so no pair of user and campaign is a row.
    """
    def run(t: pa.Table) -> pa.Table:
        cohort = t.column("cohort_id").combine_chunks().dictionary_encode().indices.to_numpy()
        by = np.argsort(cohort, kind="stable")
        size, members = np.bincount(cohort), t.column("bits").combine_chunks()
        ends, total = np.cumsum(size), np.zeros((3, campaigns), np.int64)
        at = 0
        while at < len(size):  # some cohorts at a time
            to = max(at + 1, int(np.searchsorted(ends, ends[at] - size[at] + 20_000, side="right")))
            start = ends[at] - size[at]
            have = members.take(pa.array(by[start : ends[to - 1]])).to_pylist()
            have = np.frombuffer(b"".join(x or bytes(-(-campaigns // 8)) for x in have), np.uint8).reshape(len(have), -1)
            n = np.add.reduceat(np.unpackbits(have, axis=1, count=campaigns), ends[at:to] - size[at:to] - start, axis=0, dtype=np.int64)
            hit = (n > 0) & (n >= theta * size[at:to, None])
            total += np.stack([np.where(hit, n, 0).sum(0), (hit * size[at:to, None]).sum(0), n.sum(0)])
            at = to
        some = np.flatnonzero(total[2])
        return pa.table({"run": pa.array(np.full(len(some), t.column("run")[0].as_py(), np.int32)), "campaign": pa.array(some.astype(np.int32)), **dict(zip(("tp", "audience", "wanted"), map(pa.array, total[:, some])))})

    x = assign.join(bits, "user_id", "left").withColumn("bucket", F.pmod(F.xxhash64("cohort_id"), F.lit(buckets)).cast("int"))
    part = x.groupBy("run", "bucket").applyInArrow(run, "run int, campaign int, tp long, audience long, wanted long")
    return part.groupBy("run", "campaign").agg(*[F.sum(c).alias(c) for c in ("tp", "audience", "wanted")])


def match_cohorts(matches: DataFrame, assign: DataFrame, rule: str = "share", theta: float = 0.5) -> DataFrame:
    """campaign_id, cohort_id, matched, members, hit: by 'share' of matched members, 'any' or 'all'."""
    j = matches.join(assign, "user_id").groupBy("campaign_id", "cohort_id").agg(F.count("*").alias("matched")).join(sizes(assign), "cohort_id")
    hit = {"share": F.col("matched") >= theta * F.col("members"), "any": F.col("matched") >= 1, "all": F.col("matched") == F.col("members")}[rule]
    return j.select("campaign_id", "cohort_id", "matched", "members", hit.alias("hit"))


def match_cohorts_by_score(campaigns: DataFrame, identity: DataFrame, tau: float, max_broadcast: int = 1_000_000) -> DataFrame:
    """campaign_id, cohort_id, score, members, hit: the inner product of ``campaigns`` (campaign_id, feature, weight) and each cohort's mean weights, at least ``tau``."""
    c = campaigns.select("campaign_id", "feature", "weight")
    c = F.broadcast(c) if c.limit(max_broadcast + 1).count() <= max_broadcast else c
    s = identity.join(c, "feature").groupBy("campaign_id", "cohort_id").agg(F.sum(F.col("mean_weight") * F.col("weight")).alias("score"), F.max("members").alias("members"))
    return s.select("campaign_id", "cohort_id", "score", "members", (F.col("score") >= tau).alias("hit"))


def campaign_counts(cohorts: DataFrame) -> DataFrame:
    """tp, fp, fn, audience and recall of each campaign from ``match_cohorts``; no campaign x user product."""
    on = lambda x: F.sum(F.when(F.col("hit"), x).otherwise(0))
    c = cohorts.groupBy("campaign_id").agg(on(F.col("matched")).alias("tp"), on(F.col("members") - F.col("matched")).alias("fp"), F.sum(F.when(~F.col("hit"), F.col("matched")).otherwise(0)).alias("fn"))
    return c.withColumn("audience", F.col("tp") + F.col("fp")).withColumn("recall", F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0)))


def recalls(counts: DataFrame) -> DataFrame:
    """micro_recall (mean of campaigns), macro_recall (pooled), precision (pooled), campaigns."""
    return counts.agg(F.avg("recall").alias("micro_recall"), (F.sum("tp") / F.nullif(F.sum(F.col("tp") + F.col("fn")), F.lit(0))).alias("macro_recall"), (F.sum("tp") / F.nullif(F.sum("audience"), F.lit(0))).alias("precision"), F.count("*").alias("campaigns"))


def recall_by_audience(counts: DataFrame, bands: int = 4) -> DataFrame:
    """Pooled and mean recall by band of the audience that a campaign asks for (tp + fn). The window holds one row a campaign."""
    banded = counts.withColumn("band", F.ntile(bands).over(Window.orderBy(F.col("tp") + F.col("fn"), "campaign_id")))
    return banded.groupBy("band").agg(F.avg("recall").alias("micro_recall"), (F.sum("tp") / F.sum(F.col("tp") + F.col("fn"))).alias("macro_recall"), F.count("*").alias("campaigns"))


def size_cdf(assign: DataFrame) -> DataFrame:
    """members, cohorts, cdf: the empirical distribution of cohort sizes (one row per size)."""
    n = sizes(assign).groupBy("members").agg(F.count("*").alias("cohorts"))
    w = Window.orderBy("members").rowsBetween(Window.unboundedPreceding, 0)
    return n.select("members", "cohorts", (F.sum("cohorts").over(w) / F.sum("cohorts").over(Window.partitionBy())).alias("cdf"))


def size_percentiles(assign: DataFrame, k: int) -> DataFrame:
    q = lambda p: F.percentile("members", F.lit(p))
    return sizes(assign).agg(F.min("members").alias("least"), q(0.5).alias("p50"), q(0.95).alias("p95"), q(0.99).alias("p99"), F.max("members").alias("most"), F.avg(F.when(F.col("members").between(k, 2 * k), 1.0).otherwise(0.0)).alias("in_band"))


def anonymity_audit(assign: DataFrame, users: DataFrame, k: int) -> DataFrame:
    """One row: least size, cohorts and users below ``k``, users missing and doubled, re-identification mean and most."""
    s = sizes(assign).agg(F.min("members").alias("least"), F.sum((F.col("members") < k).cast("long")).alias("cohorts_below"), F.sum(F.when(F.col("members") < k, F.col("members")).otherwise(0)).alias("users_below"), F.avg(1 / F.col("members")).alias("risk_mean"), F.max(1 / F.col("members")).alias("risk_most"))
    missing = users.join(assign, "user_id", "left_anti").agg(F.count("*").alias("missing"))
    doubled = assign.groupBy("user_id").count().where("count > 1").agg(F.count("*").alias("doubled"))
    return s.crossJoin(missing).crossJoin(doubled)  # one row each


def retrieve(impressions: DataFrame, assign: DataFrame, cohorts: DataFrame) -> DataFrame:
    """Impressions to their cohort's matched campaigns; no user id comes out."""
    return impressions.join(assign, "user_id").join(cohorts.where("hit").select("campaign_id", "cohort_id"), "cohort_id").select("impression_id", "cohort_id", "campaign_id")


def cohort_conversions(conversions: DataFrame, assign: DataFrame, k: int) -> DataFrame:
    """Counts by cohort; cohorts below ``k`` are refused."""
    ok = sizes(assign).where(F.col("members") >= k).select("cohort_id")
    return conversions.join(assign, "user_id").join(ok, "cohort_id", "left_semi").groupBy("cohort_id").agg(F.count("*").alias("conversions"))


def within_similarity(assign: DataFrame, v: DataFrame, p: float = 1.0, seed: int = 7) -> DataFrame:
    """Mean kernel of pairs of neighbours in each cohort's seeded order, and of pairs over all users: one pair a user."""
    from .similarity import minmax_kernel

    a = assign.withColumn("o", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("user_id").cast("string"))))
    inner = a.withColumn("b", F.lead("user_id").over(Window.partitionBy("cohort_id").orderBy("o"))).where("b is not null").select(F.col("user_id").alias("a"), "b")
    outer = a.withColumn("g", F.substring("o", 1, 2)).withColumn("b", F.lead("user_id").over(Window.partitionBy("g").orderBy("o"))).where("b is not null").select(F.col("user_id").alias("a"), "b")
    mean = lambda pairs, name: minmax_kernel(v, pairs, p).agg(F.avg("similarity").alias("similarity")).select(F.lit(name).alias("pairs"), "similarity")
    return mean(inner, "within").unionByName(mean(outer, "any"))
