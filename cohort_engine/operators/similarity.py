"""Exact kernels of vector pairs and estimators from signatures."""

from __future__ import annotations

import math

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData
from pyspark.sql import functions as F

from .hashing import Sparse


def minmax_kernel(v: DataFrame, pairs: DataFrame, p: float = 1.0) -> DataFrame:
    """a, b, similarity of ``pairs`` (a, b): sum of minima over sum of maxima of p-th powers.

    Maxima come from sums (max = x + y - min), so an inner join over shared features is enough.
    """
    w = v.withColumn("w", F.pow("weight", F.lit(p)))
    total = w.groupBy("user_id").agg(F.sum("w").alias("t"))
    x = pairs.join(w.select(F.col("user_id").alias("a"), "feature", F.col("w").alias("x")), "a")
    both = x.join(w.select(F.col("user_id").alias("b"), "feature", F.col("w").alias("y")), ["b", "feature"]).groupBy("a", "b").agg(F.sum(F.least("x", "y")).alias("m"))
    j = pairs.join(both, ["a", "b"], "left").join(total.select(F.col("user_id").alias("a"), F.col("t").alias("ta")), "a").join(total.select(F.col("user_id").alias("b"), F.col("t").alias("tb")), "b")
    m = F.coalesce("m", F.lit(0.0))
    return j.select("a", "b", (m / (F.col("ta") + F.col("tb") - m)).alias("similarity"))


def similarity_join(v: DataFrame, threshold: float, p: float = 1.0, max_users: int = 20_000) -> DataFrame:
    """a < b, similarity of all pairs with a kernel of at least ``threshold`` (above 0, so they share a feature).

    The kernel is at most the smaller sum over the larger one, which drops pairs before their minima are
    summed. Users that share a feature meet, so more than ``max_users`` is refused.
    """
    if threshold <= 0:
        raise ValueError("the threshold must be above 0")
    if v.select("user_id").distinct().limit(max_users + 1).count() > max_users:
        raise ValueError(f"the similarity join is refused above {max_users} users")
    w = v.select("user_id", "feature", F.pow("weight", F.lit(p)).alias("w"))
    w = w.join(w.groupBy("user_id").agg(F.sum("w").alias("t")), "user_id")
    x, y = w.toDF("a", "feature", "x", "ta"), w.toDF("b", "feature", "y", "tb")
    bound = F.least("ta", "tb") >= (threshold - 1e-9) * F.greatest("ta", "tb")
    both = x.join(y, "feature").where((F.col("a") < F.col("b")) & bound)
    both = both.groupBy("a", "b").agg(F.sum(F.least("x", "y")).alias("m"), F.first("ta").alias("ta"), F.first("tb").alias("tb"))
    return both.select("a", "b", (F.col("m") / (F.col("ta") + F.col("tb") - F.col("m"))).alias("similarity")).where(F.col("similarity") >= threshold)


def neighbour_counts(vectors: DataFrame, rows: int, threshold: float, p: float = 1.0, each: int = 8_000) -> DataFrame:
    """user_id, neighbours: how many other users have a kernel of at least ``threshold`` (above 0); users without one are left out. Arguments as in ``near_forest``."""

    def run(t: pa.Table) -> pa.Table:
        m = _Meeting(t, threshold, p)
        n = np.zeros(len(m.ids), np.int64)
        for row, hit in m.links():
            n[row] += len(hit)
            n[hit] += 1
        return pa.table({"user_id": pa.array(m.ids[n > 0], pa.int64()), "neighbours": pa.array(n[n > 0])})

    return _meetings(vectors, rows, threshold, each).applyInArrow(run, "user_id long, neighbours long").groupBy("user_id").agg(F.sum("neighbours").alias("neighbours"))


def near_forest(vectors: DataFrame, rows: int, threshold: float, p: float = 1.0, each: int = 8_000) -> DataFrame:
    """a, b, similarity: links (pairs with a kernel of at least ``threshold``, above 0) that join exactly the users that all links join.

    ``vectors`` (user_id, code, weight: parallel arrays) are dealt to shards of about ``each`` of the
    ``rows`` users. Every two shards, and every shard with itself, meet in a task, which compares each pair of
    users whatever the threshold is; of the links, one for each two groups that it joins leaves the task.
    With a column ``core`` only cores join, and all links of a core with another user leave too: at most as
    many for that user as a core has to have. Numbers of links are those of ``neighbour_counts``.
    """
    own = "core" in vectors.columns

    def run(t: pa.Table) -> pa.Table:
        m = _Meeting(t, threshold, p)
        core = m.table.column("core").to_numpy(zero_copy_only=False) if own else np.ones(len(m.ids), bool)
        group, found = np.arange(len(m.ids)), []
        for row, hit in m.links():
            inside = core[hit]
            kept = hit[~inside] if core[row] else hit[inside]
            if core[row] and (group[hit[inside]] != group[row]).any():
                others, at = np.unique(group[hit[inside]], return_index=True)
                kept = np.concatenate((kept, hit[inside][at[others != group[row]]]))
                into = np.arange(len(group))
                into[others] = group[row]
                group = into[group]
            if len(kept):
                found.append((np.full(len(kept), m.ids[row]), m.ids[kept], m.similarity(row, kept)))
        a, b, s = (np.concatenate(c) for c in zip(*found)) if found else ([], [], [])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "similarity": pa.array(s, pa.float64())})

    return _meetings(vectors, rows, threshold, each).applyInArrow(run, "a long, b long, similarity double")


def _meetings(vectors: DataFrame, rows: int, threshold: float, each: int) -> GroupedData:
    """``vectors`` by the two shards i <= j that meet; each user is sent once to each shard."""
    if threshold <= 0:
        raise ValueError("the threshold must be above 0")
    shards = max(4, -(-rows // each))
    x = vectors.where("user_id is not null").withColumn("shard", F.pmod(F.xxhash64("user_id"), F.lit(shards)).cast("int"))
    x = x.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
    x = x.withColumns({"i": F.least("shard", "other"), "j": F.greatest("shard", "other")}).drop("other")
    return x.repartition(2 * shards * (shards + 1), "i", "j").groupBy("i", "j")


class _Meeting:
    """The users of two shards, or of one; ``links`` compares every user of the first with every user of the second, or with those after it.

    Kernels are bounded first, in whole numbers of 16 bits: weights rounded down, so that a sum of minima is short
    by less than one for each feature. Pairs that this leaves open get their kernel in doubles. Users with a
    feature twice (each of its weights meets each of the other user's) always do.
    """

    def __init__(self, t: pa.Table, threshold: float, p: float):
        self.table = t = t.combine_chunks()
        self.ids, self.threshold = t.column("user_id").to_numpy(), threshold
        s = Sparse.of(t.column("code").chunk(0), t.column("weight").chunk(0))
        self.ptr, self.col, self.weight, self.names = s.ptr, s.col, s.weight**p, len(s.names)
        self.row = np.repeat(np.arange(len(self.ids)), np.diff(self.ptr))
        self.total = np.bincount(self.row, weights=self.weight, minlength=len(self.ids))
        cell = np.sort(self.row * self.names + self.col)
        self.twice = np.zeros(len(self.ids), bool)
        self.twice[cell[1:][cell[1:] == cell[:-1]] // max(self.names, 1)] = True
        shard, i, j = t.column("shard").to_numpy(), t.column("i")[0].as_py(), t.column("j")[0].as_py()
        by = np.argsort(self.total, kind="stable")
        self.first, self.second, self.same = by[shard[by] == i], by[shard[by] == j], i == j
        self.mine = np.zeros(self.names)

    def similarity(self, row: int, others: np.ndarray) -> np.ndarray:
        """Kernels of one user with others."""
        count = self.ptr[others + 1] - self.ptr[others]
        take = np.arange(count.sum()) + np.repeat(self.ptr[others] - np.cumsum(count) + count, count)
        at, col, w, m = np.repeat(np.arange(len(others)), count), self.col[take], self.weight[take], np.zeros(len(others))
        left = np.arange(self.ptr[row], self.ptr[row + 1])
        while len(left):
            names, once = np.unique(self.col[left], return_index=True)
            self.mine[names] = self.weight[left[once]]
            m += np.bincount(at, weights=np.minimum(self.mine[col], w), minlength=len(others))
            self.mine[names] = 0
            left = np.delete(left, once)
        return m / (self.total[others] + self.total[row] - m)

    def links(self) -> Iterator[tuple[int, np.ndarray]]:
        """Each user of the first shard that has links, with the users linked to it."""
        first, second, n = self.first, self.second, len(self.second)
        place = np.full(len(self.ids), -1)
        place[second] = np.arange(n)
        e = np.flatnonzero((place[self.row] >= 0) & ~self.twice[self.row])
        e = e[np.argsort(self.col[e], kind="stable")]
        start = np.searchsorted(self.col[e], np.arange(self.names + 1))
        common = np.flatnonzero(np.diff(start) * 8 >= max(n, 1))  # at most eight times the features of a user
        full = np.zeros((len(common), n))
        for k, c in enumerate(common.tolist()):
            full[k, place[self.row[e[start[c] : start[c + 1]]]]] = self.weight[e[start[c] : start[c + 1]]]
        at, share, always = np.full(self.names, -1), self.threshold / (1 + self.threshold), self.twice[second]
        at[common] = np.arange(len(common))
        first = first[self.total[first] > 0]
        room = np.empty(max(1, len(common) * n), np.uint16)
        size = np.frexp(self.total[first])[1]  # users of one power of two have one scale
        for power in np.unique(size).tolist():
            some = first[size == power]
            scale = 65_000 / self.total[some].max()
            small = lambda x: np.minimum(np.floor(x * scale), 65_535).astype(np.uint16)  # noqa: B023, E731
            table, weights, need = small(full), small(self.weight), share * scale * self.total[second]
            for row in some.tolist():
                after = place[row] + 1 if self.same else 0
                mine = slice(self.ptr[row], self.ptr[row + (not self.twice[row])])
                col, w = self.col[mine], weights[mine]
                k = at[col]
                held = k[k >= 0]
                both = room[: len(held) * (n - after)].reshape(len(held), n - after)
                both[:] = w[k >= 0, None]
                low = np.add.reduce(np.minimum(table[held, after:], both, out=both), axis=0, dtype=np.uint16)
                for c, x in zip(col[k < 0].tolist(), w[k < 0]):
                    them = e[start[c] : start[c + 1]]
                    spot = place[self.row[them]] - after
                    low[spot[spot >= 0]] += np.minimum(weights[them[spot >= 0]], x)
                gap = low - (need[after:] + share * scale * self.total[row])
                hit = gap >= 0.01
                open_ = (gap >= -0.01 - len(col)) & ~hit | always[after:] | self.twice[row]
                more = np.flatnonzero(open_)
                if len(more):
                    hit[more] = self.similarity(row, second[after:][more]) >= self.threshold
                if hit.any():
                    yield row, second[after:][hit]


def kernel_matrix(v: DataFrame, p: float = 1.0, max_users: int = 5_000) -> DataFrame:
    """a, b, similarity of all pairs that share a feature, both ways, and of each user with itself; more than ``max_users`` are refused."""
    if v.select("user_id").distinct().limit(max_users + 1).count() > max_users:
        raise ValueError(f"the kernel matrix is refused above {max_users} users")
    w = v.select("user_id", "feature", F.pow("weight", F.lit(p)).alias("w"))
    t = w.groupBy("user_id").agg(F.sum("w").alias("t"))
    both = w.toDF("a", "feature", "x").join(w.toDF("b", "feature", "y"), "feature").groupBy("a", "b").agg(F.sum(F.least("x", "y")).alias("m"))
    j = both.join(t.toDF("a", "ta"), "a").join(t.toDF("b", "tb"), "b")
    return j.select("a", "b", (F.col("m") / (F.col("ta") + F.col("tb") - F.col("m"))).alias("similarity"))


def least_eigenvalue(matrix: DataFrame) -> float:
    """Of a small kernel matrix (the rows of ``kernel_matrix``): not below 0 for a positive definite kernel."""
    import numpy as np

    t = matrix.toPandas()
    ids = {u: i for i, u in enumerate(sorted(set(t["a"])))}
    m = np.zeros((len(ids), len(ids)))
    m[t["a"].map(ids), t["b"].map(ids)] = t["similarity"]
    return float(np.linalg.eigvalsh(m)[0])


def collision_report(h_full: DataFrame, h_feature: DataFrame, v: DataFrame, pairs: DataFrame, p: float) -> DataFrame:
    """key, pairs, bias, rmse: collision rates of the full key and of the feature alone against the kernel."""
    exact = minmax_kernel(v, pairs, p)
    row = lambda h, name: estimation_error(estimate(h, pairs), exact).select(F.lit(name).alias("key"), "*")
    return row(h_full, "feature_level").unionByName(row(h_feature, "feature"))


def cosine(v: DataFrame, pairs: DataFrame) -> DataFrame:
    norm = v.groupBy("user_id").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("t"))
    x = pairs.join(v.select(F.col("user_id").alias("a"), "feature", F.col("weight").alias("x")), "a")
    both = x.join(v.select(F.col("user_id").alias("b"), "feature", F.col("weight").alias("y")), ["b", "feature"]).groupBy("a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("m"))
    j = pairs.join(both, ["a", "b"], "left").join(norm.select(F.col("user_id").alias("a"), F.col("t").alias("ta")), "a").join(norm.select(F.col("user_id").alias("b"), F.col("t").alias("tb")), "b")
    return j.select("a", "b", (F.coalesce("m", F.lit(0.0)) / F.col("ta") / F.col("tb")).alias("similarity"))


def estimate(h: DataFrame, pairs: DataFrame, bits: int | None = None, angle: bool = False) -> DataFrame:
    """Share of equal slots of ``h`` (user_id, sig); ``bits`` corrects b-bit slots, ``angle`` maps sign matches to a cosine."""
    x, y = h.select(F.col("user_id").alias("a"), F.col("sig").alias("x")), h.select(F.col("user_id").alias("b"), F.col("sig").alias("y"))
    j = pairs.join(x, "a").join(y, "b")
    same = F.aggregate(F.zip_with("x", "y", lambda s, t: s.eqNullSafe(t).cast("double")), F.lit(0.0), lambda a, s: a + s) / F.size("x")
    if bits:
        same = (same - 2.0**-bits) / (1 - 2.0**-bits)
    if angle:
        same = F.cos(math.pi * (1 - same))
    return j.select("a", "b", same.alias("estimate"))


def estimation_error(estimates: DataFrame, exact: DataFrame) -> DataFrame:
    e = F.col("estimate") - F.col("similarity")
    return estimates.join(exact, ["a", "b"]).agg(F.count("*").alias("pairs"), F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"))
