"""Nearest neighbours from hash tables: bands of slots are bucket keys."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import fits, shared_write
from .similarity import minmax_kernel


def bucket_index(h: DataFrame, bands: int, rows: int) -> DataFrame:
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.array_join(F.transform(F.slice("sig", b * rows + 1, rows), lambda x: x.cast("string")), ","))
    return h.select("user_id", F.posexplode(keys).alias("band", "bucket"))


def bucket_query(index: DataFrame, queries: DataFrame, v: DataFrame, k: int, p: float = 1.0) -> DataFrame:
    """a (query), b, similarity, place: the k most similar of those that share a bucket, reranked exactly."""
    q = index.join(queries, "user_id", "left_semi").withColumnRenamed("user_id", "a")
    pairs = q.join(index.withColumnRenamed("user_id", "b"), ["band", "bucket"]).where("a <> b").select("a", "b").distinct()
    w = Window.partitionBy("a").orderBy(F.desc("similarity"), "b")
    return minmax_kernel(v, pairs, p).withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def exact_neighbours(v: DataFrame, queries: DataFrame, k: int, p: float = 1.0) -> DataFrame:
    """The same by brute force over users that share a feature (what the tables avoid)."""
    x = v.join(queries, "user_id", "left_semi").select(F.col("user_id").alias("a"), "feature")
    pairs = x.join(v.select(F.col("user_id").alias("b"), "feature"), "feature").where("a <> b").select("a", "b").distinct()
    w = Window.partitionBy("a").orderBy(F.desc("similarity"), "b")
    return minmax_kernel(v, pairs, p).withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def nearest(index: DataFrame, queries: DataFrame, v: DataFrame, k: int, p: float = 1.0) -> DataFrame:
    """``bucket_query``, and ``exact_neighbours`` for the queries that share buckets with fewer than ``k``."""
    found = shared_write(bucket_query(index, queries, v, k, p), "nearest")
    short = queries.join(found.where(F.col("place") == k).select(F.col("a").alias("user_id")), "user_id", "left_anti")
    rest = exact_neighbours(v, short, k, p)
    return found.join(short.withColumnRenamed("user_id", "a"), "a", "left_anti").select(rest.columns).unionByName(rest)


def set_search(docs: DataFrame, rows: int, k: int, every: int = 20, parts: int = 12, each: int = 50_000) -> DataFrame:
    """a (a query: its id is a multiple of ``every``), b, similarity, shared: of sets ``docs`` (user_id, code, sig), what the ``k`` nearest need.

    Documents are dealt to groups (at least ``parts``, of about ``each`` of the ``rows`` rows at most), queries go to every group,
    all in one pass over ``docs``, so no pair is a row and no set is made twice. A task takes intersections from a matrix product over common features and from
    posting lists over the others. Each group gives, for a query, its ``k`` most similar with a common feature
    and its ``k`` most similar with an equal slot (``shared``), both exact; ``k_nearest`` unites groups.
    """
    groups, asked = max(parts, -(-rows // each)), max(1, -(-rows // (every * each)))
    deal = lambda n, salt: F.pmod(F.xxhash64("user_id", F.lit(salt)), F.lit(n)).cast("int")
    cells = lambda n, cell: F.transform(F.sequence(F.lit(0), F.lit(n - 1)), cell)
    place = lambda group, part, asks: F.struct(group.alias("group"), part.alias("asked"), F.lit(asks).alias("asks"))
    kept = cells(asked, lambda i: place(deal(groups, 0), i, False))
    sent = cells(groups, lambda i: place(i, deal(asked, 1), True))
    to = F.when(F.col("user_id") % every == 0, F.concat(kept, sent)).otherwise(kept)
    x = docs.where("user_id is not null").select("user_id", "code", "sig", F.explode(to).alias("to")).select("user_id", "code", "sig", "to.*")

    def run(t: pa.Table) -> pa.Table:
        asks = t.column("asks")
        d, q = t.filter(pc.invert(asks)).combine_chunks(), t.filter(asks).combine_chunks()
        found = list(_nearest_here(d, q, k)) if d.num_rows and q.num_rows else []
        a, b, s, same = (np.concatenate(x) for x in zip(*found)) if found else ([], [], [], [])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "similarity": pa.array(s, pa.float64()), "shared": pa.array(same, pa.bool_())})

    return x.repartition(4 * groups * asked, "group", "asked").groupBy("group", "asked").applyInArrow(run, "a long, b long, similarity double, shared boolean")


def _flat(t: pa.Table, name: str) -> tuple[np.ndarray, np.ndarray]:
    x = t.column(name).chunk(0)
    ptr = x.offsets.to_numpy().astype(np.int64)
    return x.values.to_numpy()[ptr[0] : ptr[-1]], ptr - ptr[0]


def _nearest_here(d: pa.Table, q: pa.Table, k: int, share: float = 0.1, pool: int = 3):
    """Queries' rows of ``set_search`` in one group. Features of more than ``share`` of the documents are common; pools start at ``pool`` times ``k``."""
    ids, asking = d.column("user_id").to_numpy(), q.column("user_id").to_numpy()
    (dc, dp), (qc, qp) = _flat(d, "code"), _flat(q, "code")
    ds, qs = _flat(d, "sig")[0].reshape(len(ids), -1), _flat(q, "sig")[0].reshape(len(asking), -1)
    n, dt, qt = len(ids), np.diff(dp), np.diff(qp)
    names, qf = np.unique(qc, return_inverse=True)
    df = np.minimum(np.searchsorted(names, dc), len(names) - 1)
    hit = names[df] == dc
    df, doc = df[hit], np.repeat(np.arange(n), dt)[hit]
    count = np.bincount(df, minlength=len(names))
    common = np.flatnonzero(count > share * n)
    place = np.full(len(names), -1)
    place[common] = np.arange(len(common))
    dense = np.zeros((n, len(common)), np.float32)
    heavy = place[df] >= 0
    dense[doc[heavy], place[df[heavy]]] = 1
    df, doc = df[~heavy], doc[~heavy]
    doc = doc[np.argsort(df, kind="stable")]
    start = np.concatenate(([0], np.cumsum(np.where(place >= 0, 0, count))))
    step = max(1, 4_000_000 // n)
    for low in range(0, len(asking), step):
        high = min(low + step, len(asking))
        f, row = qf[qp[low] : qp[high]], np.repeat(np.arange(high - low), qt[low:high])
        mine = np.zeros((high - low, len(common)), np.float32)
        here = place[f] >= 0
        mine[row[here], place[f[here]]] = 1
        both = mine @ dense.T
        for i in range(low, high):
            f = qf[qp[i] : qp[i + 1]]
            lists = [doc[start[x] : start[x + 1]] for x in f[place[f] < 0].tolist()]
            m = both[i - low].astype(np.int64)
            if lists:
                m += np.bincount(np.concatenate(lists), minlength=n)
            s = m / (dt + qt[i] - m)
            s[ids == asking[i]] = -1
            size = pool * k
            while True:
                if size < n:
                    at = np.flatnonzero(s >= max(np.partition(s, n - size)[n - size], 0))  # ties of the last one too
                else:
                    at = np.flatnonzero(s >= 0)
                same = (ds[at] == qs[i]).any(axis=1)
                if size >= n or same.sum() >= k:
                    break
                size *= 8
            order = np.lexsort((ids[at], -s[at]))
            order = order[(np.cumsum(same[order]) <= k) & same[order] | (np.arange(len(order)) < k) & (s[at][order] > 0)]
            at, same = at[order], same[order]
            yield np.full(len(at), asking[i]), ids[at], s[at], same


def k_nearest(rows: DataFrame, k: int) -> DataFrame:
    """a, b, similarity, place: the ``k`` most similar of each a; ties to the smaller b."""
    w = Window.partitionBy("a").orderBy(F.desc("similarity"), "b")
    return rows.select("a", "b", "similarity", F.row_number().over(w).alias("place")).where(F.col("place") <= k)


def nearest_sets(found: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """``nearest`` and ``exact_neighbours`` of sets from the rows of ``set_search``."""
    near, exact = k_nearest(found.where("shared"), k), k_nearest(found.where("similarity > 0"), k)
    full = near.where(F.col("place") == k).select("a")
    return near.join(full, "a", "left_semi").unionByName(exact.join(full, "a", "left_anti")), exact


def neighbour_recall(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    hit = exact.join(approximate.select("a", "b").withColumn("hit", F.lit(1)), ["a", "b"], "left")
    return hit.agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("recall"), F.count("*").alias("wanted"))


def similar_pairs(h: DataFrame, v: DataFrame, threshold: float, bands: int, rows: int, p: float = 1.0) -> DataFrame:
    """a < b, similarity: pairs of at least ``threshold`` among those that share a bucket, equal vectors as one.

    Users with equal vectors are a class, and only the class's smallest user enters the tables, so a
    large group of copies is one entry and not all its pairs. ``duplicates`` gives the members.
    """
    kept = duplicates(v)
    heads = kept.where("user_id = head").select("user_id")
    index = bucket_index(h.join(heads, "user_id", "left_semi"), bands, rows)
    pairs = index.withColumnRenamed("user_id", "a").join(index.withColumnRenamed("user_id", "b"), ["band", "bucket"]).where("a < b").select("a", "b").distinct()
    return minmax_kernel(v, pairs, p).where(F.col("similarity") >= threshold)


def similar_sets(docs: DataFrame, threshold: float, bands: int, rows: int, words: int = 8) -> DataFrame:
    """``similar_pairs`` of sets ``docs`` (user_id, code, sig), p = 1.

    A bucket's rows hold a set's size and a bitmap of 64 ``words`` bits, not the set. Bits that two bitmaps do not share are
    features that the sets do not share, so sizes and bitmaps drop only pairs below ``threshold``; the sets of the others meet.
    """
    docs = shared_write(docs.where("user_id is not null"), "sets")
    narrow = docs.mapInArrow(_bitmaps(words), "user_id long, size int, bits array<long>, sig array<long>, fp string")
    bucket = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.xxhash64(i, F.slice("sig", i * rows + 1, rows)))
    keys = shared_write(narrow.select("user_id", "size", "bits", "fp", bucket.alias("buckets")), "narrow")
    heads = keys.groupBy("fp").agg(F.min_by(F.struct("user_id", "size", "bits", "buckets"), "user_id").alias("h"))
    index = heads.select("h.user_id", F.explode("h.buckets").alias("bucket"), "h.size", "h.bits")
    x, y = index.toDF("a", "bucket", "na", "xa"), index.toDF("b", "bucket", "nb", "xb")
    apart = F.aggregate(F.zip_with("xa", "xb", lambda s, t: F.bit_count(s.bitwiseXOR(t))), F.lit(0), lambda s, t: s + t)
    most = (F.col("na") + F.col("nb")) * (1 - threshold) / (1 + threshold) + 1e-6
    pairs = x.join(y, "bucket").where((F.col("a") < F.col("b")) & (F.abs(F.col("na") - F.col("nb")) <= most)).where(apart <= most).select("a", "b").distinct()
    pairs = shared_write(pairs, "pairs")
    some = pairs.select(F.explode(F.array("a", "b")).alias("user_id")).distinct()
    sets = docs.join(F.broadcast(some) if fits(some, 1_000_000) else some, "user_id", "left_semi").select("user_id", "code")
    both = pairs.join(sets.toDF("a", "ca"), "a").join(sets.toDF("b", "cb"), "b")
    m = F.size(F.array_intersect("ca", "cb"))
    both = both.select("a", "b", (m / (F.size("ca") + F.size("cb") - m)).alias("similarity"))
    return both.where(F.col("similarity") >= threshold)


def _bitmaps(words: int):
    def run(batches):
        for b in batches:
            x = b.column("code")
            ptr = x.offsets.to_numpy().astype(np.int64)
            bit = x.values.to_numpy()[ptr[0] : ptr[-1]] % (64 * words)
            bits = np.zeros((b.num_rows, words), np.uint64)
            np.bitwise_or.at(bits, (np.repeat(np.arange(b.num_rows), np.diff(ptr)), bit // 64), np.uint64(1) << (bit % 64).astype(np.uint64))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * words), pa.array(bits.ravel().view(np.int64)))
            at, flat = ptr - ptr[0], x.values.to_numpy()[ptr[0] : ptr[-1]]
            fp = [hashlib.sha256(flat[i:j].tobytes()).hexdigest() for i, j in zip(at[:-1].tolist(), at[1:].tolist())]
            yield pa.RecordBatch.from_pydict({"user_id": b.column("user_id"), "size": pa.array(np.diff(ptr).astype(np.int32)), "bits": lists, "sig": b.column("sig"), "fp": pa.array(fp)})

    return run


def duplicates(v: DataFrame) -> DataFrame:
    """user_id, head: the smallest user with the same vector."""
    cell = F.struct("feature", "weight")
    same = v.groupBy("user_id").agg(F.sha2(F.to_json(F.sort_array(F.collect_list(cell))), 256).alias("fp"))
    same = shared_write(same, "fingerprints")
    return same.join(same.groupBy("fp").agg(F.min("user_id").alias("head")), "fp").select("user_id", "head")
