"""Repeated substrings by merging shard Burrows-Wheeler transforms; exact, matches stay inside documents.

Every 100-byte window has a minimizer: the smallest hash of its 32-byte grams, leftmost first. Equal
windows have equal minimizers at equal offsets, so a window can repeat only if its minimizer gram
does. Runs of windows with one minimizer are the unit: runs whose gram occurs once are dropped
(a fixed-size bit filter over the counted grams; false positives cost time only), equal runs are
one class with its first occurrence, and grams with several classes go on.

A task holds the classes of many grams as texts. Texts are cut into shards; each shard is sorted once
for its BWT and LF mapping. ``merge`` then refines the interleaving of all shards one symbol at a
time, only by stable counting over BWT symbols, and carries the block boundaries along: after h
rounds a block is a set of suffixes with a common prefix of at least h. Blocks at depth 100 are the
repeated intervals; in each, every occurrence but the first (doc_id, start) is removed. Grams with
more than ``max_classes`` classes are split by the windows' own hashes instead (exact as well).

Edge cases: null and empty texts have 0 bytes; texts shorter than the window lose nothing; of equal
documents the smallest id keeps its bytes; ids are expected to be keys; an empty table gives an
empty result; texts are read whole; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BitFilter, hash_longs, join_small, materialise

WINDOW, GRAM = 100, 32
_MIX = (np.random.default_rng(99).integers(0, 2**63, 256, dtype=np.int64).astype(np.uint64) << np.uint64(1)) | np.uint64(1)


def gram_hashes(b: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """64-bit hash of every ``gram``-byte string (``gram`` a power of two)."""
    h, n, m = _MIX[b], 1, 0x9E3779B97F4A7C15
    while n < gram:
        h = h[:-n] * np.uint64(m) + h[n:]
        n, m = 2 * n, m * m & 0xFFFFFFFFFFFFFFFF
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xC2B2AE3D27D4EB4F)
    return h ^ (h >> np.uint64(29))


def runs_of(b: np.ndarray, window: int = WINDOW, gram: int = GRAM, part: int = 60_000):
    """(gram hash, first window, last window, gram position) of the runs of windows with one minimizer."""
    n = len(b) - window + 1
    if n <= 0:
        z = np.zeros(0, np.int64)
        return z.astype(np.uint64), z, z, z
    h = gram_hashes(b, gram)
    w = window - gram + 1
    low = np.uint64(0xFFFF)
    places = []
    for a in range(0, n, part):
        e = min(n, a + part)
        key = (h[a : e + w - 1] & ~low) | np.arange(e - a + w - 1, dtype=np.uint64)
        k = 1
        while 2 * k <= w:
            key, k = np.minimum(key[:-k], key[k:]), 2 * k
        if k < w:
            key = np.minimum(key[: e - a], key[w - k : w - k + e - a])
        places.append((key[: e - a] & low).astype(np.int64) + a)
    at = np.concatenate(places)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    last = np.concatenate((first[1:], [n])) - 1
    return h[at[first]], first, last, at[first]


def _shard_order(sym: np.ndarray, end: np.ndarray, depth: int) -> np.ndarray:
    """Suffix order of one shard: symbols (0 ends a text), by rank doubling to ``depth``, then by position."""
    n = len(sym)
    at = np.arange(n)

    def shifted(x, h):
        to = at + h
        ok = to <= end
        out = np.zeros(n, dtype=np.int64)
        out[ok] = x[to[ok]]
        return out

    key = np.zeros(n, dtype=np.int64)
    for k in range(6):
        key = (key << 9) | shifted(sym, k)
    rank = np.unique(key, return_inverse=True)[1]
    h = 6
    while h < depth:
        rank = rank + 1
        rank[at == end] = 0
        rank = np.unique((rank << 31) | shifted(rank, h), return_inverse=True)[1]
        h *= 2
    return np.argsort(rank, kind="stable")


def merge(texts: list[bytes], depth: int = WINDOW, shard_bytes: int = 1 << 20, context: int = 12) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Repeated intervals at ``depth``: (text number, offset, block) of the suffixes that share their first ``depth`` symbols with another.

    Each shard is sorted once, to ``context`` symbols (a bounded-context BWT). The interleaving starts
    with the suffixes that follow the windows and takes ``depth`` LF steps; a stable count by BWT
    symbol refines order and blocks in each. A suffix alone in its block stays alone, so it is dropped.
    """
    sizes = np.array([len(t) for t in texts], dtype=np.int64)
    base = np.concatenate(([0], np.cumsum(sizes + 1)))
    n = int(base[-1])
    sym = np.zeros(n, dtype=np.int64)
    for t, a in zip(texts, base):
        sym[a : a + len(t)] = np.frombuffer(t, dtype=np.uint8)
        sym[a : a + len(t)] += 1
    end = np.repeat(base[1:] - 1, sizes + 1)
    sa, place, lf = np.empty(n, dtype=np.int32), np.empty(n, dtype=np.int32), np.empty(n, dtype=np.int32)
    a = 0
    while a < n:  # a shard: whole texts
        k = max(int(np.searchsorted(base, a + shard_bytes, side="right")) - 1, int(np.searchsorted(base, a, side="right")))
        b = int(base[k])
        order = _shard_order(sym[a:b], end[a:b] - a, context)
        sa[a:b] = order + a
        place[sa[a:b]] = np.arange(a, b)
        lf[a:b] = place[a:b][order - 1]
        a = b
    bwt = (np.maximum(sym[sa - 1], 1) - 1).astype(np.uint8)  # an end marker is never stepped over below
    windows = np.maximum(sizes - depth + 1, 0)
    text = np.repeat(np.arange(len(texts)), windows)
    offset = np.arange(len(text)) - np.repeat(np.cumsum(windows) - windows, windows)
    now = np.sort(place[base[text] + offset + depth])
    block = np.zeros(len(now), dtype=np.int32)
    for _ in range(depth):
        c = bwt[now]
        by = np.argsort(c, kind="stable")
        c, block, now = c[by], block[by], lf[now[by]]
        new = np.ones(len(c) + 1, dtype=bool)
        new[1:-1] = (c[1:] != c[:-1]) | (block[1:] != block[:-1])
        block = np.cumsum(new[:-1], dtype=np.int32)
        shared = ~(new[:-1] & new[1:])
        if not shared.all():
            block, now = block[shared], now[shared]
    pos = sa[now]
    text = np.searchsorted(base, pos, side="right") - 1
    return text, pos - base[text], block


def repeated(texts: list[bytes], doc: np.ndarray, at: np.ndarray, depth: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(text number, offset) of the windows that also occur earlier, text k starting at byte ``at[k]`` of ``doc[k]``."""
    text, offset, block = merge(texts, depth)
    d, s = doc[text], at[text] + offset
    order = np.lexsort((s, d, block))
    later = np.zeros(len(order), dtype=bool)
    later[1:] = block[order][1:] == block[order][:-1]
    hit = order[later]
    return text[hit], offset[hit]


def _spans(doc: np.ndarray, start: np.ndarray, window: int = WINDOW) -> pd.DataFrame:
    """Window starts to merged spans (doc_id, s, e)."""
    order = np.lexsort((start, doc))
    d, s = doc[order], start[order]
    new = np.ones(len(d), dtype=bool)
    new[1:] = (d[1:] != d[:-1]) | (s[1:] > s[:-1] + window)
    first = np.flatnonzero(new)
    last = np.concatenate((first[1:], [len(d)])) - 1 if len(d) else first
    return pd.DataFrame({"doc_id": d[first], "s": s[first], "e": s[last] + window})


def _bytes(text) -> np.ndarray:
    return np.frombuffer((text or "").encode("utf-8", "surrogatepass"), dtype=np.uint8)


def gram_counts(docs: DataFrame) -> DataFrame:
    """gram, n: minimizer grams and in how many runs they are."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for a in range(0, len(b), 1000):
                got = [runs_of(_bytes(t))[0] for t in b["text"].iloc[a : a + 1000]]
                g, n = np.unique(np.concatenate([*got, np.zeros(0, np.uint64)]), return_counts=True)
                yield pd.DataFrame({"gram": g.view(np.int64), "n": n.astype(np.int64)})

    return docs.select("text").mapInPandas(run, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def runs_in(docs: DataFrame, grams: BitFilter, heads: BitFilter | None = None) -> DataFrame:
    """gram, code, doc_id, s, windows of the runs whose gram passes; ``code`` is the hash of their bytes.

    With ``heads`` (a filter of xxhash of doc_id and s), only those runs, and their bytes as body.
    """
    shared = docs.sparkSession.sparkContext.broadcast((grams.words, heads.words if heads else None))
    names = ["gram", "code", "doc_id", "s", "windows", *(["body"] if heads else [])]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        by_gram, by_head = (BitFilter(w) if w is not None else None for w in shared.value)
        for b in batches:
            rows = []
            for doc_id, text in zip(b["doc_id"], b["text"]):
                raw = _bytes(text)
                g, first, last, _ = runs_of(raw)
                keep = by_gram.has(hash_longs(g.view(np.int64)))
                if by_head is not None:
                    keep &= by_head.has(hash_longs(first, np.uint64(doc_id & 0xFFFFFFFFFFFFFFFF)))
                data = raw.tobytes()
                for k in np.flatnonzero(keep).tolist():
                    body = data[first[k] : last[k] + WINDOW]
                    row = (int(g[k].view(np.int64)), xxhash.xxh3_64_intdigest(body) - 2**63, doc_id, int(first[k]), int(last[k] - first[k] + 1))
                    rows.append((*row, body) if heads else row)
                if len(rows) > 20_000:
                    yield pd.DataFrame(rows, columns=names)
                    rows = []
            if rows:
                yield pd.DataFrame(rows, columns=names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInPandas(run, "gram long, code long, doc_id long, s long, windows long" + (", body binary" if heads else ""))


def removed_spans(docs: DataFrame, max_classes: int = 20_000, task_bytes: int = 3 << 20, max_broadcast: int = 1_000_000) -> DataFrame:
    """doc_id, s, e: byte spans covered by windows that also start earlier (spans may overlap)."""
    text = docs.where("text is not null and doc_id is not null").select("doc_id", "text")
    grams = BitFilter.of(materialise(gram_counts(text).where("n > 1").select("gram"), "repeat_grams"), "gram")
    runs = materialise(runs_in(text, grams), "repeat_runs")
    first = F.min(F.struct("doc_id", "s", "windows")).alias("f")
    classes = materialise(runs.groupBy("gram", "code").agg(first, F.count("*").alias("n")).select("gram", "code", "f.doc_id", "f.s", "f.windows", "n"), "repeat_classes")
    later = runs.join(classes.select("doc_id", "s"), ["doc_id", "s"], "left_anti")  # all but the first of each class; no class meets in one task
    copies = later.select("doc_id", "s", (F.col("s") + F.col("windows") - 1 + WINDOW).alias("e"))
    per = materialise(classes.groupBy("gram").agg(F.count("*").alias("k"), F.sum(F.col("windows") + WINDOW).alias("bytes")).where("k > 1"), "repeat_per_gram")
    buckets = int((per.where(F.col("k") <= max_classes).agg(F.sum("bytes")).collect()[0][0] or 0) // task_bytes) + 1
    heads = classes.join(per.select("gram"), "gram", "left_semi").select("doc_id", "s")
    # what passes the filter by chance is a real occurrence, later than its class's first: harmless
    bodies = runs_in(text, grams, BitFilter.of(heads, ["doc_id", "s"]))
    wide_grams = materialise(per.where(F.col("k") > max_classes).select("gram"), "repeat_wide")
    any_wide = wide_grams.limit(1).count() > 0
    if any_wide:  # read twice
        bodies = materialise(bodies, "repeat_bodies")
    few = (join_small(bodies, wide_grams, "gram", "left_anti", max_broadcast) if any_wide else bodies).withColumn("bucket", F.pmod(F.xxhash64("gram"), F.lit(buckets)).cast("int"))

    def task(g: pd.DataFrame) -> pd.DataFrame:
        doc, at, body = g["doc_id"].to_numpy(np.int64), g["s"].to_numpy(np.int64), list(g["body"])
        k, off = repeated(body, doc, at)
        return _spans(doc[k], at[k] + off)

    merged = few.select("bucket", "doc_id", "s", "body").groupBy("bucket").applyInPandas(task, "doc_id long, s long, e long")
    if not any_wide:
        return copies.unionByName(merged)

    def windows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for a in range(0, len(b), 2000):
                rows = [(d, s + o, xxhash.xxh3_128_digest(x[o : o + WINDOW])) for d, s, n, x in b.iloc[a : a + 2000][["doc_id", "s", "windows", "body"]].itertuples(index=False) for o in range(n)]
                yield pd.DataFrame(rows, columns=["doc_id", "s", "w"])

    wide = join_small(bodies, wide_grams, "gram", "left_semi", max_broadcast).mapInPandas(windows, "doc_id long, s long, w binary")
    wide = materialise(wide, "repeat_windows")
    lead = wide.groupBy("w").agg(F.min(F.struct("doc_id", "s")).alias("f")).select("f.*")
    hot = wide.join(lead, ["doc_id", "s"], "left_anti").select("doc_id", "s", (F.col("s") + WINDOW).alias("e"))
    return copies.unionByName(merged).unionByName(hot)


def _mask(n: int, s, e) -> np.ndarray:
    edge = np.zeros(n + 1, dtype=np.int64)
    np.add.at(edge, np.asarray(s, dtype=np.int64), 1)
    np.add.at(edge, np.asarray(e, dtype=np.int64), -1)
    return np.cumsum(edge[:-1]) > 0


def deduplicate(docs: DataFrame, with_text: bool = False, max_broadcast: int = 2_000_000, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, kept (the bytes left)."""
    found = removed_spans(docs, **options).groupBy("doc_id").agg(F.collect_list(F.struct("s", "e")).alias("spans"))
    found = materialise(found, "repeat_spans")
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    ids = found.select("doc_id")
    whole = join_small(text, ids, "doc_id", "left_anti", max_broadcast).select("doc_id", "text", F.lit(None).cast("array<long>").alias("s"), F.lit(None).cast("array<long>").alias("e"))
    part = join_small(text, ids, "doc_id", "left_semi", max_broadcast).join(found, "doc_id").select("doc_id", "text", F.col("spans.s").alias("s"), F.col("spans.e").alias("e"))
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_text else "")

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for doc_id, text, s, e in zip(b["doc_id"], b["text"], b["s"], b["e"]):
                raw, gone, n = _bytes(text), 0, 0
                if s is not None and len(s):
                    m = _mask(len(raw), s, e)
                    gone, n = int(m.sum()), int((m[1:] & ~m[:-1]).sum() + m[0])
                    raw = raw[~m]
                left = raw.tobytes()
                rows.append((doc_id, len(left) + gone, gone, n, hashlib.sha256(left).hexdigest(), *((left,) if with_text else ())))
            yield pd.DataFrame(rows, columns=[x.strip().split()[0] for x in schema.split(",")])

    return whole.mapInPandas(cut, schema).unionByName(part.mapInPandas(cut, schema))
