"""N-gram Jaccard join by signature trees, exact, as components of the link graph.

Sets are 3-word shingles as 64-bit hashes; equal sets are one class. A link at ratio r needs a
shared token among the first |x| - ceil(r|x|) + 1 tokens in any one global order; the order puts
tokens known to be frequent last, so a passage in many documents is no meeting place unless a
document is little else. The order affects speed only.

Round 1: each class goes, with its set, to the bucket of its first token that another class has.
Every bucket is a signature tree, and a task's buckets are a forest: nodes hold the OR of their
members' bitmaps, size ranges, collision excess and component ranges; one dual traversal drops node
pairs whose maximum possible overlap is too small, leaf pairs are verified exactly unless already
united. Buckets above ``max_bucket`` are dealt to parts, and the parts' representatives meet again
in the next rounds.
Round 2: only tokens whose classes lie in different components still matter. Their trees are
traversed with size ranges, then with bitmaps, to find the classes with a surviving partner (of a
small bucket, as pairs, each pair once). The same bounds on bitmaps that widen with the set drop
nearly all that do not link, and the rest meet with their sets. Buckets above ``max_bucket`` are
traversed in pairs of blocks. So at most PAIR_ROWS - 1 pairs a row leave a task.

Edge cases: null and blank texts have no set and link with nothing; texts of fewer words than a
shingle are one shingle; copies and repeated rows share a component; ids are expected to be keys
(rows with one id are one vertex); texts are read whole; an empty table gives an empty result;
extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BitFilter, components, discard, join_small, keyed, lean, materialise, over_texts

BITS = 2048
_M1, _M2, _M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))


_BYTE = (np.random.default_rng(7).integers(0, 2**63, 256, dtype=np.int64).astype(np.uint64) << np.uint64(1)) | np.uint64(1)
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_P = 0x9E3779B97F4A7C15
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """P^i and P^-i modulo 2^64 for i < n or more."""
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(4096, 1 << (n - 1).bit_length())
        out = []
        for p in (_P, pow(_P, -1, 1 << 64)):
            x = np.full(size, p, dtype=np.uint64)
            x[0] = 1
            out.append(np.multiply.accumulate(x))
        _POWERS[:] = out
    return _POWERS[0], _POWERS[1]


class Shingler:
    """Sorted distinct 64-bit shingle hashes of texts, from differences of one running polynomial over the bytes."""

    def __init__(self, words: int = 3):
        self.words = words

    def __call__(self, text: str | None) -> np.ndarray:
        b = np.frombuffer((text or "").encode("utf-8", "surrogatepass").lower(), dtype=np.uint8)
        solid = np.zeros(len(b) + 2, dtype=bool)
        solid[1:-1] = ~_BLANK[b]
        cut = np.flatnonzero(solid[1:] != solid[:-1])
        first, last = cut[::2], cut[1::2]
        k = min(self.words, len(first))
        if not k:
            return np.zeros(0, np.uint64)
        up, down = _powers(len(b) + 1)
        total = np.zeros(len(b) + 1, dtype=np.uint64)
        np.cumsum(_BYTE[b] * up[: len(b)], out=total[1:])
        h = (total[last] - total[first]) * down[first]
        h = (h ^ (h >> np.uint64(32))) * _M3
        out = np.full(len(h) - k + 1, k, dtype=np.uint64)
        for i in range(k):
            out = (out ^ h[i : len(h) - k + 1 + i]) * _M1
            out ^= out >> np.uint64(32)
        return np.unique(out * _M2)


def needed(total, percent: int):
    """Least intersection of two sets whose sizes add to ``total``."""
    return -(-percent * total // (100 + percent))


def prefix_of(s: np.ndarray, hot: np.ndarray, percent: int) -> np.ndarray:
    """The first tokens of a set in the order (frequent last, hash)."""
    p = len(s) - (-(-percent * len(s) // 100)) + 1
    if len(hot) and len(s):
        at = np.minimum(np.searchsorted(hot, s), len(hot) - 1)
        s = s[np.argsort(hot[at] == s, kind="stable")]
    return s[:p]


def bitmap_of(s: np.ndarray) -> np.ndarray:
    out = np.zeros(BITS, dtype=np.uint8)
    out[((s * _M3) >> np.uint64(53)).astype(np.int64) & (BITS - 1)] = 1
    return np.packbits(out).view(np.uint64)


def fine_map_of(s: np.ndarray) -> np.ndarray:
    """A bitmap of four bits or more for each token; its width is a power of two, and halves of it unite to the next narrower one."""
    width = max(BITS, 1 << (4 * len(s) - 1).bit_length())
    out = np.zeros(width, dtype=np.uint8)
    out[((s * _M3) >> np.uint64(20)).astype(np.int64) & (width - 1)] = 1
    return np.packbits(out).view(np.uint64)


def folded(m: np.ndarray, words: int) -> np.ndarray:
    return np.bitwise_or.reduce(m.reshape(-1, words), axis=0)


def may_link(x: np.ndarray, y: np.ndarray, n: int, m: int, percent: int) -> bool:
    """Whether sets of n and m tokens with these fine maps can overlap enough."""
    words = min(len(x), len(y))
    x, y = folded(x, words), folded(y, words)
    only_x, only_y = int(np.bitwise_count(x & ~y).sum()), int(np.bitwise_count(y & ~x).sum())
    return min(n - only_x, m - only_y) >= needed(n + m, percent)


def _starts(*columns: np.ndarray) -> np.ndarray:
    """Whether each row differs from the one before it."""
    new = np.ones(len(columns[0]), dtype=bool)
    new[1:] = np.any([c[1:] != c[:-1] for c in columns], axis=0)
    return new


class SignatureForest:
    """A signature tree for every group of items, all traversed together.

    Items are sorted by (group, size, first word of the bitmap); ``fanout`` neighbours are a node, and
    so on up to one root a group. A node holds the OR of its members' bitmaps, their size range, the
    largest excess of size over set bits, and the range of their components. ``tested`` and ``dropped``
    count node pairs by level (0: items).
    """

    def __init__(self, maps: np.ndarray, sizes: np.ndarray, group: np.ndarray | None = None, comp: np.ndarray | None = None, fanout: int = 8):
        n = len(sizes)
        group = np.zeros(n, np.int64) if group is None else group
        comp = np.arange(n) if comp is None else comp
        self.order = np.lexsort((maps[:, 0], sizes, group))
        maps, sizes, group, comp = maps[self.order], sizes[self.order], group[self.order], comp[self.order]
        self.fanout, self.roots = fanout, []
        self.levels = [(maps, sizes, sizes, sizes - np.bitwise_count(maps).sum(axis=1).astype(np.int64), comp, comp)]
        self.children = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        while len(group):
            first = np.flatnonzero(_starts(group))
            count = np.diff(np.append(first, len(group)))
            self.roots.append(first[count == 1])
            wide, place = np.repeat(count > 1, count), np.arange(len(group)) - np.repeat(first, count)
            at = np.flatnonzero(wide & (place % fanout == 0))
            if not len(at):
                break
            stop = np.minimum(at + fanout, np.repeat(first + count, count)[at])
            cut = np.stack([at, stop], axis=1).ravel()
            cut = cut[:-1] if cut[-1] == len(group) else cut
            over = [f.reduceat(x, cut)[::2] for f, x in zip((np.bitwise_or, np.minimum, np.maximum, np.maximum, np.minimum, np.maximum), self.levels[-1])]
            self.levels.append(tuple(over))
            self.children.append((at, stop - at))
            group = group[at]
        self.tested, self.dropped = np.zeros(len(self.levels), np.int64), np.zeros(len(self.levels), np.int64)

    def possible(self, level: int, i: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
        """Whether some members of nodes i and j, of different components, can overlap enough."""
        m, lo, hi, ex, c0, c1 = self.levels[level]
        ok = (100 * hi[i] >= percent * lo[j]) & (100 * hi[j] >= percent * lo[i])
        ok &= (c0[i] != c1[j]) | (c1[i] != c0[j])  # else all are of one component
        at = np.flatnonzero(ok)
        a, b = i[at], j[at]
        least = needed(lo[a] + lo[b], percent)
        both = np.bitwise_count(m[a] & m[b]).sum(axis=1).astype(np.int64)
        if level:
            most = np.minimum(np.minimum(hi[a], hi[b]), both + np.minimum(ex[a], ex[b]))
        else:  # |x| - bits of x that y lacks
            only = lambda k: lo[k] - ex[k] - both
            most = np.minimum(lo[a] - only(a), lo[b] - only(b))
        ok[at] = most >= least
        self.tested[level] += len(i)
        self.dropped[level] += len(i) - int(ok.sum())
        return ok

    def pairs(self, percent: int, chunk: int = 8192) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of items of one group, each once, that the bounds cannot drop, by dual traversal from the roots."""
        stack = [(level, r, r) for level, r in enumerate(self.roots) if level and len(r)]
        while stack:
            level, i, j = stack.pop()
            if len(i) > chunk:
                stack += [(level, i[a : a + chunk], j[a : a + chunk]) for a in range(0, len(i), chunk)]
                continue
            ok = self.possible(level, i, j, percent)
            i, j = i[ok], j[ok]
            if not level:
                yield self.order[i], self.order[j]
                continue
            first, n = self.children[level]
            c = np.arange(int(max(n[i].max(initial=1), n[j].max(initial=1))))
            ci, cj = np.broadcast_arrays(first[i][:, None, None] + c[:, None], first[j][:, None, None] + c)
            ok = (c[:, None] < n[i][:, None, None]) & (c < n[j][:, None, None])
            ok &= (ci < cj) if level == 1 else (ci <= cj)
            if ok.any():
                stack.append((level - 1, ci[ok], cj[ok]))


def unite(sets: list[np.ndarray], lab: np.ndarray, percent: int, group: np.ndarray | None = None) -> np.ndarray:
    """Labels after uniting all linked sets of each group (its rows lie together); ``lab`` holds the labels so far (any integers)."""
    group = np.zeros(len(sets), np.int64) if group is None else group
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    forest = SignatureForest(np.stack([bitmap_of(s) for s in sets]), sizes, group, lab)
    first = np.flatnonzero(_starts(group))
    count = np.diff(np.append(first, len(group)))
    begin, end = np.repeat(first, count), np.repeat(first + count, count)
    lab = lab.copy()
    for a, b in forest.pairs(percent):
        differ = lab[a] != lab[b]
        for x, y in zip(a[differ].tolist(), b[differ].tolist()):
            if lab[x] != lab[y]:
                both = len(sets[x]) + len(sets[y]) - len(np.union1d(sets[x], sets[y]))
                if both >= needed(len(sets[x]) + len(sets[y]), percent):
                    lo, hi = sorted((lab[x], lab[y]))
                    mine = lab[begin[x] : end[x]]
                    mine[mine == hi] = lo
    return lab


def survivors(maps: np.ndarray, sizes: np.ndarray, comp: np.ndarray, percent: int, own: np.ndarray | None = None, group: np.ndarray | None = None) -> np.ndarray:
    """Items with a partner of their group in another component that the bounds cannot drop; of each pair, one must be in ``own``."""
    keep = np.zeros(len(sizes), dtype=bool)
    for a, b in SignatureForest(maps, sizes, group, comp).pairs(percent, chunk=max(64, 8192 * BITS // 64 // maps.shape[1])):
        if own is not None:
            ok = own[a] | own[b]
            a, b = a[ok], b[ok]
        keep[a] = keep[b] = True
    return keep


def fine_survivors(maps: list[np.ndarray], sizes: np.ndarray, comp: np.ndarray, percent: int) -> np.ndarray:
    """``survivors`` with fine maps: each pair meets at the width of the narrower one."""
    width = np.array([len(m) for m in maps])
    reach = 1 << (-(-100 // percent) - 1).bit_length()  # wider ones are too large to link
    keep = np.zeros(len(maps), dtype=bool)
    for words in np.unique(width):
        at = np.flatnonzero((width >= words) & (width <= words * reach))
        if len(at) > 1:
            keep[at] |= survivors(np.stack([folded(maps[k], int(words)) for k in at]), sizes[at], comp[at], percent, width[at] == words)
    return keep


#: Surviving pairs leave a task as pairs in buckets of at most so many rows, else as rows: what leaves it stays in proportion to its rows.
PAIR_ROWS = 48


def scan(docs: DataFrame, percent: int = 90, words: int = 3) -> DataFrame:
    """Rows of documents (doc_id, n, fp) and, with fp null, of first tokens by hash (doc_id = token, n)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingle = Shingler(words)
        none = np.zeros(0, np.uint64)
        for b in batches:
            sets = [shingle(t) for t in b["text"]]
            fp = [xxhash.xxh128_digest(s.tobytes()) for s in sets]
            yield pd.DataFrame({"doc_id": b["doc_id"], "n": [len(s) for s in sets], "fp": fp})
            first = [prefix_of(s, none, percent) for s in dict(zip(fp, sets)).values()]
            tok, n = np.unique(np.concatenate([*first, none]), return_counts=True)
            for a in range(0, len(tok), 500_000):
                yield pd.DataFrame({"doc_id": tok[a : a + 500_000].view(np.int64), "n": n[a : a + 500_000], "fp": None})

    return over_texts(docs.select(F.col("doc_id").cast("long"), "text"), run, "doc_id long, n long, fp binary")


def prefixes(docs: DataFrame, hot: np.ndarray, percent: int, words: int = 3) -> DataFrame:
    """rep, n, tok, place: the prefix tokens of each document and its set's size."""
    shared = docs.sparkSession.sparkContext.broadcast(hot)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingle = Shingler(words)
        for b in batches:
            whole = [shingle(t) for t in b["text"]]
            full = np.array([len(s) for s in whole], dtype=np.int64)
            sets = [prefix_of(s, shared.value, percent) for s in whole]
            k = [len(s) for s in sets]
            tok = np.concatenate([*sets, np.zeros(0, np.uint64)])
            rep, n, place = np.repeat(b["doc_id"].to_numpy(), k), np.repeat(full, k), np.concatenate([np.arange(x, dtype=np.int32) for x in k])
            for a in range(0, len(tok), 500_000):
                e = a + 500_000
                yield pd.DataFrame({"rep": rep[a:e], "n": n[a:e], "tok": tok[a:e].view(np.int64), "place": place[a:e]})

    return over_texts(docs.select("doc_id", "text"), run, "rep long, n long, tok long, place int")


def shingle_sets(docs: DataFrame, words: int = 3) -> DataFrame:
    """rep, s: the whole set as bytes."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingle = Shingler(words)
        for b in batches:
            yield pd.DataFrame({"rep": b["doc_id"], "s": [shingle(t).tobytes() for t in b["text"]]})

    return over_texts(docs.select("doc_id", "text"), run, "rep long, s binary", 500)


def _groups(g: pd.DataFrame) -> np.ndarray:
    """0, 1, ... for the sorted rows of each (key, part)."""
    return np.cumsum(_starts(g["key"].to_numpy(), g["part"].to_numpy())) - 1 if len(g) else np.zeros(0, np.int64)


def _dealt(rows: DataFrame, key: str, each: int) -> DataFrame:
    """``rows`` with a task number: all rows of a key in one, about ``each`` rows in a task."""
    return rows.withColumn("task", F.pmod(F.xxhash64(key, "part"), F.lit(max(1, rows.count() // each))).cast("int"))


def _unite_buckets(sets: DataFrame, rows: DataFrame, percent: int) -> DataFrame:
    """``rows`` (key, part, rep, comp) with ``sets`` to rep, comp0, comp: united inside each (key, part)."""

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["key", "part", "rep"])
        comp = g["comp"].to_numpy(np.int64)
        after = unite([np.frombuffer(s, dtype=np.uint64) for s in g["s"]], comp, percent, _groups(g)) if len(g) else comp
        return pd.DataFrame({"rep": g["rep"], "comp0": comp, "comp": after})

    return sets.join(_dealt(rows, "key", 300), "rep").groupBy("task").applyInPandas(lean(one), "rep long, comp0 long, comp long")


def _prune(maps: DataFrame, rows: DataFrame, percent: int, pairs: bool) -> DataFrame:
    """What the trees leave of ``rows`` (key, part, rep, comp): rows for ``_unite_buckets``, or, of small buckets, pairs."""

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["key", "part", "rep"]).reset_index(drop=True)
        m = np.stack([np.frombuffer(x, dtype=np.uint64) for x in g["map"]])
        n, comp, rep = (g[c].to_numpy(np.int64) for c in ("n", "comp", "rep"))
        group = _groups(g)
        few = np.bincount(group)[group] <= PAIR_ROWS
        out = []
        keep = np.zeros(len(g), dtype=bool)
        for a, b in SignatureForest(m, n, group, comp).pairs(percent):
            if pairs:
                x, y = a[few[a]], b[few[a]]
                lo, hi = np.where(rep[x] < rep[y], x, y), np.where(rep[x] < rep[y], y, x)
                out.append(pd.DataFrame({"rep": rep[lo], "comp": comp[lo], "rep2": rep[hi], "comp2": comp[hi]}).drop_duplicates())
                a, b = a[~few[a]], b[~few[a]]
            keep[a] = keep[b] = True
        out.append(g.loc[keep, ["key", "part", "rep", "comp"]])
        return pd.concat(out).reindex(columns=["key", "part", "rep", "comp", "rep2", "comp2"]).astype({"key": "Int64", "part": "Int32", "rep2": "Int64", "comp2": "Int64"})

    return _dealt(rows, "key", 20_000).join(maps, "rep").groupBy("task").applyInPandas(lean(one), "key long, part int, rep long, comp long, rep2 long, comp2 long")


def _sized(rows: DataFrame, percent: int) -> DataFrame:
    """``rows`` (key, part, rep, comp, n) without those that have no partner of a fitting size and another component in their bucket."""

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["key", "part", "rep"]).reset_index(drop=True)
        none = np.zeros((len(g), 1), dtype=np.uint64)
        keep = survivors(none, g["n"].to_numpy(np.int64), g["comp"].to_numpy(np.int64), percent, group=_groups(g))
        return g.loc[keep, ["key", "part", "rep", "comp"]]

    return _dealt(rows, "key", 50_000).groupBy("task").applyInPandas(lean(one), "key long, part int, rep long, comp long")


def _refine(maps: DataFrame, rows: DataFrame, percent: int) -> DataFrame:
    """What fine maps leave of ``rows`` (key, part, rep, comp)."""

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["key", "part", "rep"]).reset_index(drop=True)
        m = [np.frombuffer(x, dtype=np.uint64) for x in g["map"]]
        n, comp = g["n"].to_numpy(np.int64), g["comp"].to_numpy(np.int64)
        cut = np.append(np.flatnonzero(_starts(g["key"].to_numpy(), g["part"].to_numpy())), len(g))
        keep = np.zeros(len(g), dtype=bool)
        for a, b in zip(cut, cut[1:]):
            keep[a:b] = fine_survivors(m[a:b], n[a:b], comp[a:b], percent)
        return g.loc[keep, ["key", "part", "rep", "comp"]]

    return _dealt(rows, "key", 2000).join(maps, "rep").groupBy("task").applyInPandas(lean(one), "key long, part int, rep long, comp long")


def _with_both(pairs: DataFrame, side: DataFrame) -> DataFrame:
    """``pairs`` (rep, comp, rep2, comp2) with the columns of ``side`` for rep and, with a 2 after their names, for rep2."""
    return pairs.join(side, "rep").join(side.select(*[F.col(c).alias(c + "2") for c in side.columns]), "rep2")


def _refine_pairs(pairs: DataFrame, maps: DataFrame, percent: int) -> DataFrame:
    """What fine maps leave of ``pairs``."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in batches:
            ok = [may_link(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), n, m, percent) for x, y, n, m in zip(g["map"], g["map2"], g["n"], g["n2"])]
            yield g.loc[np.array(ok, dtype=bool), ["rep", "comp", "rep2", "comp2"]]

    return _with_both(pairs, maps).mapInPandas(run, "rep long, comp long, rep2 long, comp2 long")


def _verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """a, b: components of the linked ones among ``pairs``."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in batches:
            rows = []
            for s, t, a, b in zip(g["s"], g["s2"], g["comp"], g["comp2"]):
                x, y = np.frombuffer(s, dtype=np.uint64), np.frombuffer(t, dtype=np.uint64)
                if len(x) + len(y) - len(np.union1d(x, y)) >= needed(len(x) + len(y), percent):
                    rows.append((a, b))
            yield pd.DataFrame(rows, columns=["a", "b"])

    return _with_both(pairs, sets).select("s", "s2", "comp", "comp2").mapInPandas(run, "a long, b long")


def link_components(docs: DataFrame, percent: int = 90, words: int = 3, hot_df: int = 4, max_hot: int = 1_000_000, max_bucket: int = 4000, max_broadcast: int = 2_000_000) -> DataFrame:
    """doc_id, n_shingles, component_id."""
    seen = materialise(scan(docs, percent, words), "jaccard_scan")
    members = seen.where("fp is not null")
    local = seen.where("fp is null").groupBy("doc_id").agg(F.sum("n").alias("n")).where(F.col("n") >= hot_df)
    hot = np.sort(local.orderBy(F.desc("n"), "doc_id").limit(max_hot).select("doc_id").toPandas()["doc_id"].to_numpy(np.int64).view(np.uint64))
    reps = members.where("n > 0").groupBy("fp").agg(F.min("doc_id").alias("rep"))
    member = materialise(members.join(reps, "fp", "left").select("doc_id", "n", F.coalesce("rep", "doc_id").alias("rep")), "jaccard_members")
    others = member.where("rep != doc_id or n = 0").select("doc_id").distinct()
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    own = join_small(text, others, "doc_id", "left_anti", max_broadcast)
    toks = materialise(prefixes(own, hot, percent, words), "jaccard_prefixes")
    shared = materialise(toks.groupBy("tok").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi")).where("lo != hi").select("tok"), "jaccard_shared")
    cand = materialise(BitFilter.of(shared, "tok").keep(toks, "tok"), "jaccard_candidates")
    for used in (seen, toks, shared):
        discard(used)
    first = materialise(cand.groupBy("rep").agg(F.min_by(F.struct("tok"), F.struct("place", "tok")).alias("f")).select("rep", F.col("f.tok").alias("key")), "jaccard_first")
    size = first.groupBy("key").count()
    alone = size.where("count > 1").withColumn("parts", F.ceil(F.col("count") / max_bucket))
    dealt = materialise(first.join(alone, "key").select("rep", "key", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int").alias("part")), "jaccard_dealt")

    pick = lambda ids: join_small(text, ids.select(F.col("rep").alias("doc_id")).distinct(), "doc_id", "left_semi", max_broadcast)
    sets = lambda ids: shingle_sets(pick(ids), words)

    def unite_of(rows: DataFrame) -> DataFrame:
        live = materialise(_prune(bitmaps(pick(rows), words), rows, percent, False), "jaccard_live").drop("rep2", "comp2")
        return materialise(_unite_buckets(sets(live), live, percent), "jaccard_met")

    met = unite_of(dealt.withColumn("comp", F.col("rep")))
    comp = met.select("rep", "comp")
    while dealt.where("part > 0").limit(1).count():  # the parts' representatives meet again
        heads = met.select(F.col("comp").alias("rep")).distinct()
        again = dealt.join(heads, "rep", "left_semi")
        sizes = again.groupBy("key").agg(F.count("*").alias("count"), F.max("part").alias("p")).where("p > 0").withColumn("parts", F.ceil(F.col("count") / max_bucket))
        before = again.count()
        dealt = materialise(again.join(sizes, "key").select("rep", "key", F.pmod(F.xxhash64("rep", F.lit(1)), F.col("parts")).cast("int").alias("part")), "jaccard_dealt")
        top = unite_of(dealt.withColumn("comp", F.col("rep")))
        moved = top.where("rep != comp").select(F.col("rep").alias("comp"), F.col("comp").alias("to"))
        comp = materialise(comp.join(moved, "comp", "left").select("rep", F.coalesce("to", "comp").alias("comp")), "jaccard_comp")
        met = top
        if dealt.count() >= before or not moved.limit(1).count():
            break
    base = cand.select("rep").distinct().join(comp, "rep", "left").select("rep", F.coalesce("comp", "rep").alias("comp"))
    base = materialise(base, "jaccard_base")
    for used in (first, dealt, met, comp):
        discard(used)
    split = cand.join(base, "rep").groupBy("tok").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("count")).where("lo != hi").select("tok", F.ceil(F.col("count") / max_bucket).cast("int").alias("blocks"))
    near = cand.select("rep", "tok", "n").join(split, "tok").join(base, "rep")
    b = F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")
    mine = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: F.least(b, k) * F.col("blocks") + F.greatest(b, k))
    together = materialise(near.select("rep", "comp", "n", F.col("tok").alias("key"), F.explode(mine).alias("part")), "jaccard_met_late")
    discard(cand)
    blocks = materialise(_sized(together, percent), "jaccard_blocks")
    discard(together)
    left = materialise(_prune(bitmaps(pick(blocks), words), blocks, percent, True), "jaccard_left")
    discard(blocks)
    pairs = materialise(left.where("rep2 is not null").select("rep", "comp", "rep2", "comp2").distinct(), "jaccard_pairs")
    live = left.where("rep2 is null").drop("rep2", "comp2")
    ids = pairs.select("rep").union(pairs.select("rep2")).union(live.select("rep"))
    fine = materialise(bitmaps(pick(ids), words, fine=True), "jaccard_fine")
    pairs, wide = materialise(_refine_pairs(pairs, fine, percent), "jaccard_close"), pairs
    live = materialise(_refine(fine, live, percent), "jaccard_close_live")
    for used in (left, wide, fine):
        discard(used)
    edges = _verify(pairs, materialise(sets(pairs.select("rep").union(pairs.select("rep2"))), "jaccard_sets"), percent)
    late = _unite_buckets(sets(live), live, percent)
    edges = edges.unionByName(late.where("comp != comp0").select(F.col("comp0").alias("a"), F.col("comp").alias("b")))
    up = components(edges)
    final = base.join(up.withColumnRenamed("id", "comp"), "comp", "left").select("rep", F.coalesce("component", "comp").alias("component"))
    out = member.join(final, "rep", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep").alias("component_id"))


def bitmaps(docs: DataFrame, words: int = 3, fine: bool = False) -> DataFrame:
    """rep, n, map."""
    make = fine_map_of if fine else bitmap_of

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingle = Shingler(words)
        for b in batches:
            sets = [shingle(t) for t in b["text"]]
            yield pd.DataFrame({"rep": b["doc_id"], "n": [len(s) for s in sets], "map": [make(s).tobytes() for s in sets]})

    return over_texts(docs.select("doc_id", "text"), run, "rep long, n long, map binary")


def keep_one_each(docs: DataFrame, max_broadcast: int = 2_000_000, **options) -> DataFrame:
    """``docs`` with one row of each component: that of the smallest id (null last), and of several with that id the one whose text is first by hash.

    Rows are told apart by keys of their own, so rows that share an id but not a text are no copies.
    """
    rows = keyed(docs, "_row")
    linked = link_components(rows.select(F.col("_row").alias("doc_id"), "text"), max_broadcast=max_broadcast, **options).select(F.col("doc_id").alias("_row"), "component_id")
    if not rows.odd:
        kept = linked.where("_row = component_id").select("_row")
    else:
        place = F.struct(F.col("doc_id").isNull().alias("n"), F.col("doc_id").cast("long").alias("d"), F.xxhash64("text").alias("t"), F.col("_row").alias("r"))
        kept = rows.select("_row", place.alias("p")).join(linked, "_row").groupBy("component_id").agg(F.min("p").alias("p")).select(F.col("p.r").alias("_row"))
    return join_small(rows, materialise(kept, "jaccard_kept"), "_row", "left_semi", max_broadcast).select(*docs.columns)
