"""Consecutive splitting: each round parts a cohort into the users with its commonest key and the rest.

A split needs K users on both sides; cohorts below 2K are frozen. Vectors are packed and written once.
While some cohort has more than ``local_cells`` entries, its rounds run over the cluster: the keys of
a block of rounds come from one narrow pass over the vectors, and a round is one small aggregate over
them (labels inside a block follow from the decisions so far and are not written). All other
cohorts go, with their vectors, to one task each (the only other shuffle of vectors), which runs the
remaining rounds on the users still live. Cohorts never interact, so any schedule gives one tree.
Labels are 64-bit node numbers, the log has one row a split, and spent tables are deleted, so space
stays in proportion to the users.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.randomness import NULL_KEY, code, code_of
from .hashing import Sparse, _slices, keys_of, packed
from .storage import discard, fits, shared_write

ROOT = 0
LOG = "round int, parent long, key long, child long, rest_child long, n_matched long, n_rest long, anchor long"
_LOG = pa.schema([("round", pa.int32()), *[(c, pa.int64()) for c in ("parent", "key", "child", "rest_child", "n_matched", "n_rest", "anchor")]])


@dataclass
class Cohorts:
    """user_id, cohort_id; the log of splits (``anchor``: the cohort whose task made the row, null for the cluster's); the rounds run."""

    assignments: DataFrame
    split_log: DataFrame
    rounds: int


@dataclass(frozen=True)
class Keys:
    """How users get their keys: ``key`` 'feature' or 'feature_level' of the weighted sampler, or ``family`` 'minwise' or 'sign'; ``seed_scope`` 'round' or 'cohort' (each cohort has draws of its own)."""

    family: str = "weighted"
    key: str = "feature"
    p: float = 1.2
    seed: int = 7
    seed_scope: str = "round"

    def of(self, s: Sparse, rounds: list[int], cohort: int | None = None) -> np.ndarray:
        """Rows x rounds; rows without features have NULL_KEY."""
        family = "weighted_pair" if self.family == "weighted" and self.key == "feature_level" else self.family
        out = np.full((len(s.ptr) - 1, len(rounds)), NULL_KEY, dtype=np.int64)
        if len(s.filled):
            out[s.filled] = keys_of(s, rounds, family, self.p, self.seed, f":{cohort}" if self.seed_scope == "cohort" else "")
        return out

    def at(self, s: Sparse, rounds: np.ndarray, cohorts: np.ndarray) -> np.ndarray:
        """Each row's key at its own round and cohort."""
        out = np.full(len(rounds), NULL_KEY, dtype=np.int64)
        groups = {}
        for i, g in enumerate(zip(rounds.tolist(), cohorts.tolist() if self.seed_scope == "cohort" else [None] * len(rounds))):
            groups.setdefault(g, []).append(i)
        for (r, c), at in groups.items():
            out[at] = self.of(s.rows(np.array(at)), [r], c)[:, 0]
        return out


def child_id(parent: int, rnd: int, key: int | None = None) -> int:
    return code_of(f"{parent}/{rnd}" if key is None else f"{parent}/{rnd}/{key}")


def _child(parent: Column, rnd: Column, key: Column | None = None) -> Column:
    return code(F.concat_ws("/", parent.cast("string"), rnd.cast("string"), *([] if key is None else [key.cast("string")])))


def decisions(counts: DataFrame, least: int, fanout: str = "mode") -> DataFrame:
    """cohort_id, key, n_matched, n_rest of the keys that leave their cohort, from ``counts`` (cohort_id, key, n).

    ``mode``: the commonest key (ties to the smaller), if it and the rest have ``least`` users. ``all``:
    as many of the commonest keys as leave either nobody or ``least`` users.
    """
    total = counts.groupBy("cohort_id").agg(F.sum("n").alias("size"), F.min_by(F.struct("key", "n"), F.struct(-F.col("n"), "key")).alias("top"))
    if fanout == "mode":
        d = total.select("cohort_id", "top.key", F.col("top.n").alias("n_matched"), (F.col("size") - F.col("top.n")).alias("n_rest"))
        return d.where((F.col("n_matched") >= least) & (F.col("n_rest") >= least))
    w = Window.partitionBy("cohort_id").orderBy(F.desc("n"), "key")
    d = counts.where(F.col("n") >= least).join(total.where(F.col("top.n") >= least).select("cohort_id", "size"), "cohort_id")
    d = d.withColumn("place", F.row_number().over(w)).withColumn("left", F.col("size") - F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    ok = ((F.col("left") == 0) & (F.col("place") > 1)) | (F.col("left") >= least)
    last = d.where(ok).groupBy("cohort_id").agg(F.max(F.struct("place", "left")).alias("last"))
    d = d.join(last, "cohort_id").where(F.col("place") <= F.col("last.place"))
    return d.select("cohort_id", "key", F.col("n").alias("n_matched"), F.col("last.left").alias("n_rest"))


def relabel(labels: DataFrame, d: DataFrame, rnd: int, max_broadcast: int = 1_000_000) -> DataFrame:
    """``labels`` (user_id, cohort_id, key) after the round's decisions: user_id, cohort_id."""
    pair = d.select("cohort_id", "key", F.lit(True).alias("out"))
    split = d.select("cohort_id").distinct().withColumn("split", F.lit(True))
    if fits(pair, max_broadcast):
        pair, split = F.broadcast(pair), F.broadcast(split)
    j = labels.join(split, "cohort_id", "left").join(pair, ["cohort_id", "key"], "left")
    r, c = F.lit(rnd), F.col("cohort_id")
    return j.select("user_id", F.when(F.col("out"), _child(c, r, F.col("key"))).when(F.col("split"), _child(c, r)).otherwise(c).alias("cohort_id"))


def first_cohorts(initial: DataFrame) -> DataFrame:
    """user_id, cohort_id of ``initial``: numbers stay (to go on from earlier cohorts), names become numbers."""
    return initial.select("user_id", F.col("cohort_id") if dict(initial.dtypes)["cohort_id"] == "bigint" else code(F.col("cohort_id")).alias("cohort_id"))


def initial_by_features(v: DataFrame, users: DataFrame, features: list[str], k: int, on_small: str = "merge") -> DataFrame:
    """user_id, cohort_id: which of ``features`` a user has, as a text of 0 and 1.

    Groups below ``k`` are united ('merge'; with the smallest other group if that is still too few), an
    error ('error') or left out ('suppress').
    """
    has = v.where(F.col("feature").isin(features)).groupBy("user_id").agg(*[F.max((F.col("feature") == x).cast("int")).alias(f"f{i}") for i, x in enumerate(features)])
    name = F.concat(*[F.coalesce(F.col(f"f{i}"), F.lit(0)).cast("string") for i in range(len(features))])
    out = users.join(has, "user_id", "left").select("user_id", name.alias("cohort_id"))
    n = {r["cohort_id"]: r["count"] for r in out.groupBy("cohort_id").count().collect()}  # at most 2 ** len(features) rows
    small = [c for c, m in n.items() if m < k]
    if not small:
        return out
    if on_small == "error":
        raise ValueError(f"{len(small)} first cohorts have fewer than {k} users")
    if on_small == "suppress":
        return out.where(~F.col("cohort_id").isin(small))
    if sum(n[c] for c in small) < k and len(small) < len(n):
        small.append(min((m, c) for c, m in n.items() if m >= k)[1])
    return out.withColumn("cohort_id", F.when(F.col("cohort_id").isin(small), "merged").otherwise(F.col("cohort_id")))


class _Choice:
    """One round's decisions over the pairs (group, key) of some users."""

    def __init__(self, group: np.ndarray, keys: np.ndarray, least: int, fanout: str):
        order = np.lexsort((keys, group))
        g, k = group[order], keys[order]
        new = np.ones(len(g), dtype=bool)
        new[1:] = (g[1:] != g[:-1]) | (k[1:] != k[:-1])
        self.pair = np.empty(len(g), np.int64)
        self.pair[order] = np.cumsum(new) - 1
        first = np.flatnonzero(new)
        self.group, self.key, self.n = g[first], k[first], np.diff(np.append(first, len(g)))
        size = np.bincount(self.group, weights=self.n).astype(np.int64)
        by = np.lexsort((self.key, -self.n, self.group))
        pg, pn = self.group[by], self.n[by]
        head = np.flatnonzero(np.append(True, pg[1:] != pg[:-1])) if len(pg) else np.zeros(0, np.int64)
        count = np.diff(np.append(head, len(pg)))
        place = np.arange(len(pg)) - np.repeat(head, count)
        cum = np.cumsum(pn)
        left = size[pg] - (cum - np.repeat(cum[head] - pn[head], count))
        ok = (pn >= least) & ((left >= least) | ((left == 0) & (place > 0)))
        ok &= place == 0 if fanout == "mode" else True
        last = np.full(len(head), -1)
        np.maximum.at(last, np.repeat(np.arange(len(head)), count)[ok], place[ok])
        out = place <= np.repeat(last, count)
        self.out = np.zeros(len(self.group), dtype=bool)
        self.out[by[out]] = True
        rest = np.where(last >= 0, left[np.minimum(head + np.maximum(last, 0), max(len(left) - 1, 0))], 0) if len(head) else np.zeros(0, np.int64)
        self.rest = dict(zip(pg[head][last >= 0].tolist(), rest[last >= 0].tolist()))


def _copies(s: Sparse) -> np.ndarray:
    """Each row's first row with an equal vector (or itself)."""
    n, count = len(s.ptr) - 1, np.diff(s.ptr)
    mix = (s.code ^ (s.code >> 29)) * 0x2545F4914F6CDD1D + s.weight.view(np.int64) * 0x1B873593 * (s.code | 1)
    mix ^= mix >> 31
    total = np.zeros(n, np.int64)
    if len(s.filled):
        total[s.filled] = np.add.reduceat(mix, s.ptr[:-1][s.filled])
    order = np.lexsort((np.arange(n), count, total))
    new = np.ones(n, dtype=bool)
    new[1:] = (np.diff(total[order]) != 0) | (np.diff(count[order]) != 0)
    head = np.arange(n)
    head[order] = order[np.flatnonzero(new)][np.cumsum(new) - 1] if n else order
    other = np.flatnonzero(head != np.arange(n))
    mine, its = s.rows(other), np.repeat(s.ptr[:-1][head[other]], count[other])
    at = its + np.arange(len(its)) - np.repeat(np.cumsum(count[other]) - count[other], count[other])
    wrong = np.unique(np.repeat(np.arange(len(other)), count[other])[(mine.code != s.code[at]) | (mine.weight != s.weight[at])])
    head[other[wrong]] = other[wrong]
    return head


def split_here(s: Sparse, cohort: int, first: int, last: int, least: int, how: Keys, fanout: str = "mode", patience: int | None = None, born: int = 0) -> tuple[np.ndarray, list[tuple]]:
    """Rounds ``first`` to ``last`` on one cohort in memory: the rows' cohorts and the log. Keys are made only for rows of cohorts that can still split, and once for equal vectors.

    Copies have equal keys for ever, so a cohort with fewer than ``least`` users beside its most frequent vector never splits.
    """
    n, head = len(s.ptr) - 1, _copies(s)
    alike = len(np.unique(head)) < n
    group, ids, births, log = np.zeros(n, np.int64), [cohort], [born], []
    at = first
    while at <= last:
        size = np.bincount(group, minlength=len(ids))
        can = size >= 2 * least
        if alike:
            same, many = np.unique(group * n + head, return_counts=True)
            most = np.zeros(len(ids), np.int64)
            np.maximum.at(most, same // n, many)
            can &= size - most >= least
        if patience is not None:
            can &= np.array(births) + patience >= at
        live = np.flatnonzero(can[group])
        if not len(live):
            break
        once, back = np.unique(head[live], return_inverse=True) if alike and how.seed_scope == "round" else (live, slice(None))
        sub = s if len(once) == n else s.rows(once)
        now = next(sub.blocks(list(range(at, min(last, at + 63) + 1))))
        if how.seed_scope == "cohort":
            now = now[:1]
            keys = np.empty((len(live), 1), np.int64)
            for g in np.unique(group[live]):
                mine = np.flatnonzero(group[live] == g)
                keys[mine] = how.of(sub.rows(mine), now, ids[g])
        else:
            keys = how.of(sub, now)[back]
        for c, rnd in enumerate(now):
            g = group[live]
            some = slice(None) if patience is None else np.flatnonzero(np.array(births)[g] + patience >= rnd)
            choice = _Choice(g[some], keys[some, c], least, fanout)
            if not choice.rest:
                continue
            rest_of = np.arange(len(ids))
            for old, left in choice.rest.items():
                if left:
                    rest_of[old] = len(ids)
                    ids.append(child_id(ids[old], rnd))
                    births.append(rnd)
            to = rest_of[choice.group]
            for i in np.flatnonzero(choice.out).tolist():
                old, key = int(choice.group[i]), int(choice.key[i])
                to[i] = len(ids)
                ids.append(child_id(ids[old], rnd, key))
                births.append(rnd)
                log.append((rnd, ids[old], None if key == NULL_KEY else key, ids[-1], child_id(ids[old], rnd), int(choice.n[i]), choice.rest[old], cohort))
            group[live[some]] = to[choice.pair]
        at = now[-1] + 1
    return np.array(ids, dtype=np.int64)[group], log


def _advanced(lab: np.ndarray, born: np.ndarray, keys: np.ndarray, decided: list[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Labels and births after the block's decisions so far: (column, parents, keys, children, rest children) each, sorted by parent, then key."""
    lab, born = lab.copy(), born.copy()
    for column, rnd, parent, key, child, rest in decided:
        heads, start = np.unique(parent, return_index=True)
        which = np.searchsorted(heads, lab)
        which[which == len(heads)] = 0
        hit = heads[which] == lab
        names, num = np.unique(key, return_inverse=True)
        pairs = np.searchsorted(heads, parent) * len(names) + num
        k = np.searchsorted(names, keys[:, column])
        k[k == len(names)] = 0
        mine = which * len(names) + k
        place = np.searchsorted(pairs, mine)
        place[place == len(pairs)] = 0
        out = hit & (names[k] == keys[:, column]) & (pairs[place] == mine)
        lab = np.where(out, child[place], np.where(hit, rest[start][which], lab))
        born = np.where(hit, rnd, born)
    return lab, born


def _matrix(x: pa.ListArray) -> np.ndarray:
    flat = x.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(x), -1) if len(x) else np.zeros((0, 1), np.int64)


def mode_split(v: DataFrame, users: DataFrame, k: int = 20, rounds: int = 1000, p: float = 1.2, seed: int = 7, key: str = "feature", strict: bool = False, initial: DataFrame | None = None, first_round: int = 1, block: int = 32, local_cells: int = 4_000_000, hash_family: str = "weighted", fanout: str = "mode", patience: int | None = None, seed_scope: str = "round", max_decisions: int = 1_000_000) -> Cohorts:
    """``users`` (user_id) with vectors ``v`` to cohorts of at least ``k``; ``v`` may be the packed vectors of all ``users``, to run on them again and again.

    ``key``, ``hash_family`` and ``seed_scope``: see ``Keys``. ``initial`` (user_id, cohort_id): first
    cohorts; one below ``k`` is an error. ``first_round`` with ``initial`` goes on from earlier cohorts.
    ``fanout``: see ``decisions``. ``patience``: a cohort freezes after so many rounds without a split.
    With ``seed_scope`` 'cohort' the cluster's rounds move vectors, as draws follow the cohort.
    Users without features share the null key. Fewer than ``k`` users are an error.
    """
    spark = users.sparkSession
    how, least = Keys(hash_family, key, p, seed, seed_scope), k + 1 if strict else k
    given = "code" in v.columns
    vectors = v if given else shared_write(packed(v, users).select("user_id", "code", "weight"), "vectors")
    spend = (lambda x: None) if given else discard
    whole = initial is None
    schema = "user_id long, cohort_id long, " + LOG
    if whole:
        size = vectors.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.size("code") + 1), F.lit(0)).alias("cells")).collect()[0]
        if size["n"] < k:
            raise ValueError(f"a cohort of {size['n']} users cannot be {k}-anonymous")
        if size["cells"] <= local_cells:  # one task runs it all
            rows = vectors.withColumns({"cohort_id": F.lit(ROOT).cast("long"), "born": F.lit(first_round - 1), "done": F.lit(first_round - 1)})
            out = shared_write(rows.groupBy("cohort_id").applyInArrow(_finisher(rounds, least, how, fanout, patience), schema), "finished")
            spend(vectors)
            return Cohorts(out.where("user_id is not null").select("user_id", "cohort_id"), out.where("user_id is null").drop("user_id", "cohort_id"), rounds)
    cells = vectors.select("user_id", (F.size("code") + 1).cast("long").alias("cells"))
    labels = cells.withColumn("cohort_id", F.lit(ROOT).cast("long")) if whole else first_cohorts(initial).join(cells, "user_id")
    labels = shared_write(labels.select("user_id", "cohort_id", "cells", F.lit(first_round - 1).alias("born"), F.lit(first_round - 1).alias("done")), "labels")
    log, at = spark.createDataFrame([], LOG), first_round
    low = labels.groupBy("cohort_id").count().agg(F.min("count")).collect()[0][0] or 0
    if low < k:
        raise ValueError(f"a cohort of {low} users cannot be {k}-anonymous")
    while at <= rounds:  # over the cluster, while some cohort is too large for a task
        sizes = labels.groupBy("cohort_id").agg(F.count("*").alias("n"), F.sum("cells").alias("cells"), F.max("born").alias("born"))
        big = sizes.where((F.col("cells") > local_cells) & (F.col("n") >= 2 * least))
        if patience is not None:
            big = big.where(F.col("born") + patience >= at)
        big = shared_write(big.select("cohort_id"), "big")
        if not big.limit(1).count():
            discard(big)
            break
        now = list(range(at, min(rounds, at + (1 if seed_scope == "cohort" else block) - 1) + 1))
        side = F.broadcast(big) if fits(big, max_decisions) else big
        moving = labels.join(side, "cohort_id", "left_semi")
        keyed = shared_write(_keyed(vectors, moving, now, how, whole and at == first_round), "keys")
        done, decided, made = 0, [], []
        for c, rnd in enumerate(now):
            counts = _counted(keyed, c, rnd, decided, patience)
            d, room = decisions(counts, least, fanout), max_decisions - sum(len(x[2]) for x in decided)
            done = rnd
            t = d.limit(room + 1).toArrow().sort_by([("cohort_id", "ascending"), ("key", "ascending")])  # the round's one job
            if not t.num_rows:
                continue
            if t.num_rows <= room:
                parent, key = (t.column(x).to_numpy().astype(np.int64) for x in ("cohort_id", "key"))
                child = np.array([child_id(a, rnd, b) for a, b in zip(parent.tolist(), key.tolist())], np.int64)
                rest = np.array([child_id(a, rnd) for a in parent.tolist()], np.int64)
                decided.append((c, rnd, parent, key, child, rest))
                columns = (np.full(len(key), rnd, np.int32), parent, pa.array(key, mask=key == NULL_KEY), child, rest, t.column("n_matched"), t.column("n_rest"), pa.nulls(len(key), pa.int64()))
                made.append(pa.table(dict(zip(_LOG.names, columns))).cast(_LOG))
                continue
            d = shared_write(d, "decisions")
            parent, n = F.col("cohort_id"), F.nullif(F.col("key"), F.lit(NULL_KEY))
            rows = shared_write(d.select(F.lit(rnd).alias("round"), parent.alias("parent"), n.alias("key"), _child(parent, F.lit(rnd), F.col("key")).alias("child"), _child(parent, F.lit(rnd)).alias("rest_child"), "n_matched", "n_rest", F.lit(None).cast("long").alias("anchor")), "log")
            log = log.unionByName(rows)
            # too many to send: labels are written by a join, and a new block begins
            moved = keyed.mapInArrow(_mover(decided, keep=True), "user_id long, cohort_id long, cells long, born int, keys array<long>")
            moved = shared_write(moved.select("user_id", "cohort_id", "cells", "born", F.get("keys", F.lit(c)).alias("key")), "labels")
            after = relabel(moved, d, rnd, 0).join(moved.select("user_id", "cells", F.col("cohort_id").alias("before"), "born"), "user_id")
            moved = after.select("user_id", "cohort_id", "cells", F.when(F.col("cohort_id") == F.col("before"), F.col("born")).otherwise(F.lit(rnd)).alias("born"))
            decided = None
            break
        if made:
            log = log.unionByName(shared_write(spark.createDataFrame(pa.concat_tables(made), LOG), "log"))
        if decided is not None:
            moved = keyed.mapInArrow(_mover(decided), "user_id long, cohort_id long, cells long, born int")
        still = labels.join(side, "cohort_id", "left_anti").select("user_id", "cohort_id", "cells", "born", "done")
        before, labels = labels, shared_write(still.unionByName(moved.withColumn("done", F.lit(done))), "labels")
        for spent in (before, keyed, big):
            discard(spent)
        at = done + 1
    if labels.where(F.col("done") < rounds).limit(1).count():
        open_ = labels.groupBy("cohort_id").agg(F.count("*").alias("n")).where(F.col("n") >= 2 * least).select("cohort_id")  # a cohort goes on where the cluster left it
        rows = labels.join(open_, "cohort_id", "left_semi").drop("cells").join(vectors, "user_id")
        out = shared_write(rows.groupBy("cohort_id").applyInArrow(_finisher(rounds, least, how, fanout, patience), schema), "finished")
        moved = out.where("user_id is not null").select("user_id", "cohort_id")
        log = log.unionByName(out.where("user_id is null").drop("user_id", "cohort_id"))
        still = labels.join(open_, "cohort_id", "left_anti")
        before, labels = labels, shared_write(still.select("user_id", "cohort_id").unionByName(moved), "labels")
        discard(before)
    spend(vectors)
    return Cohorts(labels.select("user_id", "cohort_id"), log, rounds)


def _keyed(vectors: DataFrame, moving: DataFrame, now: list[int], how: Keys, all_users: bool) -> DataFrame:
    """user_id, cohort_id, cells, born, keys of the ``moving`` users: one narrow pass over the vectors; keys, not vectors, meet the labels."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in _slices(whole):
                s = Sparse.of(b.column("code"), b.column("weight"))
                keys = how.of(s, now) if how.seed_scope == "round" else _by_cohort(s, b.column("cohort_id").to_numpy(), now, how)
                yield pa.RecordBatch.from_pydict({"user_id": b.column("user_id"), "keys": pa.ListArray.from_arrays(pa.array(np.arange(len(keys) + 1, dtype=np.int32) * len(now)), pa.array(keys.ravel()))})

    schema = "user_id long, keys array<long>"
    if how.seed_scope == "cohort":  # the draws need the cohort
        return vectors.join(moving, "user_id").select("user_id", "code", "weight", "cohort_id").mapInArrow(run, schema).join(moving, "user_id").select("user_id", "cohort_id", "cells", "born", "keys")
    if not all_users and fits(ids := moving.select("user_id"), 1_000_000):
        vectors = vectors.join(F.broadcast(ids), "user_id", "left_semi")
    keys = vectors.select("user_id", "code", "weight").mapInArrow(run, schema)
    return keys.join(moving, "user_id").select("user_id", "cohort_id", "cells", "born", "keys")


def _by_cohort(s: Sparse, cohorts: np.ndarray, now: list[int], how: Keys) -> np.ndarray:
    out = np.empty((len(cohorts), len(now)), np.int64)
    for c in np.unique(cohorts):
        mine = np.flatnonzero(cohorts == c)
        out[mine] = how.of(s.rows(mine), now, int(c))
    return out


def _counted(keyed: DataFrame, column: int, rnd: int, decided: list, patience: int | None) -> DataFrame:
    """cohort_id, key, n at one round of the block; combined inside each batch first."""
    shared = keyed.sparkSession.sparkContext.broadcast(decided)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = _matrix(b.column("keys"))
            lab, born = _advanced(b.column("cohort_id").to_numpy(), b.column("born").to_numpy(), keys, shared.value)
            ok = slice(None) if patience is None else born + patience >= rnd
            (labs, i), (names, j) = (np.unique(x, return_inverse=True) for x in (lab[ok], keys[ok, column]))
            pairs, n = np.unique(i * max(len(names), 1) + j, return_counts=True)
            i, j = np.divmod(pairs, max(len(names), 1))
            yield pa.RecordBatch.from_pydict({"cohort_id": pa.array(labs[i]), "key": pa.array(names[j]), "n": pa.array(n.astype(np.int64))})

    return keyed.select("cohort_id", "born", "keys").mapInArrow(run, "cohort_id long, key long, n long").groupBy("cohort_id", "key").agg(F.sum("n").alias("n"))


def _mover(decided: list, keep: bool = False):
    """The users of a block under their cohorts after it."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = _matrix(b.column("keys"))
            lab, born = _advanced(b.column("cohort_id").to_numpy(), b.column("born").to_numpy(), keys, decided)
            out = {"user_id": b.column("user_id"), "cohort_id": pa.array(lab), "cells": b.column("cells"), "born": pa.array(born.astype(np.int32))}
            yield pa.RecordBatch.from_pydict(out | ({"keys": b.column("keys")} if keep else {}))

    return run


def _finisher(last: int, least: int, how: Keys, fanout: str, patience: int | None):
    """All remaining rounds of one cohort: its users' cohorts, then its log."""
    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        lists = [t.column(c).chunk(0) if t.num_rows else t.column(c) for c in ("code", "weight")]
        cohort = t.column("cohort_id")[0].as_py()
        label, log = split_here(Sparse.of(*lists), cohort, t.column("done")[0].as_py() + 1, last, least, how, fanout, patience, t.column("born")[0].as_py())
        people = pa.table({"user_id": t.column("user_id"), "cohort_id": pa.array(label)})
        entries = pa.table([pa.array([e[i] for e in log], f.type) for i, f in enumerate(_LOG)], schema=_LOG)
        whole = pa.schema([("user_id", pa.int64()), ("cohort_id", pa.int64()), *_LOG])
        out = pa.concat_tables([people, entries], promote_options="default")
        return out.select(whole.names).cast(whole)

    return run


def assign_new(v: DataFrame, users: DataFrame, split_log: DataFrame, p: float = 1.2, seed: int = 7, key: str = "feature", hash_family: str = "weighted", seed_scope: str = "round", root: int = ROOT, max_broadcast: int = 1_000_000, each: int = 100_000) -> DataFrame:
    """New ``users`` with vectors ``v`` to cohorts by replaying a split log (same ``Keys``): user_id, cohort_id.

    The cluster's splits are followed level by level, as joins on the node. Below them a cohort's
    users and its task's rows of the log meet in tasks of about ``each`` users.
    """
    how = Keys(hash_family, key, p, seed, seed_scope)
    at = packed(v, users).select("user_id", "code", "weight", F.lit(root).cast("long").alias("node"))
    wide = split_log.where("anchor is null").select("round", "parent", F.coalesce("key", F.lit(NULL_KEY)).alias("key"), "child", "rest_child")
    nodes = wide.groupBy("parent").agg(F.first("round").alias("round"), F.first("rest_child").alias("rest_child"))
    small = fits(wide, max_broadcast)
    send = lambda df: F.broadcast(df) if small else df

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in _slices(whole):
                k = how.at(Sparse.of(b.column("code"), b.column("weight")), b.column("round").to_numpy(), b.column("node").to_numpy())
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(k)], [*b.schema.names, "key"])

    at = shared_write(at, "walk")
    while at.join(send(nodes), F.col("node") == F.col("parent"), "left_semi").limit(1).count():
        there = at.join(send(nodes.withColumnRenamed("parent", "node")), "node").select("user_id", "code", "weight", "node", "round", "rest_child")
        there = there.mapInArrow(keys, "user_id long, code array<long>, weight array<double>, node long, round int, rest_child long, key long")
        moved = there.join(send(wide.select(F.col("parent").alias("node"), "key", "child")), ["node", "key"], "left").select("user_id", "code", "weight", F.coalesce("child", "rest_child").alias("node"))
        stay = at.join(send(nodes.select(F.col("parent").alias("node"))), "node", "left_anti").select(moved.columns)
        before, at = at, shared_write(stay.unionByName(moved), "walk")
        discard(before)
    deep = split_log.where("anchor is not null").select("round", "parent", "key", "child", "rest_child", F.col("anchor").alias("node"))
    parts = at.groupBy("node").agg(F.ceil(F.count("*") / each).cast("int").alias("parts"))
    parts = parts.join(deep.select("node").distinct(), "node", "left_semi")
    parts = shared_write(parts, "parts")
    side = F.broadcast(parts) if fits(parts, max_broadcast) else parts
    mine = at.join(side, "node").withColumn("part", F.pmod(F.xxhash64("user_id"), F.col("parts")).cast("int")).drop("parts")
    tree = deep.join(side, "node").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")

    def walk(people: pa.Table, rows: pa.Table) -> pa.Table:
        people = people.combine_chunks()
        none = {"user_id": pa.array([], pa.int64()), "cohort_id": pa.array([], pa.int64())}
        if not people.num_rows:
            return pa.table(none)
        s = Sparse.of(people.column("code").chunk(0), people.column("weight").chunk(0))
        node = people.column("node").to_numpy().copy()
        turn, rest, child = {}, {}, {}
        for r in rows.to_pylist():
            turn[r["parent"]], rest[r["parent"]] = r["round"], r["rest_child"]
            child[r["parent"], NULL_KEY if r["key"] is None else r["key"]] = r["child"]
        while True:
            live = np.flatnonzero([n in turn for n in node.tolist()])
            if not len(live):
                return pa.table({"user_id": people.column("user_id"), "cohort_id": pa.array(node)})
            k = how.at(s.rows(live), np.array([turn[n] for n in node[live].tolist()]), node[live])
            node[live] = [child.get((n, x), rest[n]) for n, x in zip(node[live].tolist(), k.tolist())]

    found = mine.groupBy("node", "part").cogroup(tree.groupBy("node", "part")).applyInArrow(walk, "user_id long, cohort_id long")
    return found.unionByName(at.join(side, "node", "left_anti").select("user_id", F.col("node").alias("cohort_id")))


def round_stats(split_log: DataFrame, assign: DataFrame, k: int) -> DataFrame:
    """One row: the last round with a split, rounds with splits, splits, cohorts and users still of 2K or more."""
    a = split_log.agg(F.max("round").alias("last_split"), F.countDistinct("round").alias("split_rounds"), F.countDistinct("parent").alias("splits"))
    n = assign.groupBy("cohort_id").count().where(F.col("count") >= 2 * k)
    return a.crossJoin(n.agg(F.count("*").alias("open_cohorts"), F.coalesce(F.sum("count"), F.lit(0)).alias("open_users")))  # one row each
