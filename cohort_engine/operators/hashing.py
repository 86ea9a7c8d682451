"""Hash families over sparse vectors. Vectors are packed once by user; every family is then one narrow Arrow pass.

A pass sees a batch of users as one sparse matrix (codes, weights, offsets). Draws are made once for
each different feature and round of the batch, and a user's winner is a segmented minimum, so nothing
is exploded by rounds and nothing is shuffled after the packing.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import randomness as rnd
from .storage import shared_write

#: Entries x rounds that a pass holds at once.
CELLS = 1_500_000


def packed(v: DataFrame, users: DataFrame | None = None) -> DataFrame:
    """user_id, code, weight, feature (parallel arrays in order of the 60-bit feature codes): the one shuffle of the hash families.

    With ``users`` also those without features, whose arrays are empty. Vectors that are packed already stay as they are.
    """
    if "code" in v.columns:
        return v
    cell = F.struct(rnd.code(F.col("feature")).alias("code"), F.col("weight").cast("double").alias("weight"), F.col("feature").cast("string").alias("feature"))
    p = v.groupBy("user_id").agg(F.sort_array(F.collect_list(cell)).alias("c"))
    if users is not None:
        p = users.select("user_id").join(p, "user_id", "left").withColumn("c", F.coalesce("c", F.array().cast("array<struct<code:bigint,weight:double,feature:string>>")))
    return p.select("user_id", "c.code", "c.weight", "c.feature")


class Sparse:
    """A batch of users as one matrix: row i has entries ptr[i] to ptr[i + 1]."""

    def __init__(self, code: np.ndarray, weight: np.ndarray, ptr: np.ndarray):
        self.code, self.weight, self.ptr = code, weight, ptr
        self.names, self.col = np.unique(code, return_inverse=True)
        self.filled = np.flatnonzero(np.diff(ptr) > 0)

    @classmethod
    def of(cls, code: pa.ListArray, weight: pa.ListArray) -> Sparse:
        ptr = code.offsets.to_numpy().astype(np.int64)
        return cls(code.values.to_numpy()[ptr[0] : ptr[-1]], weight.values.to_numpy()[ptr[0] : ptr[-1]], ptr - ptr[0])

    def rows(self, at: np.ndarray) -> Sparse:
        """Only the rows ``at`` (ascending)."""
        count = np.diff(self.ptr)[at]
        ptr = np.concatenate(([0], np.cumsum(count)))
        take = np.arange(ptr[-1]) - np.repeat(ptr[:-1], count) + np.repeat(self.ptr[:-1][at], count)
        out = object.__new__(Sparse)
        out.code, out.weight, out.ptr = self.code[take], self.weight[take], ptr
        used = np.zeros(len(self.names), dtype=bool)
        used[self.col[take]] = True
        out.names, out.col = self.names[used], (np.cumsum(used) - 1)[self.col[take]]
        out.filled = np.flatnonzero(count > 0)
        return out

    def least(self, x: np.ndarray) -> np.ndarray:
        """Of rounds x entries, rounds x filled rows: minima of the rows' entries."""
        return np.minimum.reduceat(x, self.ptr[:-1][self.filled], axis=1)

    def spread(self, x: np.ndarray) -> np.ndarray:
        """Of rounds x different codes, rounds x entries."""
        return np.take(x, self.col, axis=1)

    def blocks(self, rounds: list[int], cells: int = CELLS) -> Iterator[list[int]]:
        step = max(1, min(len(rounds), cells // max(len(self.code), 1)))
        for a in range(0, len(rounds), step):
            yield rounds[a : a + step]


def weighted_winners(s: Sparse, rounds: list[int], p: float, seed: int, scope: str = "") -> tuple[np.ndarray, np.ndarray]:
    """Filled rows x rounds: the winning entry and its level.

    Of a row's features the least of ln c - g (level + 1 - b) wins, with level = floor(p ln w / g + b); ties to the smaller code.
    """
    at, levels = [np.zeros((0, len(s.filled)), np.int64)], [np.zeros((0, len(s.filled)), np.int64)]
    logs, count, place = p * np.log(s.weight), np.diff(s.ptr)[s.filled], np.arange(len(s.code))
    for some in s.blocks(rounds):
        g = s.spread(rnd.gamma2s(s.names, seed, some, "g", scope))
        b = s.spread(rnd.units(s.names, seed, some, "b", scope))
        level = np.floor(logs / g + b)
        score = s.spread(np.log(rnd.gamma2s(s.names, seed, some, "c", scope)))
        b -= level + 1
        g *= b
        score += g
        best = score == np.repeat(s.least(score), count, axis=1)
        won = np.flatnonzero(best)  # one entry a row and round, if none tie
        won = (won % len(place)).reshape(len(some), -1) if len(won) == len(some) * len(s.filled) else s.least(np.where(best, place, len(place)))
        at.append(won)
        levels.append(np.take_along_axis(level, won, axis=1).astype(np.int64))
    return np.concatenate(at).T, np.concatenate(levels).T


def pair_keys(codes: np.ndarray, levels: np.ndarray) -> np.ndarray:
    """A 60-bit key of (feature, level)."""
    return (codes + (levels + (1 << 31)) * 1000003) & ((1 << 60) - 1)


def minwise_values(s: Sparse, rounds: list[int], seed: int, scope: str = "") -> np.ndarray:
    out = [s.least(s.spread(rnd.ranks(s.names, seed, some, scope))) for some in s.blocks(rounds)]
    return np.concatenate([np.zeros((0, len(s.filled)), np.int64), *out]).T


def dot_values(s: Sparse, rounds: list[int], seed: int) -> np.ndarray:
    """Filled rows x rounds: inner products with shared Gaussian vectors."""
    out = [np.add.reduceat(s.weight * s.spread(rnd.gausses(s.names, seed, some)), s.ptr[:-1][s.filled], axis=1) for some in s.blocks(rounds)]
    return np.concatenate([np.zeros((0, len(s.filled))), *out]).T


def keys_of(s: Sparse, rounds: list[int], family: str = "weighted", p: float = 1.0, seed: int = 7, scope: str = "", width: float = 1.0) -> np.ndarray:
    """Filled rows x rounds of one long each: 'weighted' (the feature's code), 'weighted_pair' (feature and level), 'minwise' (on the set), 'sign' or 'quantised' (cells of ``width``)."""
    if family in ("weighted", "weighted_pair"):
        at, level = weighted_winners(s, rounds, p, seed, scope)
        codes = s.code[at] if at.size else at
        return codes if family == "weighted" else pair_keys(codes, level)
    if family == "minwise":
        return minwise_values(s, rounds, seed, scope)
    dots = dot_values(s, rounds, seed)
    if family == "sign":
        return (dots >= 0).astype(np.int64)
    offsets = np.array([width * rnd.units(np.array([rnd.code_of("w")]), seed, [r], "offset")[0, 0] for r in rounds])
    return np.floor((dots + offsets) / width).astype(np.int64)


def _slices(b: pa.RecordBatch, entries: int = 500_000) -> Iterator[pa.RecordBatch]:
    """Few users at a time: about ``entries`` entries."""
    ends = b.column("code").offsets.to_numpy().astype(np.int64)
    a = 0
    while a < b.num_rows:
        e = max(a + 1, int(np.searchsorted(ends, ends[a] + entries, side="right")) - 1)
        yield b.slice(a, e - a)
        a = e


def _narrow(p: DataFrame, f: Callable[[pa.RecordBatch, Sparse], dict], schema: str, columns: list[str]) -> DataFrame:
    """``f`` over slices of packed users; its columns with those names and types."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in _slices(whole):
                yield pa.RecordBatch.from_pydict(f(b, Sparse.of(b.column("code"), b.column("weight"))))

    return p.select(*columns).mapInArrow(run, schema)


def _lists(x: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x).ravel()))


def signatures(v: DataFrame, family: str, length: int, p: float = 1.0, seed: int = 7, width: float = 1.0) -> DataFrame:
    """user_id, sig (array<long>): slots 1 to ``length`` of a family of ``keys_of``; users without features have none."""
    rounds = list(range(1, length + 1))

    def f(b: pa.RecordBatch, s: Sparse) -> dict:
        return {"user_id": b.column("user_id").take(pa.array(s.filled)), "sig": _lists(keys_of(s, rounds, family, p, seed, width=width))}

    return _narrow(packed(v), f, "user_id long, sig array<long>", ["user_id", "code", "weight"])


def ordering_signatures(v: DataFrame, family: str, length: int, p: float = 1.0, seed: int = 7, first: int = 8) -> DataFrame:
    """``signatures`` in whose order, at any number of slots from ``first`` to ``length``, users stand as in that of the whole ones.

    Users whose ``first`` slots nobody shares have only those, as no later slot is ever compared; all others have ``length``.
    """
    if first >= length:
        return signatures(v, family, length, p, seed)
    vectors, slots = packed(v), F.xxhash64("sig")
    head = shared_write(signatures(vectors, family, first, p, seed), "slots")
    again = head.groupBy(slots.alias("slots")).agg(F.count("*").alias("n"))
    again = head.withColumn("slots", slots).join(again.where("n > 1"), "slots").select("user_id")
    again = shared_write(again, "tied")
    whole = signatures(vectors.join(again, "user_id", "left_semi"), family, length, p, seed)
    return head.join(again, "user_id", "left_anti").unionByName(whole)


def signed_sets(sets: DataFrame, length: int, seed: int = 7) -> DataFrame:
    """``sets`` (user_id, code: not empty) with their min-wise slots 1 to ``length`` as sig: one narrow pass."""
    rounds = list(range(1, length + 1))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in _slices(whole):
                s = Sparse.of(b.column("code"), b.column("code"))  # min-wise values see no weights
                yield pa.RecordBatch.from_pydict({"user_id": b.column("user_id"), "code": b.column("code"), "sig": _lists(keys_of(s, rounds, "minwise", seed=seed))})

    return sets.select("user_id", "code").mapInArrow(run, "user_id long, code array<long>, sig array<long>")


def weighted_samples(v: DataFrame, rounds: list[int], p: float = 1.0, seed: int = 7) -> DataFrame:
    """user_id, round, feature, level: one consistent sample per user and round."""
    def f(b: pa.RecordBatch, s: Sparse) -> dict:
        at, level = weighted_winners(s, rounds, p, seed)
        names = b.column("feature").flatten()
        return {
            "user_id": b.column("user_id").take(pa.array(np.repeat(s.filled, len(rounds)))),
            "round": pa.array(np.tile(np.array(rounds, dtype=np.int32), len(s.filled))),
            "feature": names.take(pa.array(at.ravel())),
            "level": pa.array(level.ravel()),
        }

    return _narrow(packed(v), f, "user_id long, round int, feature string, level long", ["user_id", "code", "weight", "feature"])


def weighted_sql(vectors: str, rounds, p: float, seed: int) -> str:
    """user_id, round, feature, code, level in DuckDB, draws made once for each feature and round."""
    names = f"select feature, {rnd.code_sql('feature')} as code from (select distinct feature from {vectors})"
    draws = f"select feature, code, round, {rnd.gamma2_sql('g')} as g, {rnd.gamma2_sql('c')} as c, {rnd.unit_sql('b')} as b from ({names}) cross join ({rnd.multipliers_sql(seed, rnd.rounds_sql(rounds), ['g1', 'g2', 'c1', 'c2', 'b'])})"
    scored = f"select user_id, round, feature, code, ln(c) - g * (level + 1 - b) as score, level from (select *, floor({p!r} * ln(weight) / g + b)::bigint as level from {vectors} join ({draws}) using (feature))"
    return f"select user_id, round, w.feature as feature, w.code as code, w.level as level from (select user_id, round, arg_min(struct_pack(feature := feature, code := code, level := level), struct_pack(s := score, c := code)) as w from ({scored}) group by 1, 2)"


def minwise_sql(vectors: str, rounds, seed: int) -> str:
    names = f"select feature, {rnd.code_sql('feature')} as code from (select distinct feature from {vectors})"
    return f"select user_id, round, min(h) as h from {vectors} join (select feature, round, {rnd.rank_sql()} as h from ({names}) cross join ({rnd.multipliers_sql(seed, rnd.rounds_sql(rounds), ['perm1', 'perm2'])})) using (feature) group by 1, 2"


def dot_sql(vectors: str, rounds, seed: int) -> str:
    names = f"select feature, {rnd.code_sql('feature')} as code from (select distinct feature from {vectors})"
    return f"select user_id, round, sum(weight * g) as dot from {vectors} join (select feature, round, {rnd.gauss_sql()} as g from ({names}) cross join ({rnd.multipliers_sql(seed, rnd.rounds_sql(rounds), ['n1', 'n2'])})) using (feature) group by 1, 2"


def signature(samples: DataFrame, value: Column) -> DataFrame:
    """user_id, sig: the rounds' values in order."""
    s = samples.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("round", value.alias("x")))).alias("s"))
    return s.select("user_id", F.col("s.x").alias("sig"))


def bbit(h: DataFrame, bits: int) -> DataFrame:
    """The lowest bits of every slot of ``h`` (user_id, sig)."""
    return h.select("user_id", F.transform("sig", lambda x: x.bitwiseAND((1 << bits) - 1)).alias("sig"))


def pack_bits(h: DataFrame) -> DataFrame:
    """Bit slots as text of 0 and 1, whose order is that of the bit vectors."""
    return h.select("user_id", F.array_join(F.transform("sig", lambda x: x.cast("string")), "").alias("bits"))


def circulant_minwise(v: DataFrame, shifts: list[int], seed: int = 7) -> DataFrame:
    """user_id, sig: two permutations for all slots, one initial shuffle and one whose positions are shifted."""
    def f(b: pa.RecordBatch, s: Sparse) -> dict:
        start = rnd.ranks(s.names, seed, [0])[0] >> 2  # 60 bits
        out = [s.least(s.spread(rnd.ranks((start + r * 104729) & ((1 << 60) - 1), seed, [1]))) for r in shifts]
        return {"user_id": b.column("user_id").take(pa.array(s.filled)), "sig": _lists(np.concatenate(out).T)}

    return _narrow(packed(v), f, "user_id long, sig array<long>", ["user_id", "code", "weight"])


def _densified(d: DataFrame, bins: int) -> DataFrame:
    """user_id, sig from the filled bins (user_id, bin, h): empty bins borrow the next filled one to the right (around), with its distance."""
    m = d.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("bin", "h"))).alias("m"))
    look = lambda k: F.array_min(F.transform(F.map_keys("m"), lambda b: F.struct(((b - k + bins) % bins).alias("d"), b.alias("b"))))
    slots = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda k: F.concat_ws("+", F.element_at("m", look(k)["b"]).cast("string"), look(k)["d"].cast("string")))
    return m.select("user_id", slots.alias("sig"))


def one_permutation(v: DataFrame, bins: int, seed: int = 7) -> DataFrame:
    """One rank per feature; each of ``bins`` bins keeps its least."""
    r = v.select("user_id", rnd.rank(seed, 0, rnd.code(F.col("feature"))).alias("h"))
    return _densified(r.groupBy("user_id", (F.col("h") % bins).cast("int").alias("bin")).agg(F.min("h").alias("h")), bins)


def binwise_weighted(v: DataFrame, bins: int, p: float = 1.0, seed: int = 7) -> DataFrame:
    """One weighted sample (its feature) in each bin of features: one round's draws serve ``bins`` slots."""
    c = F.col("code")
    d = v.withColumn("code", rnd.code(F.col("feature")))
    d = d.withColumns({"g": rnd.gamma2(seed, 0, "g", c), "c": F.log(rnd.gamma2(seed, 0, "c", c)), "b": rnd.unit(seed, 0, "b", c), "bin": (rnd.rank(seed, 0, c) % bins).cast("int")})
    d = d.withColumn("level", F.floor(p * F.log("weight") / F.col("g") + F.col("b")))
    score = F.col("c") - F.col("g") * (F.col("level") + 1 - F.col("b"))
    return _densified(d.groupBy("user_id", "bin").agg(F.min_by("feature", F.struct(score, c)).alias("h")), bins)
