"""Best-fit packing of token pieces after Martello-Toth dominance reduction.

Lengths are integers in 1..capacity, so the instance is a histogram of at most ``capacity`` counts
however many documents there are: only that histogram reaches the driver. ``reduce_dominated``
fixes bins of up to three lengths that provably dominate every other bin holding the same largest
length (all equal bins at once), and ``plan`` best-fits the rest in decreasing order with
multiplicities. The plan is a list of runs (length, first rank, number, per bin, first bin, offset);
its size follows the different lengths, not the documents. Pieces get their rank within a length by
two-level counting in buckets whose number follows that length's count (no length is ranked in one
task), and look their place up in the runs.

Special tokens in a text become their ids, as the ``tokenizers`` library gives them by default.

Edge cases: null text is empty (one end token); longer documents are cut into capacity-token pieces
of which the first may be shorter; an empty table packs to nothing; equal documents and repeated
rows are separate pieces; extra columns are ignored.
"""

from __future__ import annotations

import base64
import math
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import join_small, materialise, over_texts

CAPACITY = 2048
END_ID = 0
#: Fixed values of the vocabulary, which the rank file lacks.
SPECIAL_TOKENS = {"<|endoftext|>": 50256}


@lru_cache(maxsize=2)
def encoder(ranks_file: str):
    """Byte-level BPE of the rank file; the same ids as the ``tokenizers`` file of that vocabulary (tested), four times as fast."""
    import public_tokenizers
    import tiktoken

    with open(ranks_file, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("pieces", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=SPECIAL_TOKENS)


def token_ids(enc, text: str | None) -> list[int]:
    """What ``Tokenizer.encode(text, add_special_tokens=False).ids`` is: special tokens in the text are single ids."""
    return enc.encode(text or "", allowed_special="all")


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def tokenised_pieces(docs: DataFrame, capacity: int = CAPACITY, ranks_file: str | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 and, if asked for, ids (array<int>) of every whole text."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc = encoder(ranks_file or default_ranks())
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch["doc_id"], batch["text"]):
                ids = np.array([*token_ids(enc, text), END_ID], dtype="<u4")
                first = len(ids) % capacity or capacity
                cuts = [0, *range(first, len(ids) + 1, capacity)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
                    rows.append((doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes()), *((ids[a:b].astype("int32"),) if with_ids else ())))
            yield pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32", *(("ids",) if with_ids else ())])

    return over_texts(docs.select(F.col("doc_id").cast("long"), F.col("text")), cut, schema)


class _Bins:
    """Histogram of lengths still to place, and the runs placed so far."""

    def __init__(self, counts: dict[int, int], capacity: int):
        self.capacity = capacity
        self.left = np.zeros(capacity + 2, dtype=np.int64)
        for length, n in counts.items():
            self.left[length] += n
        self.next_rank = np.zeros(capacity + 2, dtype=np.int64)
        self.bins = 0
        self.runs: list[tuple[int, int, int, int, int, int]] = []

    def put(self, length: int, per_bin: int, bins: int, first_bin: int, offset: int) -> None:
        n = per_bin * bins
        self.runs.append((length, int(self.next_rank[length]), n, per_bin, first_bin, offset))
        self.next_rank[length] += n
        self.left[length] -= n

    def close(self, lengths: list[int], bins: int) -> None:
        """Fix ``bins`` bins that each hold ``lengths``."""
        offset = 0
        for length in lengths:
            self.put(length, 1, bins, self.bins, offset)
            offset += length
        self.bins += bins


_FEW = 4


def _dominating(left: np.ndarray, j: int, capacity: int) -> list[int] | None:
    """A set with j that dominates every feasible set with j, or None; ``left`` counts the others too."""
    room = capacity - j
    here = np.flatnonzero(left[: room + 1] - (np.arange(room + 1) == j))
    if not len(here):
        return [j]
    k = int(here[-1])
    if k == room:
        return [j, k]
    a = int(here[0])
    others = left[a] - (a == j)
    second = a if others > 1 else (int(here[1]) if len(here) > 1 else capacity + 1)
    if a + second > room:  # at most one more fits: the largest that does
        return [j, k]
    third = a if others > 2 else (second if left[second] - (second == j) > (1 if second != a else 2) else next((int(x) for x in here if x > second), capacity + 1))
    if a + second + third <= room:
        return None
    fits = [int(x) for x in here if x <= room - k and left[x] - (x == j) - (x == k) > 0]
    if not fits:
        return None
    b = fits[-1]
    # {j, k, b} dominates if the smaller of any feasible pair is at most b
    for y in here[here > b]:
        if 2 * y > room:
            break
        if left[y] - (y == j) > 1 or any(y < x <= room - y for x in here):
            return None
    return [j, k, b]


def reduce_dominated(state: _Bins) -> None:
    """Fix dominating sets, largest length first, as many equal bins at once as there are copies.

    Whether three lengths dominate depends on counts only up to ``_FEW``: while more of each are left, the same three do.
    """
    for j in range(state.capacity, 0, -1):
        while state.left[j] > 0:
            found = _dominating(state.left, j, state.capacity)
            if found is None:
                break
            spare = _FEW if len(found) == 3 else 0
            state.close(found, max(1, min((int(state.left[x]) - spare) // found.count(x) for x in found)))


def best_fit(state: _Bins) -> None:
    """Best-fit decreasing with multiplicities: open bins are kept as runs by the room they have left."""
    room: list[list[tuple[int, int]]] = [[] for _ in range(state.capacity + 1)]  # (first bin, bins)
    used = np.zeros(state.capacity + 1, dtype=bool)
    for length in range(state.capacity, 0, -1):
        while state.left[length] > 0:
            n = int(state.left[length])
            fit = np.flatnonzero(used[length:])
            if len(fit):
                r = length + int(fit[0])
                first, bins = room[r].pop()
                used[r] = bool(room[r])
            else:
                r, first, bins = state.capacity, state.bins, -(-n // (state.capacity // length))
                state.bins += bins
            each = r // length
            full = min(bins, n // each)
            if full:
                state.put(length, each, full, first, state.capacity - r)
                rest = r - each * length
                room[rest].append((first, full))
                used[rest] |= rest > 0
            tail = n - full * each if full < bins else 0
            if tail:
                state.put(length, tail, 1, first + full, state.capacity - r)
                rest = r - tail * length
                room[rest].append((first + full, 1))
                used[rest] |= rest > 0
            if full + bool(tail) < bins:
                room[r].append((first + full + bool(tail), bins - full - bool(tail)))
                used[r] = True


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[np.ndarray, int]:
    """Runs (length, first rank, number, per bin, first bin, offset) and the number of bins."""
    state = _Bins(counts, capacity)
    reduce_dominated(state)
    best_fit(state)
    runs = np.array(sorted(state.runs), dtype=np.int64).reshape(-1, 6)
    return runs, state.bins


def ranked_pieces(pieces: DataFrame, per: dict[int, int]) -> DataFrame:
    """``pieces`` plus _rank, from 0 within each length of ``per`` (length: pieces): buckets are ranked apart and shifted by the counts before them.

    A length of n pieces has about sqrt(n) / 4 buckets, so buckets and rows in a bucket both stay few.
    """
    buckets = F.array(*[F.lit(max(1, math.isqrt(per.get(length, 0)) // 4)) for length in range(max(per, default=0) + 1)])
    keyed = pieces.withColumn("_bucket", F.pmod(F.xxhash64("doc_id", "piece", "start"), F.get(buckets, F.col("length").cast("int"))).cast("int"))
    counts = materialise(keyed.groupBy("length", "_bucket").count(), "pack_counts")
    before = Window.partitionBy("length").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.withColumn("_start", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    within = Window.partitionBy("length", "_bucket").orderBy("doc_id", "piece", "ids_crc32")
    ranked = keyed.withColumn("_row", F.row_number().over(within) - 1)
    return join_small(ranked, starts, ["length", "_bucket"], "inner", 200_000).withColumn("_rank", F.col("_row") + F.col("_start")).drop("_bucket", "_row", "_start")


def pack(pieces: DataFrame, capacity: int = CAPACITY, max_runs: int = 200_000) -> DataFrame:
    """``pieces`` (doc_id, piece, start, length, ids_crc32, ...) plus sequence_id and offset.

    The driver gets at most ``capacity`` counts. At most ``max_runs`` runs (48 bytes each) are
    broadcast; a longer plan is joined by length and rank.
    """
    spark = pieces.sparkSession
    per = {int(r["length"]): r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    runs, _ = plan(per, capacity)
    ranked = ranked_pieces(pieces, per)
    names = pieces.columns
    if len(runs) > max_runs:
        side = spark.createDataFrame(pd.DataFrame(runs, columns=["_length", "_first", "_number", "_per", "_bin", "_offset"]))
        k = F.col("_rank") - F.col("_first")
        j = ranked.join(side, (F.col("length") == F.col("_length")) & (k >= 0) & (k < F.col("_number")))
        return j.select(*names, (F.col("_bin") + F.floor(k / F.col("_per"))).alias("sequence_id"), (F.col("_offset") + k % F.col("_per") * F.col("length")).alias("offset"))
    shared = spark.sparkContext.broadcast(runs)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table = shared.value
        key = table[:, 0] << np.int64(44) | table[:, 1] if len(table) else np.zeros(0, np.int64)
        for batch in batches:
            length, rank = batch["length"].to_numpy(np.int64), batch["_rank"].to_numpy(np.int64)
            at = np.searchsorted(key, length << np.int64(44) | rank, side="right") - 1
            run = table[at]
            k = rank - run[:, 1]
            out = batch[names].copy()
            out["sequence_id"] = run[:, 4] + k // run[:, 3]
            out["offset"] = run[:, 5] + (k % run[:, 3]) * length
            yield out

    return ranked.select(*names, "_rank").mapInPandas(place, schema)


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, ranks_file: str | None = None) -> DataFrame:
    """Tokenise, cut and pack whole documents. The pieces (no tokens) are written once."""
    return pack(materialise(tokenised_pieces(docs, capacity, ranks_file), "pack_pieces"), capacity)
