"""Language identification by bit-sliced Bloom filters of character n-grams.

One table of slots serves all languages: bit L of a slot belongs to language L, so the AND of an
n-gram's slots is the bitmask of the languages that contain it. A slot has as many 64-bit words as
the languages need. A text's hits are counted per
language, corrected for that language's false-positive rate (its share of set bits to the power of
the number of hashes), and the largest corrected count decides; the score is its share of the sum.

Learning uses at most ``max_docs`` documents a language (seeded order) and keeps each language's
``max_grams`` commonest n-grams. Letters are the characters of Unicode category L; combining marks
stay with the letters they follow, and all else parts words.

Edge cases: null texts and texts without a letter (digits, numerals, signs) are ``und`` with score 0; ties go to the language
first in order; without any training language all texts are ``und``; texts are read whole; repeated
rows get equal rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hex_order, join_small, over_texts

NOT_LETTERS = regex.compile(r"[^\p{L}\p{M}]+")
LETTER = regex.compile(r"\p{L}")
SIZES = (3, 4)


def gram_codes(text: str) -> np.ndarray:
    """64-bit codes of the n-grams of a text: letters in lower case, words parted by one blank."""
    t = NOT_LETTERS.sub(" ", text.lower()).strip()
    if not LETTER.search(t):
        return np.zeros(0, np.uint64)
    c = np.frombuffer(f" {t} ".encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
    out = []
    for n in SIZES:
        h = np.full(max(0, len(c) - n + 1), n, dtype=np.uint64)
        for k in range(n):
            h = h * np.uint64(0x100000001B3) + c[k : len(c) - n + 1 + k]
        out.append(h)
    h = np.concatenate(out)
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


@dataclass
class BitSlicedFilter:
    languages: list[str]
    slots: np.ndarray
    hashes: int
    false_rate: np.ndarray

    @classmethod
    def build(cls, grams: dict[str, np.ndarray], log_slots: int = 19, hashes: int = 3) -> BitSlicedFilter:
        names = sorted(grams)
        slots = np.zeros((1 << log_slots, max(1, -(-len(names) // 64))), dtype=np.uint64)
        self = cls(names, slots, hashes, np.zeros(len(names)))
        for b, name in enumerate(names):
            for at in self._places(grams[name]):
                slots[at, b // 64] |= np.uint64(1) << np.uint64(b % 64)
        fill = [float(((slots[:, b // 64] >> np.uint64(b % 64)) & np.uint64(1)).mean()) for b in range(len(names))]
        self.false_rate = np.array(fill) ** hashes
        return self

    def _places(self, codes: np.ndarray):
        mask, step = np.uint64(len(self.slots) - 1), codes >> np.uint64(40)
        for k in range(self.hashes):
            yield ((codes + np.uint64(k) * (step | np.uint64(1))) & mask).astype(np.int64)

    def masks(self, codes: np.ndarray) -> np.ndarray:
        """The bitmask of languages for each n-gram: n-grams x words of 64 languages."""
        out = None
        for at in self._places(codes):
            out = self.slots[at] if out is None else out & self.slots[at]
        return out

    def decide(self, text: str | None) -> tuple[str, float]:
        codes = gram_codes(text) if text else np.zeros(0, np.uint64)
        if not len(codes) or not self.languages:
            return "und", 0.0
        m = self.masks(codes)
        hits = np.array([np.count_nonzero(m[:, b // 64] & (np.uint64(1) << np.uint64(b % 64))) for b in range(len(self.languages))], dtype=float)
        fixed = np.maximum(hits - len(codes) * self.false_rate, 0) / (1 - np.minimum(self.false_rate, 0.999))
        best = int(fixed.argmax())
        return self.languages[best], float(fixed[best] / fixed.sum()) if fixed.sum() > 0 else 1.0 / len(self.languages)


def learn(docs: DataFrame, max_docs: int = 400, max_grams: int = 30_000, near_share: float = 0.3, seed: int = 7, **options) -> BitSlicedFilter:
    """``docs`` (doc_id, text, lang) to a filter; rows without text or lang teach nothing."""
    d = docs.where("lang is not null and text is not null and doc_id is not null").select("doc_id", "text", "lang")
    per = d.groupBy("lang").count()
    per = per.select("lang", F.least(F.lit(1.0), 2 * max_docs / F.col("count")).alias("share"))  # a row a language
    order, share = hex_order(seed, "doc_id"), F.col("share")
    near = join_small(d, per, "lang", "inner", 100_000).select("doc_id", "lang", order.alias("o"), "share").where(F.conv(F.substring("o", 1, 8), 16, 10).cast("double") < share * 2**32)
    pick = near.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy("o"))).where(F.col("r") <= max_docs).select("doc_id", "lang")
    taught = d.join(F.broadcast(pick.distinct()), ["doc_id", "lang"], "left_semi")

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for lang, texts in b.groupby("lang")["text"]:
                codes, n = np.unique(np.concatenate([gram_codes(t) for t in texts]), return_counts=True)
                yield pd.DataFrame({"lang": lang, "gram": codes.view(np.int64), "n": n.astype(np.int64)})

    grams = taught.select("lang", "text").mapInPandas(count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    # an n-gram is put into a language's filter if it is not far rarer there than where it is commonest
    grams = grams.withColumn("f", F.col("n") / F.sum("n").over(Window.partitionBy("lang"))).withColumn("most", F.max("f").over(Window.partitionBy("gram")))
    top = Window.partitionBy("lang").orderBy(F.desc("n"), "gram")
    kept = grams.where(F.col("f") >= F.col("most") * near_share).withColumn("r", F.row_number().over(top)).where(F.col("r") <= max_grams).select("lang", "gram").toPandas()
    return BitSlicedFilter.build({k: v["gram"].to_numpy(np.int64).view(np.uint64) for k, v in kept.groupby("lang")}, **options)


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def identify(docs: DataFrame, model: BitSlicedFilter) -> DataFrame:
    """doc_id, held_out, lang_pred, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = shared.value
        for b in batches:
            got = [m.decide(t) for t in b["text"]]
            yield pd.DataFrame({"doc_id": b["doc_id"], "held_out": b["held_out"], "lang_pred": [g[0] for g in got], "score": [g[1] for g in got]})

    rows = docs.select(F.col("doc_id").cast("long"), held_out().alias("held_out"), "text")
    return over_texts(rows, run, "doc_id long, held_out boolean, lang_pred string, score double")


def learn_and_identify(docs: DataFrame, **options) -> DataFrame:
    """Learn from the documents that are not held out, then predict every document."""
    return identify(docs, learn(docs.where(~held_out()), **options))
