"""Secret scans: three fixed patterns, plus character Markov models. DataFrame functions only.

Two first-order character models are trained from labelled samples: ``random`` (the strings that the
fixed patterns catch, and seeded digests in hex and base 64) and ``ordinary`` (words, and words
joined as identifiers). Every long token is a secret if the log-likelihood ratio of the two models,
per transition and in total, passes its thresholds, and it is a span of its own unless a fixed span
holds all of it. The models are a table of log ratios over a fixed alphabet, so what the driver
handles does not depend on the data's size.

Positions come from splitting each text at the matches and adding lengths, in code points.

Edge cases: a null or empty text has no spans; very long texts are scanned whole; ties at one start
are ordered as kinds are listed; an empty table, or one without words, trains on the seeded samples
alone; repeated rows get equal rows; extra columns of any name are kept by ``redact``.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hex_order

ASSIGN = r"""(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
#: kind, pattern, group that must be long enough, its least length, cheap test
FIXED = [("assign", ASSIGN, 1, 6, r"(?i)(?:passw|secret|token|api_?key)"), ("access", r"AKIA[A-Z0-9]+", 0, 20, "AKIA"), ("hex", r"[0-9a-f]{24,}+", 0, 24, r"[0-9a-f]{24}")]
KINDS = ["assign", "access", "hex", "markov"]
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
CANDIDATE = r"[A-Za-z0-9+/_=-]{16,}+"


SPAN = "array<struct<s:int,e:int,k:int,t:string>>"


def matches(text: Column, pattern: str, kind: int, group: int = 0, least: int = 0, keep: bool = False) -> Column:
    """array<struct<s, e, k, t>>: leftmost non-overlapping matches whose group is long enough; t is the match if ``keep``."""
    hits = F.regexp_extract_all(text, F.lit(f"({pattern})"), F.lit(1))
    parts = F.regexp_extract_all(text, F.lit(f"({pattern})"), F.lit(group + 1)) if group else hits
    gaps = F.split(text, pattern, -1)
    rows = F.zip_with(F.zip_with(gaps, hits, lambda g, h: F.struct(F.length(g).alias("g"), h.alias("h"))), parts, lambda x, p: F.struct(x["g"].alias("g"), x["h"].alias("h"), F.length(p).alias("p")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc, x):
        s = acc["at"] + x["g"]
        e = s + F.coalesce(F.length(x["h"]), F.lit(0))
        new = F.struct(s.cast("int").alias("s"), e.cast("int").alias("e"), F.lit(kind).alias("k"), (x["h"] if keep else F.lit(None).cast("string")).alias("t"))
        ok = x["h"].isNotNull() & (x["p"] >= least)
        return F.struct(e.cast("int").alias("at"), F.when(ok, F.concat(acc["out"], F.array(new))).otherwise(acc["out"]).alias("out"))

    return F.aggregate(rows, start, step, lambda acc: acc["out"])


def _none() -> Column:
    return F.array().cast(SPAN)


def fixed_spans(text: Column) -> dict[str, Column]:
    return {kind: F.when(text.rlike(cheap), matches(text, pattern, k, group, least)).otherwise(_none()) for k, (kind, pattern, group, least, cheap) in enumerate(FIXED)}


@dataclass
class MarkovModel:
    """ratio[i * n + j]: log P(j | i) under random less that under ordinary; n = len(ALPHABET)."""

    ratio: list[float]
    per_step: float = 0.8
    total: float = 14.0

    def score(self, token: Column) -> Column:
        """Sum of log ratios over the transitions of ``token`` (characters of ALPHABET only)."""
        table = F.array(*[F.lit(float(x)) for x in self.ratio])
        codes = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
        n = len(ALPHABET)
        codes = F.filter(codes, lambda c: c >= 0)
        walk = F.aggregate(codes, F.struct(F.lit(-1).alias("last"), F.lit(0.0).alias("sum")), lambda a, c: F.struct(c.cast("int").alias("last"), (a["sum"] + F.when(a["last"] < 0, 0.0).otherwise(F.get(table, a["last"] * n + c))).alias("sum")))
        return walk["sum"]

    def is_secret(self, token: Column) -> Column:
        s = self.score(token)
        return (s >= self.total) & (s >= self.per_step * (F.length(token) - 1))


def _bigrams(tokens: DataFrame) -> dict[tuple[str, str], int]:
    """Counted transitions of a ``token`` column; at most len(ALPHABET)^2 rows come back."""
    once = tokens.groupBy("token").count()
    pairs = once.select("count", F.explode(F.transform(F.sequence(F.lit(1), F.length("token") - 1), lambda i: F.substr(F.col("token"), i, F.lit(2)))).alias("pair"))
    kept = pairs.where(F.col("pair").rlike(r"^[A-Za-z0-9+/_=-]{2}$")).groupBy("pair").agg(F.sum("count").alias("n"))
    return {(r["pair"][0], r["pair"][1]): r["n"] for r in kept.collect()}


def training_tokens(docs: DataFrame, max_documents: int = 400, n_digests: int = 10_000, seed: int = 7) -> tuple[DataFrame, DataFrame]:
    """Labelled samples (random, ordinary). Texts come from at most ``max_documents`` documents in a seeded order."""
    spark = docs.sparkSession
    picked = docs.select("doc_id").where("doc_id is not null").orderBy(hex_order(seed, "doc_id")).limit(max_documents).distinct()
    text = docs.join(F.broadcast(picked), "doc_id", "left_semi").select(F.coalesce("text", F.lit("")).alias("text"))
    caught = text.select(F.explode(F.concat(F.regexp_extract_all("text", F.lit(ASSIGN), F.lit(1)), F.regexp_extract_all("text", F.lit("(" + FIXED[1][1] + ")"), F.lit(1)), F.regexp_extract_all("text", F.lit("(" + FIXED[2][1] + ")"), F.lit(1)))).alias("token"))
    made = spark.range(n_digests).select(F.concat_ws(":", F.lit(str(seed)), "id").alias("x"))
    digests = made.select(F.explode(F.array(F.sha1("x"), F.regexp_replace(F.base64(F.unhex(F.sha2("x", 256))), "=", ""), F.upper(F.md5("x")))).alias("token"))
    words = text.select(F.explode(F.regexp_extract_all("text", F.lit(r"(?<![A-Za-z0-9+/_.=-])([A-Za-z]{2,})(?![A-Za-z0-9+/_.=-])"), F.lit(1))).alias("w"))
    camel = F.concat("w", F.initcap("w"))
    ordinary = words.select(F.explode(F.array(F.col("w"), F.lower("w"), camel, F.concat_ws("_", "w", F.lower("w"), F.lit("id")), F.concat_ws("-", F.lower("w"), "w"), F.concat_ws("/", "w", "w"), F.concat_ws("=", "w", "w"))).alias("token"))
    common = ["user_id", "max_value", "index_01", "page_2024", "getElementById", "README", "CONTENT_TYPE", "base64_encode", "http_request_2", "2024-01-01", "abcdefghijklmnopqrstuvwxyz", *[c * 16 for c in ALPHABET]]
    ordinary = ordinary.union(spark.range(1000).select(F.explode(F.array(*[F.lit(x) for x in common])).alias("token")))
    numbers = made.select(F.conv(F.substring(F.md5("x"), 1, 15), 16, 10).alias("token"))  # long decimal numbers are ordinary
    return digests.union(caught).where(F.length("token") >= 2), ordinary.union(numbers).where(F.length("token") >= 2)


def train(docs: DataFrame, smoothing: float = 0.5, **options) -> MarkovModel:
    """Both models with additive smoothing, as one table of log ratios."""
    random, ordinary = (_bigrams(t) for t in training_tokens(docs, **options))
    n, ratio = len(ALPHABET), []
    for a in ALPHABET:
        sums = [sum(m.get((a, b), 0) for b in ALPHABET) + smoothing * n for m in (random, ordinary)]
        for b in ALPHABET:
            pr, po = ((m.get((a, b), 0) + smoothing) / s for m, s in zip((random, ordinary), sums))
            ratio.append(round(max(-6.0, min(6.0, math.log(pr / po))), 6))
    return MarkovModel(ratio)


def _in_order(base: Column, more: Column) -> Column:
    """``base`` and those of ``more`` that no span of ``base`` holds whole, by start, then kind.

    One walk: a span lies in a base span if the farthest end of the base spans before it reaches its own.
    """
    key = lambda x: F.struct(x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"))
    start = F.struct(F.lit(0).alias("reach"), F.array().cast("array<struct<s:int,e:int,k:int>>").alias("out"))

    def step(acc, x):
        fixed = x["k"] < len(FIXED)
        span = F.array(F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k")))
        out = F.when(fixed | (x["e"] > acc["reach"]), F.concat(acc["out"], span)).otherwise(acc["out"])
        return F.struct(F.when(fixed, F.greatest(acc["reach"], x["e"])).otherwise(acc["reach"]).alias("reach"), out.alias("out"))

    return F.aggregate(F.array_sort(F.transform(F.concat(base, more), key)), start, step, lambda acc: acc["out"])


def scan(docs: DataFrame, model: MarkovModel) -> DataFrame:
    """doc (a struct of all columns of ``docs``), base (array of spans of the fixed patterns) and all (those and the models' spans).

    Spans are (s, e, k): code points, end exclusive, k an index into KINDS, by start, then kind. A long
    token is the models' span unless a fixed span holds all of it.
    """
    d = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("doc")).withColumn("text", F.coalesce(F.col("doc.text"), F.lit("")))
    d = d.withColumns(fixed_spans(F.col("text")))
    cheap = F.col("text").rlike(r"[A-Za-z0-9+/_=-]{16}")
    found = F.filter(matches(F.col("text"), CANDIDATE, KINDS.index("markov"), keep=True), lambda x: model.is_secret(x["t"]))
    d = d.withColumn("markov", F.when(cheap, found).otherwise(_none()))
    fixed = F.concat(*[F.col(k) for k, *_ in FIXED])
    return d.select("doc", _in_order(fixed, _none()).alias("base"), _in_order(fixed, F.col("markov")).alias("all"))


def joined(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(kinds, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def redact(docs: DataFrame, model: MarkovModel, mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with every span (overlapping ones merged) replaced by ``mark``; n_chars follows the text."""
    text, found = F.col("doc.text"), F.size("all") > 0
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc, x):
        gap = F.substr(text, acc["at"] + 1, F.greatest(F.lit(0), x["s"] - acc["at"]))
        new = F.when(x["s"] >= acc["at"], F.concat(acc["out"], gap, F.lit(mark))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), new.alias("out"))

    rest = lambda a: F.concat(a["out"], F.substr(text, a["at"] + 1, F.length(text)))
    d = scan(docs, model).withColumn("clean", F.when(found, F.aggregate("all", start, step, rest)).otherwise(text))
    kind = dict(docs.dtypes)
    new = {"text": F.col("clean"), "n_chars": F.when(found, F.length("clean").cast(kind.get("n_chars", "long"))).otherwise(F.col("doc.n_chars")) if "n_chars" in kind else None}
    return d.select(*[(new[c] if c in new else F.col(f"doc.`{c}`")).alias(c) for c in docs.columns])
