"""Quality rules: text statistics, a fixed base rule, and a learned decision list as Spark CASE.

``statistics`` counts over whole texts (one Arrow pass, vectorised windows). ``learn`` is sequential
covering: it grows a conjunction of thresholds on one part of the labelled sample by information
gain, prunes it on the other part, keeps it if it is precise enough there, removes what it covers
and goes on. ``DecisionList.expression`` emits the ordered ``CASE WHEN`` that Catalyst runs.

Repeated windows are compared by 64-bit hashes of seeded word codes, salted per document, so a
false repeat needs a collision inside one document (below 1e-9 even for millions of words).

Edge cases: a null or blank text has 0 words and fails the base rule; a very long text is read
whole; without labels of both classes the list is empty and keeps what the base rule keeps;
repeated rows get equal rows; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import give_back, hex_order, join_small, keyed, materialise

BLANKS = b" \t\n\x0b\x0c\r"
SYMBOLS = b"#*$%&|<>"
WINDOW = 8
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_marks", "n_digits", "n_lines"]
UPPER = bytes(range(65, 91))
MARKS = b"!?"
DIGITS = b"0123456789"


def _repeats(codes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Per text: words inside WINDOW-word windows that occur at least twice in that text."""
    out = np.zeros(len(sizes), dtype=np.int64)
    n = len(codes)
    if n < WINDOW + 1:
        return out
    rng = np.random.default_rng(12345)
    table = rng.integers(0, 2**63, size=int(codes.max()) + 1, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    mixed = table[codes]
    key = np.zeros(n - WINDOW + 1, dtype=np.uint64)
    for k in range(WINDOW):
        key = (key ^ mixed[k : n - WINDOW + 1 + k]) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    doc = np.repeat(np.arange(len(sizes)), sizes)
    inside = doc[: n - WINDOW + 1] == doc[WINDOW - 1 :]
    at = np.flatnonzero(inside)
    if not len(at):
        return out
    salt = rng.integers(0, 2**63, size=len(sizes), dtype=np.int64).astype(np.uint64)
    key = key[at] ^ salt[doc[at]]
    order = np.argsort(key)
    s = key[order]
    same = s[1:] == s[:-1]
    hit = np.zeros(len(s), dtype=bool)
    hit[1:] |= same
    hit[:-1] |= same
    cover = np.zeros(n + 1, dtype=np.int64)
    starts = at[order[hit]]
    np.add.at(cover, starts, 1)
    np.add.at(cover, starts + WINDOW, -1)
    covered = np.cumsum(cover[:-1]) > 0
    return np.bincount(doc[covered], minlength=len(sizes)).astype(np.int64)


def count_texts(texts: list[str | None]) -> np.ndarray:
    """COUNTS of each text, as an int64 matrix."""
    out = np.zeros((len(texts), len(COUNTS)), dtype=np.int64)
    vocabulary: dict[bytes, int] = {}
    codes: list[np.ndarray] = []
    held, first = 0, 0
    for i, text in enumerate(texts):
        b = (text or "").encode("utf-8", "surrogatepass")
        words = b.split()
        codes.append(np.fromiter((vocabulary.setdefault(w, len(vocabulary)) for w in words), dtype=np.int64, count=len(words)))
        lines = [x for x in b.split(b"\n") if x.strip()]
        blanks = len(b) - len(b.translate(None, BLANKS))
        gone = lambda chars: len(b) - len(b.translate(None, chars))  # noqa: E731, B023
        out[i] = (len(words), len(text or "") - blanks, gone(SYMBOLS), len(lines) - len(set(lines)), 0, gone(UPPER), gone(MARKS), gone(DIGITS), len(lines))
        held += len(words)
        if held > 1_000_000 or i == len(texts) - 1:
            sizes = np.array([len(c) for c in codes])
            out[first : i + 1, 4] = _repeats(np.concatenate(codes), sizes)
            codes, held, first, vocabulary = [], 0, i + 1, {}
    return out


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id and COUNTS of every whole text."""

    def count(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for b in (whole.slice(a, 1000) for whole in batches for a in range(0, whole.num_rows, 1000)):
            m = count_texts(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(m[:, k]) for k in range(len(COUNTS))]], ["doc_id", *COUNTS])
        give_back()

    return docs.select(F.col("doc_id").cast("long"), F.col("text")).mapInArrow(count, "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS))


#: Features of the learner: name, numerator, denominator (None: the count itself).
FEATURES = [("words", "n_words", None), ("mean_word", "word_chars", "n_words"), ("symbols", "n_symbols", "word_chars"), ("dup_lines", "n_dup_lines", "n_lines"), ("repeats", "n_repeat_words", "n_words"), ("upper", "n_upper", "word_chars"), ("marks", "n_marks", "word_chars"), ("digits", "n_digits", "word_chars")]


def feature_columns() -> list[Column]:
    return [(F.col(a).cast("double") if b is None else F.col(a) / F.greatest(F.col(b), F.lit(1))).alias(n) for n, a, b in FEATURES]


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


@dataclass
class DecisionList:
    """Ordered rules; each is a conjunction of (feature, '<=' or '>', threshold) that rejects."""

    rules: list[list[tuple[str, str, float]]] = field(default_factory=list)

    def expression(self) -> Column:
        """True keeps. The first rule that holds decides."""
        by_name = dict(zip([n for n, _, _ in FEATURES], feature_columns()))
        case = F
        for rule in self.rules:
            cond = F.lit(True)
            for name, op, cut in rule:
                cond = cond & ((by_name[name] <= cut) if op == "<=" else (by_name[name] > cut))
            case = case.when(cond, F.lit(False))
        return case.otherwise(F.lit(True)) if self.rules else F.lit(True)

    def rejects(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), dtype=bool)
        for rule in self.rules:
            out |= _holds(rule, x)
        return out

    def __str__(self) -> str:
        return "; else ".join("reject if " + " and ".join(f"{n} {o} {c:.6g}" for n, o, c in r) for r in self.rules) or "keep"


_COLUMN = {n: i for i, (n, _, _) in enumerate(FEATURES)}


def _holds(rule, x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), dtype=bool)
    for name, op, cut in rule:
        v = x[:, _COLUMN[name]]
        out &= v <= cut if op == "<=" else v > cut
    return out


def _grow(x: np.ndarray, bad: np.ndarray, max_terms: int, cuts: int) -> list:
    rule: list = []
    inside = np.ones(len(x), dtype=bool)
    while len(rule) < max_terms:
        p0, n0 = bad[inside].sum(), (~bad[inside]).sum()
        if n0 == 0 or p0 == 0:
            break
        base, best = np.log2(p0 / (p0 + n0)), (0.0, None)
        for name, k in _COLUMN.items():
            v = x[inside, k]
            for cut in np.unique(np.quantile(v, np.linspace(0.01, 0.99, cuts))):
                low = v <= cut
                for op, hit in (("<=", low), (">", ~low)):
                    p, n = bad[inside][hit].sum(), (~bad[inside][hit]).sum()
                    if p and (gain := p * (np.log2(p / (p + n)) - base)) > best[0] + 1e-9:
                        best = (gain, (name, op, float(cut)))
        if best[1] is None:
            break
        name, op, cut = best[1]
        v = x[inside, _COLUMN[name]]
        if (v > cut).any():  # the same split, with the threshold midway between the values beside it
            cut = float((v[v <= cut].max() + v[v > cut].min()) / 2)
        rule.append((name, op, cut))
        inside &= _holds(rule[-1:], x)
    return rule


def _prune(rule: list, x: np.ndarray, bad: np.ndarray) -> list:
    worth = lambda r: (lambda h: ((bad & h).sum() - (~bad & h).sum()) / max(h.sum(), 1))(_holds(r, x))
    while len(rule) > 1:
        shorter = max((rule[:i] + rule[i + 1 :] for i in range(len(rule))), key=worth)
        if worth(shorter) < worth(rule):
            break
        rule = shorter
    return rule


def learn(x: np.ndarray, bad: np.ndarray, min_precision: float = 0.9, max_rules: int = 12, max_terms: int = 4, cuts: int = 40, seed: int = 7) -> DecisionList:
    """Sequential covering of the ``bad`` rows: grow on two thirds, prune and accept on one third."""
    out = DecisionList()
    rng = np.random.default_rng(seed)
    left = np.ones(len(x), dtype=bool)
    while len(out.rules) < max_rules and bad[left].sum() >= 3:
        at = rng.permutation(np.flatnonzero(left))
        grow, prune = at[: len(at) * 2 // 3], at[len(at) * 2 // 3 :]
        rule = _grow(x[grow], bad[grow], max_terms, cuts)
        if not rule:
            break
        rule = _prune(rule, x[prune], bad[prune])
        hit, seen = _holds(rule, x[prune]), _holds(rule, x) & left
        if not seen.any() or (hit.any() and bad[prune][hit].mean() < min_precision) or bad[seen].mean() < min_precision:
            break
        out.rules.append(rule)
        left &= ~seen
    return out


def fit(stats: DataFrame, labels: DataFrame, max_train_rows: int = 20_000, seed: int = 7) -> DecisionList:
    """A list learned from at most ``max_train_rows`` labelled rows (seeded order), base failures left out."""
    flags = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality"))
    picked = flags.orderBy(hex_order(seed, "doc_id")).limit(max_train_rows)
    rows = stats.where(~base_failed()).join(F.broadcast(picked), "doc_id").orderBy(hex_order(seed, "doc_id"), *COUNTS).limit(max_train_rows)
    sample = rows.select("quality", *feature_columns()).toPandas()
    if sample["quality"].nunique() < 2:
        return DecisionList()
    return learn(sample.drop(columns="quality").to_numpy(float), sample["quality"].to_numpy() == 0, seed=seed)


def judge(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """doc_id, COUNTS, base_failed, kept."""
    stats = materialise(statistics(docs), "quality_statistics")
    rules = fit(stats, labels, **options)
    failed = base_failed()
    return stats.select("doc_id", *COUNTS, failed.alias("base_failed"), (~failed & rules.expression()).alias("kept"))


def keep_documents(docs: DataFrame, labels: DataFrame, max_broadcast: int = 2_000_000, **options) -> DataFrame:
    """``docs`` without the rows that are rejected; every row is judged by its own text, whatever its id."""
    rows = keyed(docs, "_row")
    stats = materialise(statistics(rows.select(F.col("_row").alias("doc_id"), "text")), "quality_statistics")
    rules = fit(stats, labels, **options)
    kept = stats.where(~base_failed() & rules.expression()).select(F.col("doc_id").alias("_row"))
    return join_small(rows, kept, "_row", "left_semi", max_broadcast).select(*docs.columns)


__all__ = ["COUNTS", "DecisionList", "count_texts", "fit", "judge", "keep_documents", "learn", "statistics"]
