"""Quality classifier with hierarchical empirical Bayes over hosts and paths.

A logistic model on the presence of words and word beginnings and a few text ratios, fitted on a bounded labelled sample, gives
each document's own evidence. All documents' evidence (labels where there are any) is summed by path
and host; beta-binomial posteriors shrink a path towards its host and a host towards the global
rate, with strengths from the method of moments over all sites. A document's posterior log-odds are
its own evidence against the global rate plus the log-odds of its path's posterior without the
document itself, so that neither its label nor its evidence counts for itself through its site.

Edge cases: a null text has no words (its evidence is the ratios'); null hosts and paths are ordinary
sites; a site's only document gets the posterior of the level above, without itself there too;
without labels of both classes there is no model, all posteriors are 0 and everything is kept; ties at the threshold are kept; texts are read whole;
repeated rows get equal rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hex_order, join_small, materialise, over_texts
from .quality_rules import count_texts

_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
RATIOS = ["short", "symbols", "upper", "marks", "repeats", "dup_lines", "digits"]


PREFIXES = (4, 5, 6, 7)


def words_of(text: str | None) -> set[str]:
    """The words of a text in lower case, and their beginnings (marked by ``*``)."""
    folded = (text or "").lower().encode("utf-8", "replace").translate(_FOLD).decode("utf-8", "replace")
    words = set(folded.split())
    starts = {w[:k] for w in words for k in PREFIXES if len(w) > k}
    return words | {x + "*" for x in starts}


def ratios_of(texts: list) -> np.ndarray:
    m = count_texts(texts).astype(float)
    words, chars, lines = np.maximum(m[:, 0], 1), np.maximum(m[:, 1], 1), np.maximum(m[:, 8], 1)
    return np.stack([m[:, 0] < 20, np.minimum(m[:, 2] / chars * 20, 1), np.minimum(m[:, 5] / chars * 2, 1), np.minimum(m[:, 6] / chars * 20, 1), m[:, 4] / words, m[:, 3] / lines, np.minimum(m[:, 7] / chars * 10, 1)], axis=1)


@dataclass
class DocumentModel:
    words: list[str] = field(default_factory=list)
    weights: np.ndarray = field(default_factory=lambda: np.zeros(len(RATIOS)))
    bias: float = 0.0
    rate: float = 0.0
    fitted: bool = False

    def features(self, texts: list) -> np.ndarray:
        at = {w: i for i, w in enumerate(self.words)}
        x = np.zeros((len(texts), len(self.words) + len(RATIOS)), dtype=np.float32)
        known = at.keys()
        for i, t in enumerate(texts):
            for w in words_of(t) & known:
                x[i, at[w]] = 1
        x[:, len(self.words) :] = ratios_of(texts)
        return x

    def evidence(self, texts: list) -> np.ndarray:
        """P(bad) of each text on its own."""
        out = [1 / (1 + np.exp(-np.clip(self.features(texts[a : a + 512]) @ self.weights + self.bias, -30, 30))) for a in range(0, len(texts), 512)]
        return np.concatenate(out) if out else np.zeros(0)


def _logistic(x: np.ndarray, y: np.ndarray, l2: float = 0.2, rounds: int = 40) -> tuple[np.ndarray, float]:
    """Newton steps with a ridge."""
    x1 = np.hstack([x, np.ones((len(x), 1))]).astype(float)
    ridge = np.full(x1.shape[1], l2)
    ridge[-1] = 1e-6
    w = np.zeros(x1.shape[1])
    w[-1] = np.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w, -30, 30)))
        step = np.linalg.solve((x1 * (p * (1 - p))[:, None]).T @ x1 + np.diag(ridge), x1.T @ (y - p) - ridge * w)
        w += step * min(1.0, 4 / max(np.abs(step).max(), 1e-9))
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1], float(w[-1])


def fit(docs: DataFrame, flags: DataFrame, max_train: int = 6000, max_words: int = 300, min_docs: int = 5, seed: int = 7) -> DocumentModel:
    """``flags`` (doc_id, bad) and ``docs`` (doc_id, text) to a model; at most ``max_train`` rows teach it."""
    picked = flags.orderBy(hex_order(seed, "doc_id")).limit(max_train)
    sample = materialise(docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").orderBy(hex_order(seed, "doc_id")).limit(max_train), "site_sample")
    n = {r["bad"]: r["count"] for r in sample.groupBy("bad").count().collect()}
    if len(n) < 2:
        return DocumentModel()
    n1, n0 = n[1], n[0]

    def seen(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            df: dict[str, list[int]] = {}
            for t, bad in zip(b["text"], b["bad"]):
                for w in words_of(t):
                    df.setdefault(w, [0, 0])[bad] += 1
            yield pd.DataFrame([(w, *c) for w, c in df.items()], columns=["w", "n0", "n1"])

    p1, p0 = (F.col("n1") + 0.5) / (n1 + 1), (F.col("n0") + 0.5) / (n0 + 1)
    z = (p1 - p0) / F.sqrt(p1 * (1 - p1) / n1 + p0 * (1 - p0) / n0)
    df = over_texts(sample.select("text", "bad"), seen, "w string, n0 long, n1 long", 500).groupBy("w").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))
    words = [r["w"] for r in df.where(F.col("n0") + F.col("n1") >= min_docs).orderBy(F.abs(z).desc(), "w").limit(max_words).collect()]
    model = DocumentModel(words, np.zeros(len(words) + len(RATIOS)), 0.0, n1 / (n1 + n0))

    def features(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x = model.features(list(b["text"]))
            yield pd.DataFrame({"bad": b["bad"], "x": [r.tobytes() for r in x]})

    rows = over_texts(sample.select("text", "bad"), features, "bad int, x binary", 500).toPandas()
    x = np.stack([np.frombuffer(r, dtype=np.float32) for r in rows["x"]])
    order = np.lexsort((*x.T[:3], rows["bad"].to_numpy()))
    model.weights, model.bias = _logistic(x[order], rows["bad"].to_numpy(float)[order])
    model.fitted = True
    return model


def score(docs: DataFrame, model: DocumentModel) -> DataFrame:
    """doc_id, host, path, evidence of ``docs`` (doc_id, text, host, path)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "host": b["host"], "path": b["path"], "evidence": shared.value.evidence(list(b["text"]))})

    return over_texts(docs.select(F.col("doc_id").cast("long"), "host", "path", "text"), run, "doc_id long, host string, path string, evidence double", 500)


def _strength(groups: DataFrame, rate, least: float = 1.0, most: float = 10_000.0):
    """Beta-binomial strength by moments: p(1-p)/between-site variance - 1. One aggregate row."""
    weighted = F.sum(F.col("n") * (F.col("s") / F.col("n") - rate) ** 2) / F.sum("n")
    within = F.sum(rate * (1 - rate)) / F.sum("n")
    row = groups.agg(F.sum("s").alias("s"), F.sum("n").alias("n"), weighted.alias("var"), within.alias("noise")).collect()[0]
    if not row["n"]:
        return least, 0.0
    p = row["s"] / row["n"]
    between = max((row["var"] or 0) - (row["noise"] or 0), 1e-9)
    return min(most, max(least, p * (1 - p) / between - 1)), p


def _shrunk(s, n, strength, towards):
    return (s + strength * towards) / (n + strength)


def posteriors(scores: DataFrame, max_broadcast: int = 1_000_000) -> DataFrame:
    """One row a path: host, path, n_path, host_posterior, path_posterior, global_rate, and what ``without`` needs. Grouped sums only."""
    paths = materialise(scores.groupBy("host", "path").agg(F.count("*").alias("n"), F.sum("soft").alias("s")), "site_paths")
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))
    total = paths.agg(F.sum("s").alias("s"), F.sum("n").alias("n")).collect()[0]
    rate = total["s"] / total["n"] if total["n"] else 0.0
    k_host, _ = _strength(hosts, F.lit(rate))
    hosts = materialise(hosts.select("host", F.col("n").alias("n_host"), F.col("s").alias("s_host"), _shrunk(F.col("s"), F.col("n"), k_host, rate).alias("host_posterior")), "site_hosts")
    side = F.broadcast(hosts) if hosts.limit(max_broadcast + 1).count() <= max_broadcast else hosts
    j = paths.alias("p").join(side.alias("h"), F.col("p.host").eqNullSafe(F.col("h.host"))).select("p.*", "n_host", "s_host", "host_posterior")
    k_path, _ = _strength(j, F.col("host_posterior"))
    path = _shrunk(F.col("s"), F.col("n"), k_path, F.col("host_posterior"))
    return j.select("host", "path", F.col("n").alias("n_path"), F.col("s").alias("s_path"), "n_host", "s_host", "host_posterior", path.alias("path_posterior"), F.lit(float(rate)).alias("global_rate"), F.lit(float(k_host)).alias("k_host"), F.lit(float(k_path)).alias("k_path"))


def without(own):
    """The path posterior of a row of ``posteriors`` without one document that adds ``own`` to its sums."""
    host = _shrunk(F.col("s_host") - own, F.col("n_host") - 1, F.col("k_host"), F.col("global_rate"))
    return _shrunk(F.col("s_path") - own, F.col("n_path") - 1, F.col("k_path"), host)


def _logit(p):
    q = F.least(F.greatest(p, F.lit(1e-6)), F.lit(1 - 1e-6))
    return F.log(q / (1 - q))


def classify(docs: DataFrame, flags: DataFrame, threshold: float = 0.5, max_broadcast: int = 1_000_000, **options) -> DataFrame:
    """doc_id, host, path, evidence, host_posterior, path_posterior, posterior, kept.

    ``docs``: doc_id, text, host, path. ``flags``: doc_id, bad (0/1).
    """
    flags = flags.where("doc_id is not null and bad is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("bad").cast("int").alias("bad"))
    flags = materialise(flags, "site_flags")
    model = fit(docs, flags, **options)
    s = materialise(score(docs, model), "site_scores")
    soft = join_small(s, flags, "doc_id", "left", max_broadcast).withColumn("soft", F.coalesce(F.col("bad").cast("double"), F.col("evidence")))
    post = materialise(posteriors(soft, max_broadcast), "site_posteriors")
    side = F.broadcast(post) if post.limit(max_broadcast + 1).count() <= max_broadcast else post
    j = soft.alias("s").join(side.alias("p"), F.col("s.host").eqNullSafe(F.col("p.host")) & F.col("s.path").eqNullSafe(F.col("p.path")), "left").select("s.doc_id", "s.host", "s.path", "s.evidence", "s.soft", *[c for c in post.columns if c not in ("host", "path")])
    odds = _logit(F.col("evidence")) - _logit(F.lit(float(model.rate))) + _logit(without(F.col("soft")))
    j = j.withColumn("posterior", 1 / (1 + F.exp(-odds)) if model.fitted else F.lit(0.0))
    return j.select("doc_id", "host", "path", "evidence", "host_posterior", "path_posterior", "posterior", (F.col("posterior") <= threshold).alias("kept"))
