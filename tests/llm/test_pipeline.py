"""The pipeline as a whole, against a plain Python version of its filters and the rules of its last two stages."""

import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from cohort_engine.llm import packing

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(text):
    w = WORD.findall(text.lower())
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def corpus():
    random.seed(11)
    vocabulary = ["".join(random.choice("abcdefghij") for _ in range(6)) for _ in range(400)]
    rows, prose = [], lambda n: [random.choice(vocabulary) for _ in range(n)]
    for i in range(40):
        rows.append((i, " ".join(prose(random.randint(30, 200))), "s" if i % 3 else None))
    near = rows[7][1].split()
    near[-1] = "other"
    rows += [(50, rows[5][1], "s"), (51, " ".join(near), "t"), (52, rows[9][1] + " password: hunter2hunter2", "t")]
    rows += [(60, None, "s"), (61, "", "s"), (62, "too short", "t"), (63, "again and again here we go on " * 30, "t")]
    rows += [(64, " ".join(prose(9000)), "s"), (65, " ".join(prose(40)) + " token=abcdef123456", None)]
    return rows


def accepted(text):
    w = WORD.findall(text or "")
    seen = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = {j for i in range(len(w) - 7) if seen[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(w) >= 20 and 100 * len(covered) <= 30 * len(w)


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """The rows after each stage, each written and read again."""
    sf = str(tmp_path_factory.mktemp("corpus"))
    made = spark.createDataFrame(corpus(), "doc_id long, text string, source string")
    made.select("doc_id", "text", F.lit("en").alias("lang"), "source", F.length("text").cast("long").alias("n_chars")).write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    docs, out = spark.read.parquet(f"{sf}/documents.parquet"), []
    names = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, sf).write.parquet(f"{sf}/after_{name}")
        docs = spark.read.parquet(f"{sf}/after_{name}")
        assert name == "packing" or docs.columns == names
        out.append([r.asDict() for r in docs.collect()])
    return out


def test_rejected_documents_go_and_no_others(stages):
    """Without labels the learned list is empty and the base rule alone decides."""
    assert sorted(r["doc_id"] for r in stages[0]) == sorted(i for i, t, _ in corpus() if accepted(t))


def test_smallest_of_each_near_group_stays(stages):
    text = {i: t for i, t, _ in corpus() if accepted(t)}
    sets, group = {i: shingles(t) for i, t in text.items()}, {i: i for i in text}
    for a in sorted(text):
        for b in sorted(text):
            if a < b and sets[a] & sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                old, new = max(group[a], group[b]), min(group[a], group[b])
                group = {i: new if g == old else g for i, g in group.items()}
    kept = sorted(i for i, g in group.items() if i == g)
    assert sorted(r["doc_id"] for r in stages[1]) == kept and not {50, 51, 52} & set(kept)


def test_secrets_are_marked_and_other_texts_stay(stages):
    before, after = ({r["doc_id"]: r["text"] for r in s} for s in stages[1:3])
    assert before.keys() == after.keys() and after[65].endswith("[SECRET]") and "abcdef123456" not in after[65]
    assert all(after[i] == before[i] for i in before if i != 65)


def test_mix_repeats_whole_documents_near_its_targets(stages):
    size = {r["doc_id"]: len(WORD.findall(r["text"])) for r in stages[2]}
    source = {r["doc_id"]: r["source"] for r in stages[2]}
    text = {r["doc_id"]: r["text"] for r in stages[2]}
    copies = Counter(r["doc_id"] for r in stages[3])
    assert max(copies.values()) <= 3 and all(r["text"] == text[r["doc_id"]] for r in stages[3])
    weights = {s: w for s, w in zip(sorted({s for s in source.values() if s}) + [None], (1, 2, 3))}
    cap = {s: 3 * sum(size[i] for i in size if source[i] == s) for s in weights}
    target, open_, left = {}, set(weights), sum(size.values())
    while open_:
        share = {s: left * weights[s] / sum(weights[x] for x in open_) for s in open_}
        full = {s for s in open_ if share[s] > cap[s]}
        target |= {s: cap[s] for s in full} if full else share
        left -= sum(cap[s] for s in full)
        open_ = open_ - full if full else set()
    for s in weights:
        taken = sum(n * size[i] for i, n in copies.items() if source[i] == s)
        assert abs(taken - target[s]) <= max(size[i] for i in size if source[i] == s) + 32


def test_pieces_hold_every_token_without_gaps(stages):
    enc = packing.encoder(packing.default_ranks())
    want = sum(len(enc.encode_ordinary(r["text"])) + 1 for r in stages[3])
    assert sum(r["length"] for r in stages[4]) == want
    bins = {}
    for r in stages[4]:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in bins.values():
        places.sort()
        ends = np.cumsum([n for _, n in places])
        assert [o for o, _ in places] == [0, *ends[:-1]] and ends[-1] <= 2048
