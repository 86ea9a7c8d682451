"""Invariants of splitting, collision laws of the hashes, DuckDB equivalents at sf0.001."""

import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from cohort_engine import catalog
from cohort_engine.functions import randomness
from cohort_engine.operators import blocks, campaigns, features, hashing, mode_split, neighbours, similarity
from cohort_engine.plans import workloads

SF = "/root/testdata/sf0.001"


def vectors(spark, rows):
    return spark.createDataFrame(rows, "user_id long, feature string, weight double")


def users(spark, n):
    return spark.range(n).withColumnRenamed("id", "user_id")


@pytest.mark.parametrize("name", ["vectors_baskets", "minmax_kernel_pairs", "weighted_sample", "sign_bits", "one_permutation_signature", "binwise_signature", "match_cohorts_any", "match_cohorts_all", "match_cohorts_score", "random_groups", "raw_buckets", "match_users", "mode_split_multiway", "mode_split_own_seeds", "mode_split_by_features", "circulant_signature", "kernel_matrix", "sorted_blocks_quantised"])
def test_queries_equal_duckdb(spark, name):
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    got = catalog.queries()[name](spark, SF)
    cols = sorted(got.columns)
    want = con.execute(f"select {', '.join(cols)} from ({catalog.oracle_sql()[name]})").fetchall()
    key = lambda r: tuple(round(float(x), 6) if isinstance(x, (int, float)) or x.__class__.__name__ == "Decimal" else str(x) for x in r)
    assert sorted(map(key, (tuple(r) for r in got.select(*cols).collect())), key=str) == sorted(map(key, want), key=str)


def test_two_blocks_split_and_strict_does_not(spark):
    v = vectors(spark, [(i, "a" if i < 5 else "b", 1.0) for i in range(10)])
    sizes = lambda c: sorted(r["members"] for r in campaigns.sizes(c.assignments).collect())
    assert sizes(mode_split.mode_split(v, users(spark, 10), k=5, rounds=3)) == [5, 5]
    assert sizes(mode_split.mode_split(v, users(spark, 10), k=5, rounds=3, strict=True)) == [10]


def test_identical_short_empty_and_too_few(spark):
    same = vectors(spark, [(i, "a", 1.0) for i in range(25)])
    assert mode_split.mode_split(same, users(spark, 25), k=5, rounds=4).assignments.select("cohort_id").distinct().count() == 1
    none = vectors(spark, [(i, "a", 1.0) for i in range(5)])
    assert mode_split.mode_split(none, users(spark, 10), k=5, rounds=2).assignments.select("cohort_id").distinct().count() == 2
    with pytest.raises(ValueError):
        mode_split.mode_split(same, users(spark, 4), k=5, rounds=1)


@pytest.mark.parametrize("options", [{"key": "feature_level"}, {"fanout": "all"}, {"seed_scope": "cohort"}, {"patience": 2}])
def test_global_equals_local(spark, options):
    v = features.baskets(spark, SF)
    u = v.select("user_id").distinct()
    a = mode_split.mode_split(v, u, k=5, rounds=5, **options)
    audit = campaigns.anonymity_audit(a.assignments, u, 5).collect()[0]
    assert (audit["cohorts_below"], audit["missing"], audit["doubled"]) == (0, 0, 0) and audit["least"] >= 5
    for other in ({"block": 5, "local_cells": 0}, {"block": 3, "local_cells": 700}):
        b = mode_split.mode_split(v, u, k=5, rounds=5, **options, **other)
        assert a.assignments.exceptAll(b.assignments).count() == 0
        assert a.split_log.drop("anchor").exceptAll(b.split_log.drop("anchor")).count() == 0


def test_decisions_too_many_to_send_are_joined(spark):
    v = features.baskets(spark, SF)
    u = v.select("user_id").distinct()
    a = mode_split.mode_split(v, u, k=5, rounds=6)
    b = mode_split.mode_split(v, u, k=5, rounds=6, local_cells=700, block=4, max_decisions=1)
    assert a.assignments.exceptAll(b.assignments).count() == 0


def test_log_adds_up_resumes_and_assigns(spark):
    v = features.baskets(spark, SF)
    u = v.select("user_id").distinct()
    c = mode_split.mode_split(v, u, k=5, rounds=30)
    size = {r["cohort_id"]: r["members"] for r in campaigns.sizes(c.assignments).collect()}
    for r in sorted(c.split_log.collect(), key=lambda r: -r["round"]):
        assert (size.setdefault(r["child"], r["n_matched"]), size.setdefault(r["rest_child"], r["n_rest"])) == (r["n_matched"], r["n_rest"])
        size[r["parent"]] = r["n_matched"] + r["n_rest"]
    assert size[mode_split.ROOT] == u.count()
    half = mode_split.mode_split(v, u, k=5, rounds=4)
    rest = mode_split.mode_split(v, u, k=5, rounds=30, initial=half.assignments, first_round=5)
    assert rest.assignments.exceptAll(c.assignments).count() == 0
    for log in (c.split_log, mode_split.mode_split(v, u, k=5, rounds=30, local_cells=700).split_log):
        assert mode_split.assign_new(v, u, log, each=40).exceptAll(c.assignments).count() == 0


def brute_split(vectors, k, rounds, p, seed):
    """The prose of the method on dicts."""
    units = lambda r, tag, c: float(randomness.units(np.array([c]), seed, [r], tag)[0, 0])
    gamma = lambda r, tag, c: -np.log(units(r, tag + "1", c) * units(r, tag + "2", c))

    def key(user, r):
        best = None
        for f, w in vectors[user].items():
            c = randomness.code_of(f)
            g, b = gamma(r, "g", c), units(r, "b", c)
            score = np.log(gamma(r, "c", c)) - g * (np.floor(p * np.log(w) / g + b) + 1 - b)
            best = min(best, (score, c)) if best else (score, c)
        return best[1]

    cohorts = [sorted(vectors)]
    for r in range(1, rounds + 1):
        after = []
        for members in cohorts:
            seen = {}
            for u in members:
                seen.setdefault(key(u, r), []).append(u)
            modal = min(seen.values(), key=lambda x: (-len(x), key(x[0], r)))
            rest = [u for u in members if u not in modal]
            after += [modal, rest] if len(modal) >= k and len(rest) >= k else [members]
        cohorts = after
    return sorted(map(tuple, cohorts))


def test_split_equals_brute_force(spark):
    v = features.baskets(spark, SF).where("user_id < 70")
    vectors = {}
    for r in v.collect():
        vectors.setdefault(r["user_id"], {})[r["feature"]] = r["weight"]
    got = {}
    for r in mode_split.mode_split(v, v.select("user_id").distinct(), k=4, rounds=6, p=1.1, seed=3).assignments.collect():
        got.setdefault(r["cohort_id"], []).append(r["user_id"])
    assert sorted(tuple(sorted(x)) for x in got.values()) == brute_split(vectors, 4, 6, 1.1, 3)


def test_first_cohorts_of_few_users(spark):
    v = vectors(spark, [(i, "a", 1.0) for i in range(3)] + [(i, "b", 1.0) for i in range(3, 20)])
    u = users(spark, 20)
    assert mode_split.initial_by_features(v, u, ["a"], 5).select("cohort_id").distinct().count() == 1
    assert mode_split.initial_by_features(v, u, ["a"], 5, "suppress").count() == 17
    with pytest.raises(ValueError):
        mode_split.initial_by_features(v, u, ["a"], 5, "error")


def test_draws_are_uniform_and_the_same_in_spark_and_numpy(spark):
    codes = np.array([randomness.code_of(str(i)) for i in range(4000)])
    x = randomness.units(codes, 7, list(range(1, 9)), "b")
    assert abs(x.mean() - 0.5) < 0.01 and abs(np.corrcoef(x)[np.triu_indices(8, 1)]).max() < 0.07
    assert abs(randomness.gamma2s(codes, 7, [1], "g").mean() - 2) < 0.1 and abs(randomness.gausses(codes, 7, [1]).std() - 1) < 0.05
    got = [r[0] for r in spark.range(50).select(randomness.unit(7, 3, "b", randomness.code(F.col("id"))).alias("x"), "id").orderBy("id").collect()]
    assert np.allclose(got, randomness.units(codes[:50], 7, [3], "b")[0], atol=0, rtol=0)


def test_collision_follows_the_kernel(spark):
    v = vectors(spark, [(1, "a", 1.0), (1, "b", 2.0), (2, "b", 1.0), (2, "c", 3.0)])
    pair = spark.createDataFrame([(1, 2)], "a long, b long")
    assert abs(similarity.minmax_kernel(v, pair).collect()[0]["similarity"] - 1 / 6) < 1e-12
    m = 900
    got = similarity.estimate(hashing.signatures(v, "weighted_pair", m, 1.0), pair).collect()[0]["estimate"]
    assert abs(got - 1 / 6) < 4 * (1 / 6 * 5 / 6 / m) ** 0.5


def test_sorted_blocks_tail(spark):
    h = users(spark, 22).select("user_id", F.array(F.col("user_id") % 4).alias("sig"))
    n = lambda t: sorted(r["members"] for r in campaigns.sizes(blocks.sorted_blocks(h, 5, t)).collect())
    assert n("merge") == [5, 5, 5, 7] and n("short") == [2, 5, 5, 5, 5]


def test_recall_by_hand(spark):
    assign = spark.createDataFrame([(i, "x" if i <= 3 else "y") for i in range(1, 7)], "user_id long, cohort_id string")
    matches = spark.createDataFrame([("c", i) for i in (1, 2, 4)], "campaign_id string, user_id long")
    r = campaigns.campaign_counts(campaigns.match_cohorts(matches, assign)).collect()[0]
    assert (r["tp"], r["fp"], r["fn"]) == (2, 1, 1)


def test_weights_are_cleaned(spark):
    v = features.clean(vectors(spark, [(1, "a", 0.5), (1, "b", None), (1, "c", float("nan")), (1, "d", -1.0), (1, "a", 0.5)]))
    assert [tuple(r) for r in v.collect()] == [(1, "a", 1.0)]


def test_density_sees_all_pairs_and_long_chains(spark):
    v = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id < 60"), "vec_id", "embedding")
    u = v.select("user_id").distinct()
    every = u.toDF("a").crossJoin(u.toDF("b")).where("a < b")
    want = {(r["a"], r["b"]) for r in similarity.minmax_kernel(v, every).where("similarity >= 0.2").collect()}
    assert {(r["a"], r["b"]) for r in similarity.similarity_join(v, 0.2).collect()} == want and any(b - a > 3 for a, b in want)
    with pytest.raises(ValueError):
        similarity.similarity_join(v, 0.2, max_users=10)
    chain = spark.createDataFrame([(i, i + 1, 1.0) for i in range(80)], "a long, b long, similarity double")
    got = blocks.density_cohorts(chain, users(spark, 82), 0.5, 2)
    assert {r["cohort_id"]: r["count"] for r in got.groupBy("cohort_id").count().collect()} == {"0": 81, "noise": 1}


def test_bucket_query_finds_the_nearest(spark):
    r = catalog.queries()["neighbour_recall"](spark, SF).collect()[0]
    assert r["wanted"] == 100 and r["recall"] >= 0.9


def test_short_bucket_queries_fall_back_to_all(spark):
    v = vectors(spark, [(i, x, 1.0) for i in range(12) for x in ("all", *(f"{i}.{j}" for j in range(30)))])
    q = users(spark, 1)
    none = neighbours.bucket_index(users(spark, 12).select("user_id", F.array("user_id").alias("sig")), 1, 1)
    assert neighbours.nearest(none, q, v, 5).exceptAll(neighbours.exact_neighbours(v, q, 5)).count() == 0 and neighbours.nearest(none, q, v, 5).count() == 5


def test_set_search_is_the_search_by_pairs_without_a_row_a_pair(spark, monkeypatch):
    """Several groups, common and rare features, copies that tie and a query without enough equal slots."""
    rows = [(i, x, 1.0) for i in range(80) for x in {"all", f"c{i % 3}", f"r{i % 11}", *(f"{i // 2}.{j}" for j in range(i % 7))}] + [(100, "lone", 1.0)]
    v = vectors(spark, rows)
    sets = hashing.signed_sets(v.groupBy("user_id").agg(F.array_sort(F.collect_list(randomness.code(F.col("feature")))).alias("code")), 4)
    q = v.where("user_id % 20 = 0").select("user_id").distinct()
    index = neighbours.bucket_index(hashing.signatures(v, "minwise", 4), 4, 1)
    near, exact = neighbours.nearest_sets(neighbours.set_search(sets, 81, 5, parts=3).localCheckpoint(), 5)
    for got, want in ((near, neighbours.nearest(index, q, v, 5)), (exact, neighbours.exact_neighbours(v, q, 5))):
        assert got.count() == want.count() > 0 and got.exceptAll(want).count() == 0
    monkeypatch.setattr(neighbours, "minmax_kernel", lambda *a: pytest.fail("pairs as rows"))
    assert catalog.queries()["bucket_query"](spark, SF).count() == 100


def test_set_search_makes_sets_once(spark):
    """Documents and queries leave one narrow pass: sets were split, hashed and signed once for each."""
    sets = hashing.signed_sets(features.term_sets(spark.read.parquet(f"{SF}/documents.parquet"), "doc_id", "text"), 4)
    plan = neighbours.set_search(sets, 200, 5)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1 and plan.count("Exchange hashpartitioning") == 1


def test_similar_sets_are_the_similar_pairs_without_rows_of_features(spark, monkeypatch):
    """Copies, pairs on and beside the threshold, and the documents."""
    rows = [(i, f"w{j}", 1.0) for i, most in enumerate((20, 20, 16, 15, 18, 90, 72, 71)) for j in range(most)]
    sets = lambda v: hashing.signed_sets(v.groupBy("user_id").agg(F.array_sort(F.collect_list(randomness.code(F.col("feature")))).alias("code")), 48)
    for v in (vectors(spark, rows), features.binarise(features.doc_terms(spark, SF))):
        want = neighbours.similar_pairs(hashing.signatures(v, "minwise", 48), v, 0.8, 12, 4)
        got = neighbours.similar_sets(sets(v), 0.8, 12, 4)
        assert got.count() == want.count() > 0 and got.exceptAll(want).count() == 0
    monkeypatch.setattr(neighbours, "minmax_kernel", lambda *a: pytest.fail("pairs by features"))
    catalog.queries()["similar_pairs"](spark, SF)


def test_forest_joins_what_all_links_join(spark):
    """Over several shards, at thresholds with one, several and no clusters; more users than the join of pairs takes."""
    v = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id < 90"), "vec_id", "embedding")
    u = v.select("user_id").distinct()
    for threshold in (0.2, 0.24, 0.9):
        want = blocks.density_cohorts(similarity.similarity_join(v, threshold), u, threshold, 2)
        forest = similarity.near_forest(hashing.packed(v), 90, threshold, each=30)
        assert blocks.density_cohorts(forest, u, threshold, 2).exceptAll(want).count() == 0
    many = spark.range(20_001).select(F.col("id").alias("user_id"), F.array(F.col("id") % 7).alias("code"), F.array(F.lit(1.0)).alias("weight"))
    assert similarity.near_forest(many, 20_001, 0.5).select("b").distinct().count() >= 20_001 - 7 * 2


def test_density_counts_every_neighbour(spark):
    """Cores by their number of links, with common and rare features, sums of several sizes, copies and a feature twice."""
    e = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id < 90"), "vec_id", "embedding")
    rows = [(i, x, w * 1.15 ** (i % 17)) for i in range(60) for x, w in (("all", 1.0), (f"c{i % 3}", 2.0), (f"r{i % 13}", 1.5), (f"o{i // 2}", 0.7))]
    twice = vectors(spark, [*rows, (7, "all", 2.0), (8, "c2", 0.5), (8, "c2", 0.25)])
    for v, threshold in ((e, 0.24), (vectors(spark, rows), 0.25), (twice, 0.25)):
        u = v.select("user_id").distinct()
        x, n, t = hashing.packed(v).localCheckpoint(), u.count(), v.groupBy("user_id").agg(F.sum("weight").alias("t")).localCheckpoint()
        m = v.toDF("a", "feature", "x").join(v.toDF("b", "feature", "y"), "feature").where("a <> b").groupBy("a", "b").agg(F.sum(F.least("x", "y")).alias("m"))
        m = m.join(t.toDF("a", "s"), "a").join(t.toDF("b", "t"), "b").selectExpr("a", "b", "m / (s + t - m) as similarity").where(F.col("similarity") >= threshold).localCheckpoint()
        counts = similarity.neighbour_counts(x, n, threshold, each=20).localCheckpoint()
        want = {r["a"]: r["count"] for r in m.groupBy("a").count().collect()}
        assert {r["user_id"]: r["neighbours"] for r in counts.collect()} == want and len(set(want.values())) > 2
        least = sorted(want.values())[len(want) // 2] + 1
        core = counts.where(F.col("neighbours") >= least - 1).select("user_id", F.lit(True).alias("core"))
        flagged = x.join(core, "user_id", "left").withColumn("core", F.coalesce("core", F.lit(False)))
        got = blocks.density_cohorts(similarity.near_forest(flagged, n, threshold, each=20), u, threshold, least, counts).localCheckpoint()
        assert got.exceptAll(blocks.density_cohorts(m, u, threshold, least)).count() == 0 and got.count() == n


def test_density_query_is_not_one_cluster_of_cores(spark):
    """Clusters, borders and noise are left by its threshold and its number of points, and the number of points matters."""
    c = catalog.queries()["density_cohorts"](spark, SF).localCheckpoint()
    v = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet"), "vec_id", "embedding")
    pairs = similarity.similarity_join(v, catalog.NEAR).localCheckpoint()
    u = v.select("user_id").distinct()
    assert c.exceptAll(blocks.density_cohorts(pairs, u, catalog.NEAR, catalog.NEAR_POINTS)).count() == 0 and c.count() == u.count()
    assert c.where("cohort_id <> 'noise'").select("cohort_id").distinct().count() > 1 and c.where("cohort_id = 'noise'").count() > 0
    assert blocks.density_cohorts(pairs, u, catalog.NEAR, 2).exceptAll(c).count() > 0


def test_agglomeration_in_batches_is_that_by_single_merges():
    m = np.abs(np.random.default_rng(1).normal(size=(300, 16)))
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    sums, members, live = m.copy(), [[i] for i in range(300)], list(range(300))
    while len(live) > 1 and len(members[small := min(live, key=lambda c: (len(members[c]), c))]) < 8:
        live.remove(small)
        to = live[int(((sums[live] @ sums[small]) / [len(members[c]) for c in live]).argmax())]
        sums[to] += sums[small]
        members[to] += members[small]
    head = {i: min(members[c]) for c in live for i in members[c]}
    for cells in (300 * 16, 8_000_000):
        assert blocks.merged(m.copy(), 8, cells).tolist() == [head[i] for i in range(300)]


def test_agglomerative_takes_more_than_2000_users(spark):
    v = spark.range(2_400).selectExpr("id as user_id", "cast(id % 40 as string) as feature", "1.0 as weight")
    sizes = [r["members"] for r in campaigns.sizes(blocks.agglomerative_cohorts(v, 20)).collect()]
    assert min(sizes) >= 20 and sum(sizes) == 2_400


def test_experiments_have_all_rounds_and_lengths(spark, monkeypatch):
    seen = []
    table = users(spark, 1).selectExpr("1.0 as micro_recall", "1.0 as macro_recall", "1.0 as precision")
    monkeypatch.setattr(catalog.workloads, "compare", lambda v, c, k, rounds, lengths, p, seed: seen.append((rounds, lengths)) or table)
    monkeypatch.setattr(catalog.workloads, "p_sweep", lambda v, u, c, grid, k, rounds, seed: seen.append((rounds, grid)) or table)
    monkeypatch.setattr(catalog.mode_split, "mode_split", lambda v, u, **o: seen.append(o["rounds"]) or mode_split.Cohorts(u, u, 0))
    for name in ("recall_table", "p_sweep", "full_split_baskets", "full_split_pair_key", "full_split_strict"):
        catalog.queries()[name](spark, SF)
    assert seen == [(1000, (50, 75, 100)), (1000, [x / 10 for x in range(5, 16)]), 1000, 1000, 1000]


def test_copies_get_keys_once_and_stop(monkeypatch):
    """Fifty copies beside ten others never split at K = 20; keys of copies were made in all 1000 rounds."""
    made, of = [], mode_split.Keys.of
    monkeypatch.setattr(mode_split.Keys, "of", lambda self, s, *a: made.append(len(s.ptr) - 1) or of(self, s, *a))
    code = np.concatenate([np.tile([1, 2, 3], 50), np.arange(100, 110)])
    s = hashing.Sparse(code, np.ones(160), np.concatenate([np.arange(0, 150, 3), np.arange(150, 161)]))
    label, log = mode_split.split_here(s, 0, 1, 1000, 20, mode_split.Keys())
    assert set(label.tolist()) == {0} and not log and not made
    code = np.concatenate([np.tile([1, 2, 3], 50), np.tile([7, 8], 50)])
    s = hashing.Sparse(code, np.ones(250), np.concatenate([np.arange(0, 150, 3), np.arange(150, 251, 2)]))
    label, log = mode_split.split_here(s, 0, 1, 1000, 20, mode_split.Keys())
    assert len(log) == 1 and len(set(label.tolist())) == 2 and set(made) == {2}


def test_comparison_makes_no_row_of_user_and_campaign(spark, monkeypatch):
    """Packed documents, their campaigns and recalls by bits are those by rows."""
    docs, v = spark.read.parquet(f"{SF}/documents.parquet"), features.doc_terms(spark, SF)
    packed = features.packed_terms(docs, "doc_id", "text").localCheckpoint()
    assert packed.exceptAll(hashing.packed(v).select("user_id", "code", "weight")).count() == 0 and packed.count() == 200
    camps, want = workloads.packed_campaigns(docs, packed, "doc_id", "text", 5).localCheckpoint(), workloads.word_campaigns(v, 5)
    assert camps.exceptAll(want).count() == 0 and camps.count() == want.count() > 0
    runs = [(F.lit(n).alias("groups"), packed.select("user_id", (F.col("user_id") % n).alias("cohort_id"))) for n in (7, 40)]
    nine = lambda d: d.select("groups", *[F.round(c, 9) for c in ("micro_recall", "macro_recall", "precision")], "campaigns")
    rows = nine(workloads.evaluate_all(runs, campaigns.match_users(camps, v))).collect()
    monkeypatch.setattr(workloads.campaigns, "match_users", lambda *a: pytest.fail("matches as rows"))
    assert sorted(nine(workloads.evaluate_bits(runs, camps, packed, 200, each=50)).collect()) == sorted(rows)


def test_sweep_packs_vectors_once(spark, monkeypatch):
    """Each power runs on the same packed vectors, with users without features; they were packed and matched by rows for each."""
    v, u = vectors(spark, [(i, f"n:{i % 2}", 1.0 + i) for i in range(20)] + [(i, f"n:{i % 5}", 2.0) for i in range(15)]), users(spark, 26)
    v, camps, seen, split = features.clean(v), workloads.basket_campaigns(spark), [], mode_split.mode_split
    want = workloads.evaluate_all([(F.lit(p).alias("p"), split(v, u, 3, 40, p, 7).assignments) for p in (0.5, 1.2)], campaigns.match_users(camps, v))
    monkeypatch.setattr(workloads.mode_split, "mode_split", lambda x, *a: seen.append(x.inputFiles()) or split(x, *a))
    got = workloads.p_sweep(v, u, camps, (0.5, 1.2), 3, 40, 7)
    nine = lambda d: sorted(map(str, d.select("p", *[F.round(c, 9) for c in ("micro_recall", "macro_recall", "precision")], "campaigns").collect()))
    assert nine(got) == nine(want) and len(seen) == 2 and seen[0] == seen[1] and seen[0]


def test_signature_plan_has_one_exchange_and_no_join(spark):
    v = spark.createDataFrame([(1, "a", 1.0)], "user_id long, feature string, weight double")
    plan = hashing.signatures(v, "weighted", 32)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "Join" not in plan


def test_kernel_matrix_is_positive_definite(spark):
    v = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id < 60"), "vec_id", "embedding")
    assert similarity.least_eigenvalue(similarity.kernel_matrix(v, 1.2)) > -1e-9


def test_packing_power_and_floor_repair(spark):
    v = features.baskets(spark, SF)
    assert features.unpack(features.pack(v)).exceptAll(v).count() == 0
    pair = spark.createDataFrame([(1, 2)], "a long, b long")
    one, two = (similarity.minmax_kernel(x, pair, p).collect()[0]["similarity"] for x, p in ((v, 1.7), (features.power(v, 1.7), 1.0)))
    assert abs(one - two) < 1e-12
    a = spark.createDataFrame([(i, "x" if i < 7 else "y") for i in range(9)], "user_id long, cohort_id string")
    assert blocks.enforce_floor(a, 5).count() == 7 and blocks.enforce_floor(a, 5, "merge").where("cohort_id = 'merged'").count() == 2


def test_copies_are_one_entry_of_the_tables(spark):
    rows = [(i, f"w{j}", 1.0) for i in range(30) for j in range(20)] + [(99, f"w{j}", 1.0) for j in range(19)]
    v = vectors(spark, rows)
    got = neighbours.similar_pairs(hashing.signatures(v, "minwise", 48), v, 0.8, 12, 4).collect()
    assert [(r["a"], r["b"]) for r in got] == [(0, 99)]
    assert neighbours.duplicates(v).where("head = 0").count() == 30


def test_agglomerative_keeps_its_floor_and_kmeans_its_count(spark):
    v = features.split_signs(spark.read.parquet(f"{SF}/embeddings.parquet").where("vec_id < 80"), "vec_id", "embedding")
    sizes = [r["members"] for r in campaigns.sizes(blocks.agglomerative_cohorts(v, 8)).collect()]
    assert min(sizes) >= 8 and sum(sizes) == 80
    assert blocks.kmeans_cohorts(v, 5, dimensions=128).select("cohort_id").distinct().count() <= 5
    with pytest.raises(ValueError):
        blocks.agglomerative_cohorts(v, 8, max_users=10)


def test_own_seeds_of_each_user_would_break_the_law(spark):
    """Users with equal vectors share every key under shared draws; with draws of their own they would not."""
    s = hashing.Sparse(np.tile(np.array([randomness.code_of(x) for x in "abcd"]), 2), np.ones(8), np.array([0, 4, 8]))
    shared = hashing.keys_of(s, list(range(64)), p=1.0)
    own = np.stack([hashing.keys_of(s.rows(np.array([i])), list(range(64)), p=1.0, scope=f":{i}")[0] for i in range(2)])
    assert (shared[0] == shared[1]).all() and (own[0] == own[1]).mean() < 0.6
