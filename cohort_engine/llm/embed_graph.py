"""Embedding near-duplicates by robust-pruned flat graphs on overlapping cluster shards; no link is lost at a border.

1. Vectors with equal direction data and label are one class (its smallest id stands for it).
2. ``shards``: cells are split around sampled centres, each class going to its nearest centre, until
   a cell has at most ``shard_rows`` classes of its own. At every level a class also visits each cell
   that may hold a vector within the threshold of it (``visited``), so no link is lost at a border
   and a dense group that no centres can part is compared in all pairs of its sub-blocks.
3. ``parts``: a cell with many visitors becomes several tasks, each with all members of the cell.
4. ``flat_graph``: a cell's members are dealt to overlapping cluster shards (each member to its two
   nearest centres), each shard gives robust-pruned adjacency lists, and the union of the lists in
   both directions is the cell's flat graph.
5. ``range_search``: every member and every visitor searches the united graph greedily from the
   shards' medoids and, once near, expands over everything within the range (less a slack). Links
   are the classes found whose double-precision cosine is at least the threshold. The counts of all
   cells of a class add up.
6. The task audits its search: sampled queries are compared with brute force over the cell, and beam
   and slack are doubled until the recall of the audit is reached; a cell where it never is compares
   everything. ``audit`` does the same over the whole table, for
   a sample of queries in blocks.

Visits grow with what lies near borders: to a group's size squared over ``shard_rows`` in a dense
group (as its links do), and towards the same for the table where a label's vectors have no clusters.

Only counts and one edge per class towards its local component leave a task, never all pairs.

Edge cases: null label or vector, zero vectors, null or non-finite components and empty vectors
link with nothing (0 links, own component); vectors of another length than most are compared only
with equal lengths; repeated ids count as separate vectors of a class; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, discard, join_small, lean, materialise


def robust_prune(v: np.ndarray, degree: int = 24, pool: int = 48, far: int = 32, alpha: float = 1.2, block: int = 512) -> np.ndarray:
    """n x degree neighbours (-1 pads) of the ``pool`` nearest and ``far`` drawn ones, which join clusters: nearest first, dropping those that a kept one is ``alpha`` times nearer to."""
    n = len(v)
    pool = min(pool, n - 1)
    drawn = np.random.default_rng(n).integers(0, max(n, 1), (n, far if n > pool + 1 else 0))
    out = np.full((n, degree), -1, dtype=np.int32)
    if pool <= 0:
        return out
    for a in range(0, n, block):
        s = v[a : a + block] @ v.T
        s[np.arange(len(s)), np.arange(a, a + len(s))] = -9
        near = np.concatenate([np.argpartition(-s, pool - 1, axis=1)[:, :pool], drawn[a : a + block]], axis=1)
        near = np.take_along_axis(near, np.argsort(-np.take_along_axis(s, near, 1), axis=1, kind="stable"), 1)
        dist = 1 - np.take_along_axis(s, near, 1)
        cand = v[near]
        between = 1 - np.matmul(cand, cand.transpose(0, 2, 1))
        alive = dist < 9  # a vector is no neighbour of itself
        rows, filled = np.arange(len(s)), np.zeros(len(s), dtype=int)
        for k in range(near.shape[1]):
            take = alive[:, k] & (filled < degree)
            out[a + rows[take], filled[take]] = near[take, k]
            filled[take] += 1
            alive[take] &= ~(alpha * between[take, k] <= dist[take]) & (near[take] != near[take, k][:, None])
    return out


def _cluster_shards(v: np.ndarray, rows: int, overlap: int = 2) -> list[np.ndarray]:
    """Overlapping shards of about ``rows`` vectors: each vector goes to its ``overlap`` nearest centres; what stays too large is cut along one more direction, halves overlapping."""
    n = len(v)
    k = -(-n // rows)
    if k < 2:
        return [np.arange(n)]
    rng = np.random.default_rng(n)
    centres = v[np.sort(rng.permutation(n)[: 2 * k])]
    near = np.argpartition(-(v @ centres.T), min(overlap, len(centres) - 1) - 1, axis=1)[:, :overlap]
    out = []
    for c in range(len(centres)):
        own = np.flatnonzero((near == c).any(axis=1))
        if len(own) > 2 * rows:
            own = own[np.argsort(v[own] @ rng.normal(size=v.shape[1]), kind="stable")]
            out += [own[a : a + rows] for a in range(0, len(own) - rows // 2, rows // 2)]
        elif len(own):
            out.append(own)
    return out


def _medoids(v: np.ndarray, shards: list[np.ndarray], near: float = 0.9, each: int = 16) -> np.ndarray:
    """The shards' medoids, and farthest-first vectors until each vector is ``near`` one or one in ``each`` is taken."""
    out = [int(own[(v[own] @ v[own].mean(axis=0)).argmax()]) for own in shards]
    best = (v @ v[out].T).max(axis=1)
    while len(out) < len(v) // each and best.min() < near:
        out.append(int(best.argmin()))
        best = np.maximum(best, v @ v[out[-1]])
    return np.unique(out)


def flat_graph(v: np.ndarray, degree: int = 24, graph_rows: int = 640) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts of the lists, neighbours, medoids): the union, in both directions, of the shards' robust-pruned lists."""
    n = len(v)
    pairs, shards = [np.zeros(0, np.int64)], _cluster_shards(v, graph_rows)
    for own in shards:
        near = robust_prune(v[own], degree)
        i, k = np.nonzero(near >= 0)
        a, b = own[i].astype(np.int64), own[near[i, k]].astype(np.int64)
        pairs += [a * n + b, b * n + a]
    pairs = np.unique(np.concatenate(pairs))
    return np.searchsorted(pairs // n, np.arange(n + 1)), pairs % n, _medoids(v, shards)


def _lists(ptr: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(which of ``nodes``, place in the neighbour array) of all their neighbours."""
    count = ptr[nodes + 1] - ptr[nodes]
    which = np.repeat(np.arange(len(nodes)), count)
    return which, np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count) + ptr[nodes][which]


def range_search(v: np.ndarray, graph: tuple[np.ndarray, np.ndarray, np.ndarray], queries: np.ndarray, radius: float, patience: int = 12, slack: float = 0.03, members: int = 0):
    """Yields (first query of a block, cosines of its queries x ``v`` with -9 for what was not reached).

    The first ``members`` queries are the first rows of ``v`` and start at themselves too.
    """
    ptr, adj, medoids = graph
    n = len(v)
    size = max(1, min(256, 8_000_000 // max(n, 1)))
    for a in range(0, len(queries), size):
        q = queries[a : a + size]
        sim = np.full((len(q), n), -9.0)
        open_ = np.full((len(q), n), -9.0)  # reached, not yet expanded
        sim[:, medoids] = open_[:, medoids] = q @ v[medoids].T
        own = np.arange(max(0, min(members - a, len(q))))
        sim[own, a + own] = open_[own, a + own] = np.einsum("ij,ij->i", q[own], v[a + own])
        best, since = sim.max(axis=1), np.zeros(len(q), dtype=int)
        live = np.arange(len(q))
        while len(live):
            head = open_[live].argmax(axis=1)
            top = open_[live, head]
            within = open_[live] >= radius - slack
            go = (top > -9) & ((since[live] < patience) | within.any(axis=1))
            live, head, within = live[go], head[go], within[go]
            if not len(live):
                break
            i, node = np.nonzero(within)
            greedy = ~within.any(axis=1)
            qi, ni = np.concatenate([live[i], live[greedy]]), np.concatenate([node, head[greedy]])
            open_[qi, ni] = -9.0
            for c in range(0, len(qi), 20_000):
                which, at = _lists(ptr, ni[c : c + 20_000])
                pq, pn = qi[c : c + 20_000][which], adj[at]
                ok = sim[pq, pn] == -9.0
                flat = np.unique(pq[ok].astype(np.int64) * n + pn[ok])
                pq, pn = flat // n, flat % n
                sim[pq, pn] = open_[pq, pn] = np.einsum("ij,ij->i", q[pq], v[pn])
            now = sim[live].max(axis=1)
            since[live] = np.where(now > best[live] + 1e-12, 0, since[live] + 1)
            best[live] = now
        yield a, sim


def _union(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest position reachable, by repeated minimum and pointer jumping."""
    lab = np.arange(n)
    while len(a):
        low = np.minimum(lab[a], lab[b])
        before = lab.copy()
        np.minimum.at(lab, lab[a], low)
        np.minimum.at(lab, lab[b], low)
        np.minimum.at(lab, a, low)
        np.minimum.at(lab, b, low)
        lab = lab[lab]
        if (lab == before).all():
            break
    return lab


def classes(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members: vec_id, cls or null; reps: id, label, v (unit, double), w) of ``rows`` (vec_id, embedding, label)."""
    e = F.transform("embedding", lambda x: x.cast("double"))
    d = rows.select(F.col("vec_id").cast("long"), F.col("label").cast("string").alias("label"), e.alias("e"))
    finite = F.forall("e", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    top = F.array_max(F.transform("e", F.abs))
    good = F.col("label").isNotNull() & F.col("e").isNotNull() & (F.size("e") > 0) & finite & (top > 0)
    d = d.withColumn("ok", F.coalesce(good, F.lit(False)))
    scaled = F.transform("e", lambda x: x / top)  # so that squares of very small or large values neither vanish nor overflow
    d = d.withColumn("e", F.when(F.col("ok"), scaled))
    norm = F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x))
    d = d.withColumn("v", F.when(F.col("ok"), F.transform("e", lambda x: x / norm))).select("vec_id", "label", "v", "ok")
    d = materialise(d, "embed_rows")
    good_rows = d.where("ok")
    reps = materialise(good_rows.groupBy("label", "v").agg(F.min("vec_id").alias("id"), F.count("*").alias("w")), "embed_reps")
    member = good_rows.join(reps.select("label", "v", F.col("id").alias("cls")), ["label", "v"]).select("vec_id", "cls")
    return member.unionByName(d.where("not ok").select("vec_id", F.lit(None).cast("long").alias("cls"))), reps


def visited(x: np.ndarray, centres: np.ndarray, threshold: float) -> np.ndarray:
    """Rows x centres: whether the centre's cell may hold a unit vector at cosine ``threshold`` or more to the row.

    Whatever is nearer to c than to d lies beyond the plane between them, and x is within the angle of
    the threshold of it only if x . (d - c) / |d - c| is at most that angle's sine.
    """
    s = x @ centres.T
    out = np.ones(s.shape, dtype=bool)
    if threshold > 0:
        sine = max(1 - threshold * threshold, 0.0) ** 0.5
        for c in range(len(centres)):
            apart = np.linalg.norm(centres - centres[c], axis=1)
            out[:, c] = (s - s[:, c : c + 1] <= sine * apart + 1e-9).all(axis=1)
    return out


def shards(reps: DataFrame, shard_rows: int = 2500, branch: int = 16, levels: int = 8, max_broadcast: int = 20_000, threshold: float = 0.98) -> DataFrame:
    """id, cell, v, w, home: each class in its home cell, and as a visitor in every cell that may hold a link of it."""
    now = reps.select("id", "v", "w", F.concat_ws("/", "label", F.size("v").cast("string")).alias("cell"), F.lit(True).alias("home"))
    schema = "id long, v array<double>, w long, cell string, home boolean"

    def assign(batches):
        for b in batches:
            for _, g in b.groupby("cell"):
                c = np.stack([np.asarray(x, float) for x in g["centres"].iloc[0]])
                for a in range(0, len(g), 1000):
                    part = g.iloc[a : a + 1000]
                    v, own = np.stack(part["v"].to_list()), part["home"].to_numpy()
                    near, goes = (v @ c.T).argmax(axis=1), visited(v, c, threshold)
                    goes[np.flatnonzero(own), near[own]] = True
                    i, k = np.nonzero(goes)
                    rows = part.iloc[i]
                    yield rows.assign(cell=[f"{x}/{y}" for x, y in zip(rows["cell"], k)], home=own[i] & (near[i] == k))[["id", "v", "w", "cell", "home"]]

    for _ in range(levels):
        before, now = now, materialise(now, "embed_cells")
        discard(before)
        homes = now.where("home")
        big = homes.groupBy("cell").count().where(F.col("count") > shard_rows).withColumn("k", F.least(F.lit(branch), F.ceil(F.col("count") * 2 / shard_rows)))
        big = materialise(big, "embed_big")
        if not big.limit(1).count():
            return now
        drawn = join_small(homes, big, "cell", "inner", max_broadcast).withColumn("h", F.xxhash64("id", "cell") / F.lit(2.0**64) + 0.5)
        drawn = drawn.where(F.col("h") < 6 * F.col("k") / F.col("count")).withColumn("r", F.row_number().over(Window.partitionBy("cell").orderBy("h", "id"))).where("r <= k")
        centres = materialise(drawn.groupBy("cell").agg(F.collect_list("v").alias("centres")), "embed_centres")
        split = join_small(now, centres, "cell", "inner", max_broadcast).mapInPandas(assign, schema)
        kept = now.join(F.broadcast(centres.select("cell")) if centres.limit(max_broadcast + 1).count() <= max_broadcast else centres.select("cell"), "cell", "left_anti")
        split = kept.select("id", "v", "w", "cell", "home").unionByName(split)
        split._cohort_path = now._cohort_path
        now = split
    return materialise(now, "embed_shards")


def parts(cells: DataFrame, visitors: int = 5000, max_broadcast: int = 20_000) -> DataFrame:
    """``cells`` with ``part``: a cell's visitors are dealt over parts of about ``visitors``, and its own members come with each part."""
    n = cells.groupBy("cell").agg(F.ceil(F.count(F.when(~F.col("home"), 1)) / visitors).cast("int").alias("n"))
    n = materialise(n.withColumn("n", F.greatest("n", F.lit(1))), "embed_parts")
    every = F.sequence(F.lit(0), F.col("n") - 1)
    return join_small(cells, n, "cell", "inner", max_broadcast).withColumn("part", F.explode(F.when(F.col("home"), every).otherwise(F.array(F.pmod(F.xxhash64("id"), F.col("n")).cast("int"))))).drop("n")


def _merge(lab: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Labels ``lab`` after the pairs (a, b) are joined."""
    a, b = lab[a], lab[b]
    apart = np.unique((np.minimum(a, b) * len(lab) + np.maximum(a, b))[a != b])
    return _union(len(lab), apart // len(lab), apart % len(lab))[lab] if len(apart) else lab


def cell_links(v: np.ndarray, w: np.ndarray, n: int, first: int, threshold: float, degree: int = 24, audit_queries: int = 128, audit_recall: float = 1.0) -> tuple[np.ndarray, np.ndarray, bool]:
    """(links of each row of ``v`` from ``first`` on with the ``n`` members, labels of linked rows, whether the graph's audit was reached).

    The members come first in ``v``; each row stands for ``w`` vectors.
    """
    own, q = v[:n], v[first:]
    counts, lab = np.zeros(len(v), dtype=np.int64), np.arange(len(v))
    if not n or not len(q):
        return counts, lab, True
    graph = flat_graph(own, degree)
    sample = q[np.unique(np.linspace(0, len(q) - 1, min(audit_queries, len(q))).astype(int))]
    there = int((sample @ own.T >= threshold).sum())
    patience, slack, reached = 12, 0.03, False
    for _ in range(6):
        found = sum(int((s >= threshold).sum()) for _, s in range_search(own, graph, sample, threshold, patience, slack))
        reached = found >= audit_recall * there
        if reached:
            break
        patience, slack = patience * 2, slack * 2
    blocks = range_search(own, graph, q, threshold, patience, slack, n - first) if reached else ((a, q[a : a + 256] @ own.T) for a in range(0, len(q), 256))
    inner = [np.zeros(0, np.int64)]
    for a, sim in blocks:
        i, j = np.nonzero(sim >= threshold)
        i = i + a + first
        i, j = i[i != j], j[i != j]
        inner.append(i[i < n] * n + j[i < n])
        i, j = i[i >= n], j[i >= n]
        counts += np.bincount(i, weights=w[j], minlength=len(v)).astype(np.int64)
        lab = _merge(lab, i, j)
    found = np.concatenate(inner)  # a link found from either end is one
    found = np.unique(np.concatenate([found, found % n * n + found // n]))
    counts += np.bincount(found // n, weights=w[found % n], minlength=len(v)).astype(np.int64)
    lab = _merge(lab, found // n, found % n)
    counts[first:n] += w[first:n] - 1
    return counts, lab, reached


def links(rows: DataFrame, threshold: float = 0.98, shard_rows: int = 2500, degree: int = 24, audit_queries: int = 128, audit_recall: float = 1.0) -> DataFrame:
    """vec_id, n_links, component_id, kept."""
    member, reps = classes(rows)
    nodes = parts(shards(reps, shard_rows, threshold=threshold))

    def search(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["home", "id"], ascending=[False, True])
        ids, n = g["id"].to_numpy(), int(g["home"].sum())
        first = 0 if g["part"].iloc[0] == 0 else n  # the members' own links belong to part 0
        counts, lab, _ = cell_links(np.stack(g["v"].to_list()), g["w"].to_numpy(), n, first, threshold, degree, audit_queries, audit_recall)
        out = pd.DataFrame({"id": ids, "n_links": counts, "root": ids[lab]})
        return out[(counts > 0) | (lab != np.arange(len(ids)))]

    found = materialise(nodes.groupBy("cell", "part").applyInPandas(lean(search), "id long, n_links long, root long"), "embed_found")
    comp = components(found.where("id != root").select(F.col("id").alias("a"), F.col("root").alias("b")))
    per = found.groupBy(F.col("id").alias("cls")).agg(F.sum("n_links").alias("n_links"))
    per = per.join(comp.withColumnRenamed("id", "cls"), "cls", "left")
    out = member.join(per, "cls", "left")
    comp_id = F.coalesce("component", "cls", "vec_id")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), comp_id.alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))


def audit(rows: DataFrame, result: DataFrame, threshold: float = 0.98, every: int = 20, block: int = 20_000) -> float:
    """Recall of ``result``'s links for ids divisible by ``every``, against brute force.

    The queries are a stated set; they go to the executors in blocks and meet every row there.
    """
    member, reps = classes(rows)
    cls = {r["cls"] for r in member.where((F.col("vec_id") % every == 0) & F.col("cls").isNotNull()).select("cls").distinct().collect()}
    want: dict[int, int] = {}
    ids = sorted(cls)
    for a in range(0, len(ids), block):
        q = reps.where(F.col("id").isin(ids[a : a + block])).toPandas()
        per = {(k, n): (g["id"].to_numpy(), np.stack(g["v"].to_list())) for (k, n), g in q.assign(n=q["v"].map(len)).groupby(["label", "n"])}

        def count(batches, per=per):
            for b in batches:
                for (label, n), g in b.assign(n=b["v"].map(len)).groupby(["label", "n"]):
                    if (label, n) in per:
                        ids_, m = per[label, n]
                        yield pd.DataFrame({"id": ids_, "n": (m @ np.stack(g["v"].to_list()).T >= threshold) @ g["w"].to_numpy()})

        for r in reps.mapInPandas(count, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).collect():
            want[r["id"]] = r["n"] - 1
    got = {r["vec_id"]: r["n_links"] for r in result.where(F.col("vec_id").isin(ids)).collect()}
    total = sum(want.values())
    return sum(min(got.get(k, 0), n) for k, n in want.items()) / total if total else 1.0
