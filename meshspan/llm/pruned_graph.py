"""Embedding near-dedup on a robust-pruned flat graph.

Equal vectors of a label are one class. Each label's classes are cut into cluster shards around
sampled centres, every class in its few nearest shards, so that shards overlap. A shard links each
class to a pruned choice of its nearest ones: a candidate is dropped if a kept one is closer to it, by
the factor alpha, than the class itself is. The adjacency lists of a class from all its shards are
united, edges are made mutual, and every class is searched in its shards: a greedy beam from the
shard's medoid and the class's own place, then an expansion through all neighbours in range. Cosines
are verified in double precision. A sample of each shard's searches is audited against an exact
scan; a shard that misses a link is searched again exactly. How many shards a class enters is set per
label by trial: sampled rows get partners at just the threshold's angle, and the overlap is the one at
which all but a given share of such pairs, the hardest there are, have a shard in common.

A pair that shares several shards is counted in the first of them. A shard returns link counts
and a spanning forest, never its pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.llm.common import connected_components, stored
from meshspan.llm.hashed_search import matrix
from meshspan.llm.simhash import forest

_MAX_CENTRES = 1 << 16


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(1))[:, None]


def cosines(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Cosines of row pairs, in double precision."""
    out = np.empty(len(a))
    norm = np.sqrt((x * x).sum(1))
    for at in range(0, len(a), 1 << 18):
        i, j = a[at : at + (1 << 18)], b[at : at + (1 << 18)]
        out[at : at + (1 << 18)] = np.einsum("ij,ij->i", x[i], x[j]) / (norm[i] * norm[j])
    return out


# ---------------------------------------------------------------- one shard


def pruned_neighbours(x: np.ndarray, degree: int = 24, candidates: int = 64, alpha: float = 1.2) -> np.ndarray:
    """Robust-pruned out-neighbours of unit rows, -1 where fewer are kept."""
    n = len(x)
    c = min(candidates, n - 1)
    out = np.full((n, degree), -1, np.int64)
    if c < 1:
        return out
    for at in range(0, n, 256):
        own = np.arange(at, min(at + 256, n))
        sims = x[own] @ x.T
        sims[np.arange(len(own)), own] = -2
        near = np.argpartition(-sims, c - 1, axis=1)[:, :c]
        near = np.take_along_axis(near, np.argsort(-np.take_along_axis(sims, near, 1), axis=1, kind="stable"), 1)
        to_own = np.sqrt(np.maximum(0, 2 - 2 * np.take_along_axis(sims, near, 1)))
        between = np.sqrt(np.maximum(0, 2 - 2 * np.einsum("bid,bjd->bij", x[near], x[near], optimize=True)))
        alive = np.ones(near.shape, bool)
        row = np.arange(len(own))
        for slot in range(degree):
            first = alive.argmax(1)
            there = alive[row, first]
            if not there.any():
                break
            out[own[there], slot] = near[row[there], first[there]]
            alive[row, first] = False
            alive &= ~(there[:, None] & (alpha * between[row, first] <= to_own))
    return out


def range_search(x: np.ndarray, links: np.ndarray, threshold: float, beam: int = 16, steps: int = 48, block: int = 256):
    """Pairs (query, other) with cosine >= threshold that the graph search finds for every row.

    ``links``: boolean adjacency. Rows are unit vectors.
    """
    n = len(x)
    medoid = int(np.argmax(x @ x.mean(0)))
    degree = max(1, int(links.sum(1).max()))
    table = np.full((n + 1, degree), n)
    at = np.nonzero(links)
    table[at[0], np.arange(len(at[0])) - np.repeat(np.cumsum(links.sum(1)) - links.sum(1), links.sum(1))] = at[1]
    padded = np.vstack((x, np.zeros((1, x.shape[1]))))
    found_a, found_b = [], []
    floats = links.astype(np.float32)
    for start in range(0, n, block):
        own = np.arange(start, min(start + block, n))
        q, row = x[own], np.arange(len(own))
        seen = np.zeros((len(own), n + 1), bool)
        seen[:, n] = True
        sims = np.full((len(own), n + 1), -2.0)
        for entry in (np.full(len(own), medoid), own):
            seen[row, entry] = True
            sims[row, entry] = np.einsum("ij,ij->i", q, x[entry])
        ids = np.column_stack((np.full(len(own), medoid), own))
        open_ = np.ones(ids.shape, bool)
        open_[own == medoid, 1] = False
        for _ in range(steps):
            value = np.where(open_, sims[row[:, None], ids], -3)
            best = value.argmax(1)
            go = value[row, best] > -3
            if not go.any():
                break
            r = row[go]
            open_[r, best[go]] = False
            around = table[ids[r, best[go]]]
            fresh = ~seen[r[:, None], around]
            seen[r[:, None], around] = True
            new = np.where(fresh, np.einsum("ijk,ik->ij", padded[around], q[r]), -2.0)
            sims[r[:, None], around] = np.where(fresh, new, sims[r[:, None], around])
            wide_ids = np.full((len(own), degree), n)
            wide_ids[r] = np.where(fresh, around, n)
            ids = np.hstack((ids, wide_ids))
            open_ = np.hstack((open_, wide_ids < n))
            order = np.argsort(-sims[row[:, None], ids], axis=1, kind="stable")[:, :beam]
            ids, open_ = np.take_along_axis(ids, order, 1), np.take_along_axis(open_, order, 1)
        inside = seen[:, :n] & (sims[:, :n] >= threshold - 0.01)
        spread = inside
        while spread.any():  # expand through everything in range
            near = (spread.astype(np.float32) @ floats > 0) & ~seen[:, :n]
            i, j = np.nonzero(near)
            sims[i, j] = np.einsum("ij,ij->i", q[i], x[j])
            seen[i, j] = True
            spread = near & (sims[:, :n] >= threshold - 0.01)
            inside = inside | spread
        i, j = np.nonzero(inside)
        found_a.append(own[i])
        found_b.append(j)
    a, b = np.concatenate(found_a), np.concatenate(found_b)
    return a[a != b], b[a != b]


def exact_pairs(x: np.ndarray, rows: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """All pairs (row, other) with cosine >= threshold, by blocks."""
    found_a, found_b = [], []
    for at in range(0, len(rows), 512):
        own = rows[at : at + 512]
        i, j = np.nonzero(x[own] @ x.T >= threshold - 1e-6)
        found_a.append(own[i])
        found_b.append(j)
    a, b = np.concatenate(found_a), np.concatenate(found_b)
    return a[a != b], b[a != b]


def shard_links(vectors: np.ndarray, links: np.ndarray, threshold: float, audit: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """Verified links (both directions) among a shard's vectors."""
    n = len(vectors)
    if n < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    x = unit(vectors)
    a, b = range_search(x, links, threshold)
    a, b = np.unique(np.concatenate((a * n + b, b * n + a))) // n, np.unique(np.concatenate((a * n + b, b * n + a))) % n
    good = cosines(vectors, a, b) >= threshold
    a, b = a[good], b[good]
    probe = np.arange(0, n, audit)
    true_a, true_b = exact_pairs(x, probe, threshold)
    sure = cosines(vectors, true_a, true_b) >= threshold
    if np.setdiff1d(true_a[sure] * n + true_b[sure], a * n + b).size:
        a, b = exact_pairs(x, np.arange(n), threshold)
        good = cosines(vectors, a, b) >= threshold
        a, b = a[good], b[good]
    return a, b


def overlap_needed(rows: np.ndarray, centres: np.ndarray, threshold: float, least: int, miss: float = 1e-3, probes: int = 1024, seed: int = 0) -> int:
    """Nearest centres that each row must enter so that of pairs at exactly ``threshold`` no more than the share
    ``miss`` has no centre in common; at least ``least``. Partners of up to ``probes`` unit rows that are no centres
    are drawn: one in any direction, one towards another row."""
    if len(centres) <= least or not len(rows):
        return least
    random = np.random.default_rng(seed)
    u = rows[random.permutation(len(rows))[: 2 * probes]]
    u = u[(u @ centres.T).max(1) < 1 - 1e-9][:probes]
    ranks = []
    for towards in (random.standard_normal(u.shape), rows[random.integers(0, len(rows), len(u))]):
        side = towards - (towards * u).sum(1)[:, None] * u
        length = np.sqrt((side * side).sum(1))
        some = length > 1e-9
        v = threshold * u[some] + np.sqrt(1 - threshold**2) * side[some] / length[some][:, None]
        for at in range(0, len(v), 64):
            # place of each centre in a row's order; a pair meets at the least of the larger places
            places = [np.argsort(np.argsort(-(x[at : at + 64] @ centres.T), axis=1, kind="stable"), axis=1) for x in (u[some], v)]
            ranks.append(np.maximum(*places).min(1) + 1)
    ranks = np.concatenate(ranks) if ranks else np.zeros(0, int)
    return max(least, int(np.quantile(ranks, 1 - miss, method="higher"))) if len(ranks) else least


# ---------------------------------------------------------------- Spark plan


def _centres(classes: DataFrame, shard_rows: int, overlap: int, threshold: float, seed: int) -> dict[int, tuple[np.ndarray, int]]:
    """Unit centres of every label, and how many of them a class enters: a hash sample of bounded size, thinned so
    that no two of a label lie close together (a dense group has one centre)."""
    sizes = {r["label"]: r["n"] for r in classes.groupBy("label").agg(F.count("*").alias("n")).orderBy(F.desc("n")).limit(_MAX_CENTRES).collect()}
    total = sum(sizes.values())
    rate = max(1, int(max(shard_rows, total / _MAX_CENTRES * 4) / 4))
    rows = classes.where(F.pmod(F.xxhash64(F.lit(seed), "rep"), F.lit(rate)) == 0).select("label", "rep", "x").toArrow().sort_by([("label", "ascending"), ("rep", "ascending")])
    labels, x = np.asarray(rows["label"]), matrix(rows["x"])
    out = {}
    for label, n in sizes.items():
        own = unit(x[labels == label]) if (labels == label).any() else np.zeros((0, x.shape[1]))
        chosen: list[np.ndarray] = []
        for v in own:
            if len(chosen) >= max(1, n // shard_rows):
                break
            if not chosen or (np.array(chosen) @ v).max() < 0.6:
                chosen.append(v)
        out[label] = np.array(chosen), overlap_needed(own, np.array(chosen), threshold, overlap, seed=seed)
    return out


_PLACED = pa.schema([("label", pa.int64()), ("shard", pa.int32()), ("rep", pa.int64()), ("n", pa.int64()), ("x", pa.list_(pa.float64())), ("shards", pa.list_(pa.int32()))])


def near_duplicate_vectors(vectors: DataFrame, threshold: float = 0.93, shard_rows: int = 256, overlap: int = 4, degree: int = 24, seed: int = 5, largest: int = 4096) -> DataFrame:
    """Links among ``vectors(vec_id, embedding, label)`` of equal, non-null labels with cosine >= threshold.

    One row per input row: vec_id, n_links (rows linked to it directly), component_id (smallest vec_id
    reachable, itself included), kept (vec_id = component_id). Null labels, and vectors that are null,
    zero or hold null or non-finite components link with nothing; equal vectors link; vectors of other
    lengths than their label's are an error; repeated rows link as equal vectors; an empty table gives no
    rows. ``overlap``: least number of shards per vector (:func:`overlap_needed`); ``shard_rows``: aim for a shard before overlap;
    ``largest``: rows of a task, beyond which a dense shard is searched by pairs of its chunks.
    """
    spark = vectors.sparkSession
    x = F.transform(F.col("embedding").cast("array<double>"), lambda v: v + F.lit(0.0))
    bad = F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    fit = F.coalesce(F.col("label").isNotNull() & F.col("vec_id").isNotNull() & ~bad & F.exists(x, lambda v: v != 0), F.lit(False))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.when(fit, x).alias("x"))
    keyed = stored(rows.select("*", F.xxhash64("label", "x").alias("h1"), F.xxhash64(F.lit(seed), "x", "label").alias("h2")), "rows")
    classes = stored(
        keyed.where("x is not null").groupBy("label", "x", "h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n")), "classes"
    )
    centres = _centres(classes, shard_rows, overlap, threshold, seed)
    shared = spark.sparkContext.broadcast(centres)

    def place(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            labels, v = np.asarray(batch.column("label")), matrix(batch.column("x"))
            reps, n = np.asarray(batch.column("rep")), np.asarray(batch.column("n"))
            parts = []
            for label in np.unique(labels):
                own = np.flatnonzero(labels == label)
                c, m = shared.value.get(int(label), (np.zeros((0, v.shape[1])), 1))
                m = min(m, len(c)) or 1
                near = np.sort(np.argsort(-(unit(v[own]) @ c.T), axis=1, kind="stable")[:, :m], axis=1) if len(c) else np.zeros((len(own), 1), int)
                for j in range(m):
                    parts.append((own, near[:, j], near))
            for own, shard, near in parts:
                yield pa.RecordBatch.from_arrays(
                    [pa.array(labels[own]), pa.array(shard.astype(np.int32)), pa.array(reps[own]), pa.array(n[own])]
                    + [batch.column("x").take(pa.array(own)).cast(pa.list_(pa.float64())), pa.array(near.astype(np.int32).tolist(), pa.list_(pa.int32()))],
                    schema=_PLACED,
                )

    placed = stored(
        classes.select("label", "rep", "n", "x").mapInArrow(place, "label long, shard int, rep long, n long, x array<double>, shards array<int>"), "placed"
    )

    def build(key: tuple, group: pa.Table) -> pa.Table:
        group = group.sort_by("rep")
        reps, v = np.asarray(group["rep"]), unit(matrix(group["x"]))
        out = pruned_neighbours(v, degree)
        i, slot = np.nonzero(out >= 0)
        j = out[i, slot]
        return pa.table({"label": pa.array(np.full(2 * len(i), key[0].as_py()), pa.int64()), "rep": pa.array(np.concatenate((reps[i], reps[j])), pa.int64()), "other": pa.array(np.concatenate((reps[j], reps[i])), pa.int64())})

    # A shard beyond its size is cut into chunks, and every two chunks are a task of their own.
    sizes = placed.groupBy("label", "shard").agg(F.count("*").alias("n_shard")).where(F.col("n_shard") > largest)
    sizes = stored(sizes.select("label", "shard", F.ceil(F.col("n_shard") / (largest // 2)).cast("int").alias("chunks")), "sizes")
    cut = placed.join(sizes, ["label", "shard"], "left").withColumn("chunks", F.coalesce("chunks", F.lit(1)))
    cut = cut.withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    placed = cut.withColumn("low", F.least("chunk", "other")).withColumn("high", F.greatest("chunk", "other")).drop("other", "chunks")
    task = ["label", "shard", "low", "high"]
    edges = placed.groupBy(*task).applyInArrow(build, "label long, rep long, other long")
    adjacency = stored(edges.groupBy("label", "rep").agg(F.collect_set("other").alias("others")), "adjacency")
    ready = placed.join(adjacency, ["label", "rep"], "left")

    def search(key: tuple, group: pa.Table) -> pa.Table:
        group = group.sort_by("rep")
        reps, n, v = np.asarray(group["rep"]), np.asarray(group["n"]), matrix(group["x"])
        shard = key[1].as_py()
        links = np.zeros((len(reps), len(reps)), bool)
        for i, others in enumerate(group["others"].to_pylist()):
            if others:
                others = np.array(others)
                at = np.minimum(np.searchsorted(reps, others), len(reps) - 1)
                links[i, at[reps[at] == others]] = True
        links |= links.T
        a, b = shard_links(v, links, threshold)
        chunk = np.asarray(group["chunk"])
        due = (chunk[a] != chunk[b]) == (key[2].as_py() != key[3].as_py())  # chunk pairs count their own pairs
        a, b = a[due], b[due]
        entered = np.array(group["shards"].to_pylist(), np.int32)  # as many for each class of a label, in order
        first = np.zeros(len(a), bool)
        for at in range(0, len(a), 8192):
            own, other = entered[a[at : at + 8192]], entered[b[at : at + 8192]]
            common = (own[:, :, None] == other[:, None, :]).any(2)
            first[at : at + 8192] = own[np.arange(len(own)), common.argmax(1)] == shard
        weight = np.bincount(a[first], weights=n[b[first]], minlength=len(reps)).astype(np.int64)
        root = forest(a[a < b], b[a < b], len(reps))
        return pa.table({"rep": pa.array(reps, pa.int64()), "links": pa.array(weight, pa.int64()), "root": pa.array(reps[root], pa.int64())})

    found = stored(ready.groupBy(*task).applyInArrow(search, "rep long, links long, root long"), "found")
    parts = connected_components(found.select(F.col("rep").alias("src"), F.col("root").alias("dst")))
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    result = stored(
        classes.select("h1", "h2", "rep", "n").join(counts, "rep").join(parts.withColumnRenamed("node", "rep"), "rep", "left")
        .select("h1", "h2", (F.col("n") - 1 + F.col("links")).alias("n_links"), F.coalesce("component", "rep").alias("component_id")),
        "result",
    )
    linked = keyed.where("x is not null").join(result, ["h1", "h2"]).select("vec_id", "n_links", "component_id")
    alone = keyed.where("x is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def recall(found: DataFrame, vectors: DataFrame, threshold: float = 0.93, sample: int = 256) -> float:
    """Share of all true links of a bounded sample of rows that ``found`` counts (1 if they have none): each sampled
    row of ``vectors`` against all rows of its label, whatever shards they share."""
    x = F.col("embedding").cast("array<double>")
    bad = F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    rows = vectors.where(F.col("label").isNotNull() & F.col("vec_id").isNotNull() & x.isNotNull() & ~bad & F.exists(x, lambda v: v != 0))
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), x.alias("x"))
    asked = rows.orderBy(F.xxhash64("vec_id")).limit(sample).toArrow()
    ids, labels, q = np.asarray(asked["vec_id"]), np.asarray(asked["label"]), matrix(asked["x"])

    def count(batches):
        for batch in batches:
            if batch.num_rows and len(ids):
                hits = (unit(matrix(batch.column("x"))) @ unit(q).T >= threshold) & (np.asarray(batch.column("label"))[:, None] == labels)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(hits.sum(0).astype(np.int64))], ["vec_id", "n"])

    true = rows.mapInArrow(count, "vec_id long, n long").groupBy("vec_id").agg((F.sum("n") - 1).alias("n"))
    sums = true.join(found.select("vec_id", "n_links"), "vec_id").agg(F.sum("n").alias("n"), F.sum(F.least("n", "n_links")).alias("hit")).first()
    return sums["hit"] / sums["n"] if sums["n"] else 1.0
