"""The experiments, on the given tables.

A workload turns its samples into node moments once. While their pieces fit a task, its settings run as one Spark
job with a task per setting; beyond that every product of every setting is a distributed job on pieces that stay
where they are. Rows of the result are the settings' outcomes; ``CLAIMS`` says what of the published behaviour a
row of the registered query must show.
"""

from __future__ import annotations

import dataclasses
import functools
import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.functions.linalg import angle_error, positive_qr, random_basis
from meshspan.operators import loops, moments, nodes, partition
from meshspan.operators.subspace import baseline_loop
from meshspan.operators.topology import Topology, complete, erdos_renyi, ring, second_modulus, star
from meshspan.plans.schedules import RULES, rounds
from meshspan.sources import features
from meshspan.sources.tables import executors, session_conf

BUDGET = 256 << 20
DRIVER_BYTES = 32 << 20  # of node moments that go to the tasks by the driver
TASK_BYTES = 1 << 30  # of node moments that the tasks of an executor read for their settings
SMALL_BATCHES = {"spark.sql.execution.arrow.maxBytesPerBatch": str(2 << 20)}  # they lie beside the moments
#: The union of frames of one partition each keeps their partitions, else their tasks would run as one.
APART = {"spark.sql.unionOutputPartitioning": "false"}
OUTCOME = (
    "workload string, setting string, method string, rule string, nodes int, rank int, delta double, outer int, "
    "p2p_k double, inner_total long, error double, error_max double, below_1e2 long, below_1e4 long, below_1e8 long, slem double, seconds double"
)


def gathered(samples: DataFrame, ns: list[int], d: int, r: int, center: str = "exact") -> dict[int, nodes.LocalNodes | nodes.StoredNodes | nodes.SpreadNodes]:
    """Node moments of the networks of ``ns`` nodes that hold the rows by :func:`partition.by_hash`, over the largest
    eigenvalue of their mean, which is the covariance: in memory, in tables that fit a task, or left distributed.
    Nodes of a network whose size divides the largest hold what several of that network's hold: one scan serves both."""
    with session_conf(samples.sparkSession, SMALL_BATCHES):
        return _gathered(samples, ns, d, r, center)


def _gathered(samples: DataFrame, ns: list[int], d: int, r: int, center: str) -> dict:
    most = max(ns)
    if any(most % n for n in ns):
        samples = samples.cache()
        own = {n: nodes.node_pieces(partition.by_hash(samples, n), n, d, center=center) for n in ns}
        samples.unpersist()
    else:
        whole = nodes.node_pieces(partition.by_hash(samples, most), most, d, center=center)
        own = {n: whole if n == most else whole.coarser(n) for n in ns}
    known, out = None, {}
    for n, table in own.items():
        if max(table.compact, table.bytes) <= DRIVER_BYTES:
            m = table.local()
            out[n] = m.scaled(1 / m.leading(r)[0][0])
            continue
        known = table.leading(r) if known is None else known
        table = dataclasses.replace(table, scale=1 / known[0][0])
        out[n] = nodes.StoredNodes(table, (known[0] / known[0][0], known[1])) if table.compact <= TASK_BYTES else nodes.SpreadNodes(table)
    return out


def node_matrices(samples: DataFrame, n: int, d: int, center: str = "exact") -> np.ndarray:
    """Stacked node matrices, behind a check of their size."""
    if n * d * d * 8 > BUDGET:
        raise ValueError("node matrices exceed the budget")
    m = nodes.node_pieces(samples, n, d, center=center).local()
    return m.matrices if m.matrices is not None else np.stack([x.T @ x for x in m.rows])


def whitened(m: np.ndarray) -> np.ndarray:
    values, vectors = np.linalg.eigh(m.mean(0))
    a = (vectors / np.sqrt(values)).T
    return a @ m @ a.T


def coloured(white: np.ndarray, r: int, delta: float, tied: bool) -> np.ndarray:
    s = np.sqrt(features.spectrum(white.shape[1], r, delta, tied))
    return s[:, None] * white * s


def graph_of(spec: str, n: int) -> Topology:
    """er:<p>, ring, star or complete."""
    kind, _, p = spec.partition(":")
    return erdos_renyi(n, float(p)) if kind == "er" else {"ring": ring, "star": star, "complete": complete}[kind](n)


def _steps(m, c: dict, w: np.ndarray) -> loops.Steps:
    outer, method = c["outer"], c["method"]
    q0 = random_basis(m.d, c["rank"], c.get("seed", 7))
    plan = rounds(RULES.get(c.get("rule", "-"), RULES["50"]), outer)
    if method in ("column", "column_sequential"):
        blocks, whole = partition.column_blocks(m.d, len(w)), nodes.as_nodes(m.total)
        return loops.column_split(whole, blocks, w, plan, q0) if method == "column" else loops.column_sequential(whole, blocks, w, plan, max(1, outer // c["rank"]), q0)
    if method == "row":
        return loops.row_split(m, w, plan, q0)
    return baseline_loop(method, w, plan, outer, q0, c.get("step", 0.1), c.get("mix", 3))(m)


def _outcome(workload: str, c: dict, m, values: np.ndarray, truth: np.ndarray) -> tuple:
    """One setting, run to its end: a row of :data:`OUTCOME`."""
    began = time.perf_counter()
    graph, r = graph_of(c["graph"], c["nodes"]), c["rank"]
    w = graph.weights(c.get("weights", "local_degree"))
    below: dict[float, int | None] = {1e-2: None, 1e-4: None, 1e-8: None}
    inner, error = 0, np.array([1.0])
    for inner, q in _steps(m, c, w):
        error = angle_error(q, truth[:, :r])
        for level in below:
            if below[level] is None and error.mean() < level:
                below[level] = inner
    alone = c["method"].startswith("central")
    return (
        workload, c.get("setting", c["graph"]), c["method"], c.get("rule", "-"), c["nodes"], r, float(c.get("delta", values[r] / values[r - 1])), c["outer"],
        0.0 if alone else round(graph.mean_degree() * inner / 1000, 6), inner, float(error.mean()), float(error.max()), below[1e-2], below[1e-4], below[1e-8], second_modulus(w), time.perf_counter() - began,
    )


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=[x.split()[0] for x in OUTCOME.split(", ")]).astype({"below_1e2": "Int64", "below_1e4": "Int64", "below_1e8": "Int64"})


def _shares(data: dict, grid: list[dict], tasks: int, executors: int) -> list[tuple[nodes.StoredNodes, list[dict]]]:
    """Settings of equal moments that one task runs, so that the moments are read by few tasks and these are of about
    equal work; what takes longest first. Moments that tasks of one executor hold stay within :data:`TASK_BYTES`."""
    work = lambda c: data[c["data"]].n * c["outer"] * c["rank"]
    total, out = sum(map(work, grid)), []
    for k in dict.fromkeys(c["data"] for c in grid):
        own = sorted((c for c in grid if c["data"] == k), key=work, reverse=True)
        many = min(len(own), -(-tasks * sum(map(work, own)) // total), executors * max(1, TASK_BYTES // data[k].table.compact))
        out += [(data[k], own[i::many]) for i in range(many)]
    return sorted(out, key=lambda x: -sum(map(work, x[1])))


def _reading(workload: str, m: nodes.StoredNodes, own: list[dict]) -> DataFrame:
    """Outcomes of settings by one task that reads their moments."""
    bare, known = m.bare(), m.leading(max(c["rank"] for c in own))
    kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    schema = pa.schema([(name, kinds[kind]) for name, kind in map(str.split, OUTCOME.split(", "))])

    def run(batches):
        here = nodes.CompactNodes.from_batches(bare, batches)
        nodes.given_back()
        for c in own:
            yield pa.RecordBatch.from_pandas(_frame([_outcome(workload, c, here, *known)]), schema, preserve_index=False)

    return m.table.df.coalesce(1).mapInArrow(run, OUTCOME)


def run_grid(spark: SparkSession, workload: str, data: dict, grid: list[dict]) -> DataFrame:
    """Outcomes of the settings. ``data``: node moments (or stacked matrices) by the name that a setting's ``data``
    gives. Moments in memory go to the tasks, stored ones are read by them; of moments that stay distributed, four
    settings run at a time."""
    data = {k: nodes.as_nodes(m) for k, m in data.items()}
    most = max(c["rank"] for c in grid)
    truths = {k: m.leading(min(most, m.d)) for k, m in data.items() if not all("delta" in c for c in grid if c["data"] == k)}
    far = [c for c in grid if isinstance(data[c["data"]], nodes.SpreadNodes)]
    kept = [c for c in grid if isinstance(data[c["data"]], nodes.StoredNodes)]
    near = [c for c in grid if not isinstance(data[c["data"]], (nodes.SpreadNodes, nodes.StoredNodes))]
    rows = []
    if far:
        with ThreadPoolExecutor(4) as pool:
            rows += pool.map(lambda c: _outcome(workload, c, data[c["data"]], *truths[c["data"]]), far)
    if kept:
        with session_conf(spark, SMALL_BATCHES | APART):
            shares = _shares(data, kept, 2 * spark.sparkContext.defaultParallelism, executors(spark))
            rows += functools.reduce(DataFrame.union, [_reading(workload, *x) for x in shares]).collect()
    out = spark.createDataFrame(rows, OUTCOME) if rows else None
    if near:
        shared = spark.sparkContext.broadcast(({k: data[k] for k in {c["data"] for c in near}}, truths))

        def run(frames):
            for frame in frames:
                known, truths = shared.value
                rows = []
                for k in frame.k:
                    c = near[int(k)]
                    m = known[c["data"]]
                    if "delta" in c:
                        m = nodes.as_nodes(coloured(m.matrices, c["rank"], c["delta"], c.get("tied", False)))
                        rows.append(_outcome(workload, c, m, *m.leading(c["rank"])))
                    else:
                        rows.append(_outcome(workload, c, m, *truths[c["data"]]))
                yield _frame(rows)

        tasks = spark.range(len(near), numPartitions=min(len(near), 4096)).select(F.col("id").cast("int").alias("k"))
        own = tasks.mapInPandas(run, OUTCOME)
        out = own if out is None else out.union(own)
    return out


def _embedding_nodes(spark: SparkSession, sf_dir: str, n: int, d: int) -> np.ndarray:
    return whitened(node_matrices(partition.by_hash(features.embeddings(spark, sf_dir, d), n), n, d))


# ---------------------------------------------------------------- what was reported, as a test of each row

Claim = Callable[[pd.DataFrame, pd.Series], bool | None]


def _other(all_: pd.DataFrame, row: pd.Series, **changed) -> pd.Series:
    """The setting that differs from a row's as given."""
    want = {c: row[c] for c in ("setting", "method", "rule", "nodes", "rank", "delta")} | changed
    at = np.logical_and.reduce([all_[c] == v for c, v in want.items()])
    return all_[at].iloc[0]


def _later(a, b) -> bool:
    """Whether a level is reached later (or never) than by another that reaches it."""
    return pd.isna(a) or (not pd.isna(b) and a > b)


def same_floor(all_: pd.DataFrame, row: pd.Series) -> bool:
    """Ramped rounds reach what the fixed ones reach, with fewer messages."""
    fixed = _other(all_, row, rule="50")
    return bool(row.error <= 3 * fixed.error + 1e-5 and (row.rule == "50" or row.inner_total < fixed.inner_total))


def compared(all_: pd.DataFrame, row: pd.Series) -> bool | None:
    """Sequential methods fall only at the last vector; Hebbian and gradient rules stay in a neighbourhood; the
    central iteration has the lowest floor; tracking needs fewer messages."""
    ours, central = (_other(all_, row, method=m, rule=k) for m, k in (("row", "50"), ("central", "-")))
    if row.method == "row":
        return same_floor(all_, row)
    if row.method in ("hebbian", "projected_gradient"):
        return bool(1e-9 < row.error and 10 * ours.error < row.error)
    if row.method in ("sequential", "central_sequential"):
        return _later(row.below_1e2, (ours if row.method == "sequential" else central).below_1e2)
    if row.method == "central":
        return bool(row.error <= ours.error + 1e-9)
    return bool(_later(ours.below_1e2, row.below_1e2))


def natural(all_: pd.DataFrame, row: pd.Series) -> bool | None:
    """As on synthetic data, but for tracking: on hashed documents its steps stall at some ranks, so nothing is
    claimed of it."""
    if row.setting != "compared":
        return same_floor(all_, row)
    return None if row.method == "tracking" else compared(all_, row)


def sparser_is_worse(all_: pd.DataFrame, row: pd.Series) -> bool:
    """Sparser graphs end higher; a longer cap repairs that."""
    if row.rule == "5t+1,200":
        return bool(row.error < _other(all_, row, rule="50").error / 10)
    denser = {"er:0.5": "er:0.5", "er:0.25": "er:0.5", "er:0.1": "er:0.25"}[row.setting]
    return bool(row.error >= 0.5 * _other(all_, row, setting=denser).error and row.error <= 2 * _other(all_, row, setting="er:0.1").error)


def ring_is_poor(all_: pd.DataFrame, row: pd.Series) -> bool:
    """The periodic ring stays poor under local-degree weights; weights that break the period repair it."""
    poor = _other(all_, row, setting="ring/local_degree")
    return bool(row.error > 1e-2) if row.setting == "ring/local_degree" else bool(10 * row.error < poor.error)


def longer_caps(all_: pd.DataFrame, row: pd.Series) -> bool:
    best = _other(all_, row, rule="100").error
    return bool(row.error > 10 * best) if row.rule in ("50", "2t+1") else bool(row.error <= 1.5 * best + 1e-12)


def columns_beat_sequential(all_: pd.DataFrame, row: pd.Series) -> bool:
    first, central = _other(all_, row, method="column"), _other(all_, row, method="central")
    if row.method in ("column", "central"):
        return not pd.isna(row.below_1e2)
    return _later(row.below_1e2, (first if row.method == "column_sequential" else central).below_1e2)


def converged(all_: pd.DataFrame, row: pd.Series) -> bool:
    return bool(row.error < 1e-2)


# ---------------------------------------------------------------- the workloads


@dataclasses.dataclass(frozen=True)
class Workload:
    """``data`` builds node moments by name, ``grid`` lists the settings, ``claim`` says what each must show."""

    name: str
    data: Callable[[SparkSession, str], dict]
    grid: list[dict]
    claim: Claim

    def outcomes(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """All measured figures of every setting."""
        return run_grid(spark, self.name, self.data(spark, sf_dir), self.grid)

    def checked(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """Every setting with its exact counts, and whether it shows what was reported: a row per setting of the grid."""
        found = self.outcomes(spark, sf_dir).toPandas()
        shown = [self.claim(found, r) for _, r in found.iterrows()]
        rows = [
            (r.setting, r.method, r.rule, int(r.nodes), int(r["rank"]), int(r.outer), int(r.inner_total), float(r.p2p_k), None if ok is None else bool(ok)) for ok, (_, r) in zip(shown, found.iterrows(), strict=True)
        ]
        return spark.createDataFrame(rows, "setting string, method string, rule string, nodes int, rank int, outer_steps int, inner_total long, p2p_k double, holds boolean")


def _white(n: int, d: int = 20):
    return lambda spark, sf_dir: {"x": _embedding_nodes(spark, sf_dir, n, d)}


def _synthetic(name: str, claim: Claim, grid: list[dict], n: int = 20, d: int = 20) -> Workload:
    return Workload(name, _white(n, d), [{"setting": g["graph"], "rule": "-"} | g | {"data": "x", "nodes": n} for g in grid], claim)


def _row(graph: str, rule: str, **more) -> dict:
    return dict(method="row", graph=graph, rank=5, delta=0.7, outer=200, rule=rule) | more


def _baseline_grid(tied: bool, outer: int = 200) -> list[dict]:
    grid = []
    for r in (4, 8):
        for delta in (0.4, 0.85):
            b = dict(graph="er:0.5", rank=r, delta=delta, tied=tied, outer=outer)
            grid += [b | dict(method="row", rule=k) for k in ("50", "t+1")] + [b | dict(method=m) for m in ("central", "central_sequential", "sequential", "tracking")]
            grid += [b | dict(method=m, outer=1500, step=0.1) for m in ("hebbian", "projected_gradient")]
    return grid


#: Methods that the published comparisons on natural data run on ten nodes, beside the row split.
COMPARED = ("central", "central_sequential", "sequential", "hebbian", "projected_gradient", "tracking")


def _natural(name: str, view: Callable[[SparkSession, str], DataFrame], d: int, cells: list[tuple[int, float, int, int]], comparisons: list[tuple[int, int]] = (), rules: tuple[str, ...] = ("t+1", "2t+1", "50")) -> Workload:
    """Natural data at the published sizes: ``cells`` are (nodes, edge probability, rank, outer steps), run under
    every rule; ``comparisons`` are (rank, outer steps) on ten nodes, run by every method. Moments are scaled by their
    largest eigenvalue, which step sizes are made for."""
    grid = []
    for n, p, r, outer in cells:
        grid += [{"data": str(n), "setting": f"er:{p}", "graph": f"er:{p}", "nodes": n, "rank": r, "outer": outer, "method": "row", "rule": k} for k in rules]
    for r, outer in comparisons:
        base = {"data": "10", "setting": "compared", "graph": "er:0.5", "nodes": 10, "rank": r, "outer": outer, "rule": "-", "mix": 10}
        grid += [base | {"method": "row", "rule": k} for k in ("50", "t+1")] + [base | {"method": x} for x in COMPARED]

    def data(spark: SparkSession, sf_dir: str) -> dict:
        ns, most = sorted({c["nodes"] for c in grid}), max(c["rank"] for c in grid)
        return {str(n): m for n, m in gathered(view(spark, sf_dir), ns, d, min(most, d)).items()}

    return Workload(name, data, grid, natural)


def _documents(d: int):
    return lambda spark, sf_dir: features.documents_hashed(spark, sf_dir, d)


def _scaling_data(spark: SparkSession, sf_dir: str) -> dict:
    return {f"{n}/{d}": _embedding_nodes(spark, sf_dir, n, d) for d in (10, 20, 64) for n in (10, 20, 100)}


_NETS = {10: "er:0.5", 20: "er:0.25", 100: "er:0.05", 200: "er:0.03"}
GRIDS = {
    w.name: w
    for w in (
        _synthetic("w1_round_rules", same_floor, [_row("er:0.25", k, delta=g, setting=f"gap {g}") for g in (0.3, 0.7, 0.9) for k in ("half_floor", "t+1", "2t+1", "50")]),
        _synthetic("w2_connectivity", sparser_is_worse, [_row(f"er:{p}", k) for p in (0.5, 0.25, 0.1) for k in ("2t+1", "50")] + [_row("er:0.1", "5t+1,200")]),
        _synthetic("w3_ring", ring_is_poor, [_row("ring", k, weights=w, setting=f"ring/{w}") for w in ("local_degree", "metropolis", "lazy") for k in ("2t+1", "50", "5t+1,200")]),
        _synthetic("w4_star", longer_caps, [_row("star", k) for k in ("2t+1", "50", "2t+1,100", "5t+1,100", "100")]),
        _synthetic("w6_baselines", compared, _baseline_grid(False), 10),
        _synthetic("w7_tied", compared, _baseline_grid(True), 10),
        _synthetic(
            "w8_columns", columns_beat_sequential,
            [dict(graph="er:0.5", rank=r, delta=g, outer=200, method=m) for r in (4, 8) for g in (0.4, 0.85) for m in ("column", "central", "central_sequential", "column_sequential")], 10, 10,
        ),
        _natural("w9_digits", _documents(784), 784, [(20, 0.25, 5, 400), (20, 0.25, 10, 400), (100, 0.05, 5, 200)], [(10, 400), (20, 400)]),
        _natural("w9_embeddings", features.embeddings, 64, [(20, 0.25, 3, 400), (20, 0.25, 6, 400), (100, 0.05, 3, 200)], [(3, 400), (6, 400)]),
        _natural("w10_documents", _documents(1024), 1024, [(20, 0.25, 5, 400), (20, 0.25, 7, 400), (100, 0.05, 7, 400)], [(10, 400), (15, 400)]),
        _natural("w11_wide_documents", _documents(2914), 2914, [(20, 0.25, 7, 200), (20, 0.5, 7, 200)]),
        _natural("w12_networks", _documents(1024), 1024, [(n, float(g[3:]), 5, 200) for n, g in _NETS.items()]),
        _natural("w12_orders", lambda spark, sf_dir: features.standardized(features.line_aggregates(spark, sf_dir, "l_orderkey")), 8, [(n, float(g[3:]), r, 200) for n, g in _NETS.items() for r in (1, 4, 5)]),
        Workload(
            "w13_scaling", _scaling_data,
            [dict(method="row", data=f"{n}/{d}", setting=f"d={d}", graph=_NETS[n], nodes=n, rank=5, delta=0.7, outer=100, rule="2t+1") for d in (10, 20, 64) for n in (10, 20, 100)], converged,
        ),
    )
}


def stragglers_measured(n: int, p: float, rule: str, outer: int, delay: float, matrices: np.ndarray, r: int = 5, seed: int = 1) -> tuple[int, float]:
    """(rounds, seconds) of a run whose nodes are threads that meet after every averaging round; in each round one
    node, drawn anew, sleeps before it sends."""
    w, plan, q0 = erdos_renyi(n, p).weights(), rounds(RULES[rule], outer), random_basis(matrices.shape[1], r, 7)
    draw, total = np.random.default_rng(seed), sum(plan)
    late = draw.integers(0, n, total)
    near = [np.flatnonzero(w[:, i]) for i in range(n)]
    sent: list[dict[int, tuple]] = [{}, {}]
    meet = threading.Barrier(n)

    def node(i: int) -> np.ndarray:
        q, k = q0, 0
        for steps in plan:
            z, anchor = matrices[i] @ q, float(i == 0)
            for _ in range(steps):
                if delay and late[k] == i:
                    time.sleep(delay)
                sent[k % 2][i] = (z, anchor)
                meet.wait()
                got = sent[k % 2]
                z, anchor = sum(w[j, i] * got[j][0] for j in near[i]), sum(w[j, i] * got[j][1] for j in near[i])
                k += 1
            q = positive_qr(z / anchor if anchor > 1e-12 else z * n)[0]
        return q

    began = time.perf_counter()
    with ThreadPoolExecutor(n) as pool:
        list(pool.map(node, range(n)))
    return total, time.perf_counter() - began


def w5_stragglers(spark: SparkSession, sf_dir: str, outer: int = 5) -> DataFrame:
    """Modelled time of 200 outer steps with one late node per round; and a real run of a few steps with and
    without the delays: whether it waits at least once per round, and the run without delays does not."""
    from meshspan.operators.cost import straggler_makespan, straggler_table

    out = None
    for n, p in ((10, 0.5), (20, 0.25)):
        m = _embedding_nodes(spark, sf_dir, n, 20)
        for rule in ("2t+1", "50"):
            plan = rounds(RULES[rule], 200)
            total, slow = stragglers_measured(n, p, rule, outer, 0.01, m)
            _, quick = stragglers_measured(n, p, rule, outer, 0.0, m)
            own = straggler_makespan(straggler_table(spark, plan, n)).select(
                F.lit(n).alias("nodes"), F.lit(p).alias("p"), F.lit(rule).alias("rule"), F.lit(sum(plan)).cast("long").alias("rounds_total"), F.round("makespan_s", 4).alias("makespan_s"),
                F.lit(total).cast("long").alias("rounds_run"), F.lit(slow >= 0.01 * total and slow > quick).alias("holds"),
            )
            out = own if out is None else out.union(own)
    return out


def w14_downstream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest-centroid accuracy on the labels of the embeddings, before and after encoding."""
    from meshspan.operators import encode
    from meshspan.operators.subspace import exact_subspace

    samples = features.embeddings(spark, sf_dir).where("label is not null")
    out = encode.nearest_centroid_accuracy(samples, "label", "features").withColumn("rank", F.lit(64))
    mean = moments.global_moments(samples).mean
    for r in (3, 6, 16, 32):
        q = exact_subspace(samples, r)[1]
        out = out.union(encode.nearest_centroid_accuracy(encode.encode(samples, q, mean), "label", "code").withColumn("rank", F.lit(r)))
    return out.select("rank", "accuracy", "n")


def w15_monte_carlo(spark: SparkSession, sf_dir: str, trials: int = 20, n: int = 20, per_node: int = 500, d: int = 20) -> DataFrame:
    """Normal samples drawn anew for every trial (500 rows a node): mean and deviation of the error over trials.
    All trials' moments come from one scan; a trial's truth is that of its own sample."""
    values = features.spectrum(d, 5, 0.7)
    drawn = features.gaussian(spark, trials * n, per_node, values, seed=11)
    m = node_matrices(drawn, trials * n, d, "none").reshape(trials, n, d, d)
    grid = [dict(method="row", data=str(k), setting=f"trial {k}", graph="er:0.25", nodes=n, rank=5, outer=200, rule=rule) for k in range(trials) for rule in ("t+1", "2t+1", "50")]
    runs = run_grid(spark, "w15", {str(k): m[k] for k in range(trials)}, grid)
    return runs.groupBy("rule").agg(F.avg("error").alias("mean"), F.stddev_samp("error").alias("sd"), F.avg("below_1e8").alias("below_1e8"), F.first("p2p_k").alias("p2p_k"), F.count("*").alias("trials"))


WORKLOADS = {name: w.checked for name, w in GRIDS.items()} | {f.__name__: f for f in (w5_stragglers, w14_downstream, w15_monte_carlo)}
