"""Subspace methods over DataFrames.

After one scan that turns samples into pieces of node moments (:mod:`meshspan.operators.nodes`), a method runs
in one of these modes; all of them give the same bases, traces, stops and costs:

* *resident*: one executor task holds all pieces and runs every step; right while they fit its budget.
* *fused*: the pieces stay distributed and are laid out once. A step is one job without a shuffle: the node
  bases go out as a broadcast, products of N*d*r numbers come back, and the driver applies the power of the mixing
  matrix and the QR. N*d*r, which does not grow with the rows, is checked.
* *spread*: bases beyond that check live in tables too: a join on the node with pieces that are bucketed by node,
  a shuffle by blocks of features for the averaging, one by node for the QR.
* *literal*: the same with every averaging round as a join; it exists to prove the others.

Column split has *cross* (moments of all rows, as resident or fused), *streamed* (products straight from the samples,
one scan per step, averaged inside each row) and *literal* (scores of every sample and node, averaged by joins).
Its basis is d x r in all, and stays with the driver.
"""

from __future__ import annotations

import dataclasses
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.functions.linalg import Powers, anchor_scale, angle_error, leading, positive_qr, random_basis
from meshspan.functions.vectors import vec_dot
from meshspan.operators import consensus, loops, moments
from meshspan.operators.nodes import PieceTable, SampleNodes, SpreadNodes, dimension, node_pieces
from meshspan.operators.topology import Topology
from meshspan.plans.schedules import Fixed, Schedule, rounds
from meshspan.plans.stopping import Step, Stop
from meshspan.sources.tables import released, stored, stored_by

RESIDENT_BYTES = 256 << 20
BASIS_BYTES = 128 << 20  # of all nodes' bases, broadcast and gathered in a step
BASIS = "node int, i int, q array<double>"
TRACE = "method string, t int, inner_total long, node int, error double, objective double, disagreement double"
_BOTH = "kind string, method string, t int, inner_total long, node int, i int, q array<double>, error double, objective double, disagreement double"
_BOTH_ARROW = pa.schema([
    ("kind", pa.string()), ("method", pa.string()), ("t", pa.int32()), ("inner_total", pa.int64()), ("node", pa.int32()), ("i", pa.int32()), ("q", pa.list_(pa.float64())),
    ("error", pa.float64()), ("objective", pa.float64()), ("disagreement", pa.float64()),
])


@dataclasses.dataclass
class SubspaceResult:
    """``basis``: (node, i, q); ``trace``: one row per step and node; ``cost``: messages per node of the steps
    that ran, if the method sends any; ``meta`` has the number of steps and rounds that ran."""

    basis: DataFrame
    trace: DataFrame
    cost: DataFrame | None
    meta: dict

    def as_matrix(self, node: int = 0) -> np.ndarray:
        rows = self.basis.where(F.col("node") == node).orderBy("i").toPandas()
        return np.stack(rows.q.to_list())

    def as_components(self, covariance: np.ndarray, node: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Eigenvalues and eigenvectors inside the subspace, by the small rotation that makes the projected
        covariance diagonal."""
        q = self.as_matrix(node)
        values, turn = leading(q.T @ covariance @ q, q.shape[1])
        return values, q @ turn


Truth = np.ndarray | str | None


class HeldBases:
    """Node bases in a stored table (node, q: d x r numbers), read by groups of nodes that fit the budget."""

    def __init__(self, df: DataFrame, n: int, d: int, r: int):
        self.df, self.n, self.d, self.r = df, n, d, r

    def groups(self) -> Iterator[np.ndarray]:
        per = max(1, BASIS_BYTES // (8 * self.d * self.r))
        for low in range(0, self.n, per):
            rows = self.df.where(F.col("node").between(low, low + per - 1)).toArrow().sort_by("node")
            yield np.frombuffer(b"".join(rows["q"].to_pylist())).reshape(-1, self.d, self.r)

    def table(self) -> DataFrame:
        d, r = self.d, self.r

        def rows(batches):
            for batch in batches:
                for node, q in zip(batch.column("node").to_pylist(), batch.column("q").to_pylist(), strict=True):
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (d + 1) * r, r), pa.int32()), pa.array(np.frombuffer(q)))
                    yield pa.RecordBatch.from_arrays([pa.array([node] * d, pa.int32()), pa.array(range(d), pa.int32()), lists], ["node", "i", "q"])

        return self.df.mapInArrow(rows, BASIS)


def _groups(q) -> Iterator[np.ndarray]:
    if isinstance(q, HeldBases):
        yield from q.groups()
    else:
        yield q


def _figures(q, m, truth: np.ndarray | None, objective: bool) -> tuple[np.ndarray, np.ndarray, float, np.ndarray]:
    """Errors, lost variances and largest distance from the mean basis, and the first node's basis."""
    error, kept, total, n, first = [], [], 0.0, 0, None
    for own in _groups(q):
        first = own[0] if first is None else first
        error.append(angle_error(own, truth) if truth is not None else np.full(len(own), np.nan))
        kept.append(m.kept(own) if objective else np.full(len(own), np.nan))
        total, n = total + own.sum(0), n + len(own)
    off = max(float(np.sqrt(((own - total / n) ** 2).sum((1, 2))).max()) for own in _groups(q))
    return np.concatenate(error), m.trace - np.concatenate(kept), off, first


def _walked(steps: Iterator, m, truth: Truth, r: int, method: str, stop: Stop | None, every: int, degree: float) -> tuple[list[tuple], int, int, object]:
    """Run a loop to its end or stop: rows of the trace (every ``every`` steps and the last), the step and rounds
    it ended at, and the bases it ended with."""
    if isinstance(truth, str):
        truth = m.leading(r)[1]
    rows, before, t, inner, q, done = [], None, -1, 0, None, -1

    def look(objective: bool) -> tuple:
        return _figures(q, m, truth, objective)

    def note(found: tuple) -> None:
        error, lost, off, _ = found
        rows.extend((method, t, inner, k, float(error[k]), float(lost[k]), off) for k in range(len(error)))

    for t, (inner, q) in enumerate(steps):
        due = t % every == 0
        if due or stop is not None:
            found = look(due)
            if due:
                note(found)
                done = t
        if stop is not None:
            error, _, off, first = found
            change = float(angle_error(before, first)) if before is not None else np.inf
            mq = m.mean_apply(first)
            before = first
            if stop(Step(t, inner, change, float(np.linalg.norm(mq - first @ (first.T @ mq))), off, float(np.nanmax(error)) if truth is not None else np.inf, degree * inner)):
                break
    if t != done and q is not None:
        note(look(True))
    return rows, t, inner, q


def _basis_table(q: np.ndarray) -> pa.Table:
    n, d, r = q.shape
    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (n * d + 1) * r, r), pa.int32()), pa.array(np.ascontiguousarray(q).ravel()))
    return pa.table({"node": pa.array(np.repeat(np.arange(n), d), pa.int32()), "i": pa.array(np.tile(np.arange(d), n), pa.int32()), "q": lists})


def _resident(table: PieceTable, make: Callable, r: int, method: str, truth: Truth, stop: Stop | None, every: int, degree: float) -> tuple[DataFrame, DataFrame, int, int]:
    """All steps in one executor task."""
    df, bare = table.df, dataclasses.replace(table, df=None)

    def run(batches):
        from meshspan.operators.nodes import LocalNodes

        m = LocalNodes.from_batches(bare, batches)
        rows, t, inner, q = _walked(make(m), m, truth, r, method, stop, every, degree)
        if rows:
            columns = list(zip(*rows, strict=True))
            k = len(rows)
            yield pa.RecordBatch.from_arrays(
                [pa.array(["trace"] * k), pa.array(columns[0]), pa.array(columns[1], pa.int32()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.int32()), pa.nulls(k, pa.int32()), pa.nulls(k, pa.list_(pa.float64()))]
                + [pa.array(c, pa.float64()) for c in columns[4:]], schema=_BOTH_ARROW,
            )
        if q is not None:
            own = _basis_table(np.asarray(q)).combine_chunks()
            k = own.num_rows
            yield pa.RecordBatch.from_arrays(
                [pa.array(["basis"] * k), pa.array([method] * k), pa.array([t] * k, pa.int32()), pa.array([inner] * k, pa.int64()), *[own[c].combine_chunks() for c in ("node", "i", "q")], *[pa.nulls(k, pa.float64())] * 3],
                schema=_BOTH_ARROW,
            )

    both = stored(df.coalesce(1).mapInArrow(run, _BOTH), "result")
    basis = both.where("kind = 'basis'").select("node", "i", "q")
    trace = both.where("kind = 'trace'").select("method", "t", "inner_total", "node", "error", "objective", "disagreement")
    last = both.where("kind = 'basis'").select("t", "inner_total").limit(1).collect()
    return basis, trace, (last[0]["t"] if last else -1), (last[0]["inner_total"] if last else 0)


def _driven(spark, m, steps: Iterator, r: int, method: str, truth: Truth, stop: Stop | None, every: int, degree: float) -> tuple[DataFrame, DataFrame, int, int]:
    """Steps driven from here: products are jobs."""
    rows, t, inner, q = _walked(steps, m, truth, r, method, stop, every, degree)
    trace = spark.createDataFrame(rows, TRACE)
    if isinstance(q, HeldBases):
        return q.table(), trace, t, inner
    return stored(spark.createDataFrame(_basis_table(np.asarray(q))), "basis"), trace, t, inner


def _ran(out: tuple[DataFrame, DataFrame, int, int], topology: Topology | None, meta: dict) -> SubspaceResult:
    from meshspan.operators.cost import p2p_cost

    basis, trace, t, inner = out
    cost = p2p_cost(basis.sparkSession, topology, [inner]) if topology is not None else None
    return SubspaceResult(basis, trace, cost, meta | {"steps": t + 1, "rounds": inner})


def _start(init, d: int, r: int) -> np.ndarray:
    if isinstance(init, int):
        return random_basis(d, r, init)
    if isinstance(init, str) and init == "axes":
        return np.eye(d)[:, :r]
    q, _ = positive_qr(np.asarray(init, float))
    if q.shape != (d, r):
        raise ValueError(f"the start must be {d} x {r}")
    return q


def _placed(table: PieceTable, mode: str, r: int) -> str:
    """The mode that the sizes ask for, and a check of the one that is asked for."""
    n, d = table.n, table.d
    dense = bool((table.rows > d).any())
    fits = (n * d * d * 8 if dense else table.bytes) <= RESIDENT_BYTES
    bases = n * d * r * 8 <= BASIS_BYTES
    if mode == "auto":
        return "resident" if fits and bases else "fused" if bases else "spread"
    if mode == "resident" and not fits:
        raise ValueError("node moments exceed a task's budget: use mode='fused'")
    if mode == "fused" and not bases:
        raise ValueError("the nodes' bases exceed the budget: use mode='spread'")
    if mode not in ("resident", "fused", "spread", "literal"):
        raise ValueError(f"unknown mode {mode!r}")
    return mode


def run_method(table: PieceTable, make: Callable, r: int, method: str, mode: str = "auto", truth: Truth = None, stop: Stop | None = None, every: int = 1, degree: float = 0.0) -> tuple[DataFrame, DataFrame, int, int]:
    """Any loop of :mod:`meshspan.operators.loops` on a piece table, resident or fused: (basis, trace, last step,
    rounds)."""
    mode = _placed(table, mode, r)
    if mode == "resident":
        return _resident(table, make, r, method, truth, stop, every, degree)
    if mode != "fused":
        raise ValueError(f"{method} runs resident or fused")
    m = SpreadNodes(table)
    out = _driven(table.df.sparkSession, m, make(m), r, method, truth, stop, every, degree)
    released(m.df)
    return out


# ---------------------------------------------------------------- row split


def rowsplit_subspace(
    samples: DataFrame, topology: Topology, r: int, schedule: Schedule = Fixed(50), outer: int = 200, init: int | str | np.ndarray = 7, mode: str = "auto",
    weights: str = "local_degree", stop: Stop | None = None, rescale: str = "safe", truth: Truth = None, every: int = 1, center: str = "exact", local_scale: str = "sum",
) -> SubspaceResult:
    """Leading subspace from ``samples(node, features)`` split by rows over a network.

    ``init``: a seed, ``"axes"``, or a matrix (a warm start); all nodes share it. ``truth``: a basis, or
    ``"exact"``, to trace errors. ``mode``: auto, resident, fused, spread or literal (rounds as joins): the same
    result by different plans. ``center``: exact, consensus (the mean by averaging rounds of the first
    step's number) or none.
    """
    d = dimension(samples)
    q0, w = _start(init, d, r), topology.weights(weights)
    plan = rounds(schedule, outer)
    if center == "consensus":
        samples, center = consensus_centred(samples, topology, w, max(plan, default=0), rescale, d), "none"
    table = node_pieces(samples, topology.n, d, center=center, local_scale=local_scale)
    mode, method = _placed(table, mode, r), f"row[{schedule.name}]"
    meta = {"method": method, "mode": mode, "topology": topology.kind, "d": d, "r": r}
    degree = topology.mean_degree()
    if mode in ("resident", "fused"):
        return _ran(run_method(table, lambda m: loops.row_split(m, w, plan, q0, rescale), r, method, mode, truth, stop, every, degree), topology, meta)
    m = SpreadNodes(table)
    return _ran(_driven(samples.sparkSession, m, _spread_steps(table, w, plan, q0, rescale, mode == "literal"), r, method, truth, stop, every, degree), topology, meta)


def consensus_centred(samples: DataFrame, topology: Topology, w: np.ndarray, mixing_rounds: int, rescale: str, d: int) -> DataFrame:
    """Every node's samples about its own estimate of the mean of all rows: counts and sums are averaged by the
    network, and their ratio is what a node subtracts. Counts and sums are N x (d + 1) numbers."""

    def partial(batches):
        from meshspan.operators.nodes import vectors_of

        held: dict[int, np.ndarray] = {}
        for batch in batches:
            if batch.num_rows:
                x, node = vectors_of(batch.column("features"), d), np.asarray(batch.column("node"))
                for k in np.unique(node):
                    own = x[node == k]
                    held[int(k)] = held.get(int(k), np.zeros(d + 1)) + np.concatenate((own.sum(0), [len(own)]))
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array(range(len(held)), pa.int32()), pa.array(list(held.values()), pa.list_(pa.float64()))], ["node", "i", "z"])

    parts = samples.select(F.col("node").cast("int").alias("node"), F.col("features").cast("array<double>").alias("features")).mapInArrow(partial, consensus.VALUES)
    wide = parts.select("node", F.posexplode("z").alias("k", "v")).groupBy("node", "k").agg(F.sum("v").alias("v"))
    sums = wide.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "v"))), lambda s: s["v"]).alias("z")).select("node", F.lit(0).alias("i"), "z")
    agreed = stored(consensus.consensus_sum(sums, w, mixing_rounds, rescale), "means")
    mean = agreed.select(F.col("node").alias("_at"), F.transform(F.slice("z", 1, d), lambda v: v / F.element_at("z", d + 1)).alias("_mean"))
    return samples.join(F.broadcast(mean), F.col("node") == F.col("_at")).withColumn("features", F.zip_with(F.col("features").cast("array<double>"), "_mean", lambda a, b: a - b)).drop("_at", "_mean")


def centred(scatter: DataFrame) -> DataFrame:
    """Each node's moments about the mean of all rows, still distributed by (node, i)."""
    whole = scatter.groupBy("i").agg(F.sum("total").alias("s"), F.sum("n").alias("all"))
    mean = whole.agg(F.transform(F.array_sort(F.collect_list(F.struct("i", (F.col("s") / F.col("all")).alias("m")))), lambda x: x["m"]).alias("mean"))
    sums = scatter.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "total"))), lambda x: x["total"]).alias("sums"))
    joined = scatter.join(F.broadcast(sums), "node").crossJoin(F.broadcast(mean))  # one vector per node, one in all
    own = F.element_at("mean", F.col("i") + 1)
    row = F.zip_with(F.zip_with("row", "sums", lambda a, s: a - own * s), F.col("mean"), lambda a, m: a - m * (F.col("total") - F.col("n") * own))
    return joined.select("node", "i", "n", "total", row.alias("row"))


def spread_product(pieces: DataFrame, bases: DataFrame, table: PieceTable, r: int) -> DataFrame:
    """(node, i, z): every node's product with its basis, from ``pieces`` bucketed by node and bases (node, q)."""
    spark, d = pieces.sparkSession, table.d
    shared = spark.sparkContext.broadcast((table.mean, table.factors))

    def run(batches):
        held: dict[int, np.ndarray] = {}
        mean, factors = shared.value
        for batch in batches:
            for node, low, k, n, total, body, q in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "n", "total", "body", "q")), strict=True):
                own, block = np.frombuffer(q).reshape(d, r), np.frombuffer(body).reshape(k, d)
                z = held.setdefault(node, np.zeros((d, r)))
                if low < 0:
                    z += factors[node] * (block.T @ (block @ own))
                else:
                    z[low : low + k] += factors[node] * (block @ own)
                if total is not None:
                    sums, along = np.frombuffer(total), mean @ own
                    z -= factors[node] * (np.outer(sums, along) + np.outer(mean, sums @ own - n * along))
        for node, z in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([node] * d, pa.int32()), pa.array(range(d), pa.int32()), pa.array(list(z), pa.list_(pa.float64()))], ["node", "i", "z"])

    joined = bases.hint("merge").join(pieces, "node", "left")  # nodes without rows have a product of zero
    some = joined.where("body is not null").select("node", "low", "k", "n", "total", "body", "q").mapInArrow(run, consensus.VALUES)
    empty = [int(i) for i in np.flatnonzero(table.rows == 0)]
    if not empty:
        return some
    zero = spark.createDataFrame([(i,) for i in empty], "node int").withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(d - 1)))).withColumn("z", F.array_repeat(F.lit(0.0), r))
    return some.union(zero)


def _spread_steps(table: PieceTable, w: np.ndarray, plan: Sequence[int], q0: np.ndarray, rescale: str, literal: bool) -> Iterator[tuple[int, HeldBases]]:
    spark, (d, r), n = table.df.sparkSession, q0.shape, table.n
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(n, 4096))
    pieces, powers, inner = stored_by(table.df, "node", buckets), Powers(w), 0
    at = np.argwhere(w > 0)
    edges = spark.createDataFrame([(int(i), int(j), float(w[i, j])) for i, j in at], "src int, dst int, w double")
    first = spark.sparkContext.broadcast(q0.tobytes())

    def begun(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array([first.value] * batch.num_rows, pa.binary())], ["node", "q"])

    def orthonormal(key: tuple, group: pa.Table) -> pa.Table:
        group = group.sort_by("i")
        q, _ = positive_qr(np.asarray(group["z"].combine_chunks().flatten()).reshape(group.num_rows, -1))
        return pa.table({"node": key, "q": pa.array([q.tobytes()], pa.binary())})

    basis = stored(spark.range(n).select(F.col("id").cast("int").alias("node")).mapInArrow(begun, "node int, q binary"), "basis")
    for t, k in enumerate(plan):
        inner += k
        scale = anchor_scale(powers[k], rescale)
        z = spread_product(pieces, basis, table, r)
        if literal:
            factors = spark.createDataFrame([(i, float(s)) for i, s in enumerate(scale)], "node int, s double")
            z = consensus.run_rounds(z, edges, k).join(F.broadcast(factors), "node").select("node", "i", F.transform("z", lambda v: v * F.col("s")).alias("z"))
        else:
            z = consensus.run_fused(z, powers[k], scale)
        now = stored(z.groupBy("node").applyInArrow(orthonormal, "node int, q binary"), f"basis{t}")
        released(basis)
        basis = now
        yield inner, HeldBases(basis, n, d, r)


# ---------------------------------------------------------------- column split


def _whole(samples: DataFrame, d: int, center: str) -> PieceTable:
    """Moments of all rows as one node's."""
    return node_pieces(samples.select(F.lit(0).alias("node"), "features"), 1, d, center=center)


class LiteralColumns(SampleNodes):
    """Scores as rows (sample, node), averaged by as many joins with the weights as the plan's next step says,
    then multiplied back."""

    def __init__(self, samples: DataFrame, d: int, center: str, w: np.ndarray, plan: Sequence[int]):
        super().__init__(samples, d, center)
        self.w, self.plan = w, iter(plan)

    def column_product(self, blocks, power, q, rescale):
        spark, r, k = self.samples.sparkSession, q.shape[1], next(self.plan)
        mean = spark.createDataFrame([(self.mean.tolist(),)], "mean array<double>")
        samples = self.samples.crossJoin(F.broadcast(mean)).select("sample_id", F.zip_with("features", "mean", lambda a, b: a - b).alias("features"))
        rows = [(n, [int(i) for i in b], [q[b, j].tolist() for j in range(r)]) for n, b in enumerate(blocks)]
        parts = spark.createDataFrame(rows, "node int, columns array<int>, q array<array<double>>")
        at = np.argwhere(self.w > 0)
        edges = spark.createDataFrame([(int(i), int(j), float(self.w[i, j])) for i, j in at], "src int, dst int, w double")
        x = F.transform("columns", lambda c: F.element_at("features", c + 1))
        z = samples.crossJoin(F.broadcast(parts)).withColumn("x", x).select(F.col("node"), F.col("sample_id").alias("i"), F.transform("q", lambda column: vec_dot(column, F.col("x"))).alias("z"))
        mixed = consensus.run_rounds(z, edges, k)
        scale = spark.createDataFrame([(n, float(s)) for n, s in enumerate(anchor_scale(power, rescale))], "node int, s double")
        back = mixed.join(samples.withColumnRenamed("sample_id", "i"), "i").join(F.broadcast(parts.select("node", "columns")), "node").join(F.broadcast(scale), "node")
        flat = back.select(F.posexplode("columns").alias("p", "feature"), "features", "z", "s").select("feature", (F.element_at("features", F.col("feature") + 1) * F.col("s")).alias("x"), "z")
        sums = flat.groupBy("feature").agg(*[F.sum(F.col("x") * F.element_at("z", j + 1)).alias(f"v{j}") for j in range(r)]).orderBy("feature").toPandas()
        return sums[[f"v{j}" for j in range(r)]].to_numpy() / (self.rows * len(blocks))


def colsplit_subspace(
    samples: DataFrame, blocks: Sequence[np.ndarray], topology: Topology, r: int, schedule: Schedule = Fixed(50), outer: int = 200, init: int | str | np.ndarray = 7,
    mode: str = "auto", qr: str = "gram", push_rounds: int | None = 50, weights: str = "local_degree", rescale: str = "safe", truth: Truth = None, every: int = 1,
    stop: Stop | None = None, center: str = "exact",
) -> SubspaceResult:
    """Leading subspace from ``samples(sample_id, features)`` whose columns are split over a network.

    ``blocks``: the features of each node. The basis has one row per feature, with the node that holds it.
    ``qr``: gram or mgs; ``push_rounds``: averaging rounds of the distributed QR (None: the exact sum).
    ``mode``: auto, cross, streamed or literal; streamed and literal take a truth only as a basis.
    """
    if len(blocks) != topology.n:
        raise ValueError("one block of columns per node")
    d = dimension(samples)
    if not np.array_equal(np.sort(np.concatenate(blocks)), np.arange(d)):
        raise ValueError("the blocks must hold every feature once")
    q0, w, plan = _start(init, d, r), topology.weights(weights), rounds(schedule, outer)
    owner = np.empty(d, int)
    for k, b in enumerate(blocks):
        owner[b] = k
    if mode == "auto":
        mode = "cross" if d * d * 8 <= RESIDENT_BYTES else "streamed"
    method, degree, spark = f"column[{schedule.name}]", topology.mean_degree(), samples.sparkSession

    def make(c):
        return loops.column_split(c, blocks, w, plan, q0, qr, push_rounds, rescale)

    if mode == "cross":
        out = run_method(_whole(samples, d, center), make, r, method, "auto", truth, stop, every, degree)
    else:
        c = SampleNodes(samples, d, center) if mode == "streamed" else LiteralColumns(samples, d, center, w, plan)
        out = _driven(spark, c, make(c), r, method, truth, stop, every, degree)
        released(c.samples)
    nodes = spark.createDataFrame([(int(i), int(n)) for i, n in enumerate(owner)], "i int, holder int")
    basis = out[0].join(F.broadcast(nodes), "i").select(F.col("holder").alias("node"), "i", "q")
    return _ran((basis, *out[1:]), topology, {"method": method, "mode": mode, "topology": topology.kind, "d": d, "r": r})


# ---------------------------------------------------------------- what they are compared with

BASELINES = ("central", "central_sequential", "sequential", "hebbian", "projected_gradient", "tracking", "fast_tracking")


def baseline_loop(name: str, w: np.ndarray, plan: Sequence[int], outer: int, q0: np.ndarray, step: float = 0.1, rounds_per_step: int = 3) -> Callable:
    """The loop of one of :data:`BASELINES` as a function of node moments. Sequential methods share ``outer`` steps
    among the vectors."""
    per = max(1, outer // q0.shape[1])
    return {
        "central": lambda m: loops.central(m, outer, q0),
        "central_sequential": lambda m: loops.central_sequential(m, per, q0),
        "sequential": lambda m: loops.sequential(m, w, plan, per, q0),
        "hebbian": lambda m: loops.hebbian(m, w, outer, q0, step),
        "projected_gradient": lambda m: loops.projected_gradient(m, w, outer, q0, step),
        "tracking": lambda m: loops.tracking(m, w, outer, q0, rounds_per_step),
        "fast_tracking": lambda m: loops.tracking(m, w, outer, q0, rounds_per_step, fast=True),
    }[name]


def baseline(samples: DataFrame, name: str, r: int, topology: Topology | None = None, schedule: Schedule = Fixed(50), outer: int = 200, init: int | str | np.ndarray = 7, step: float = 0.1, rounds_per_step: int = 3, truth: Truth = None, every: int = 1, weights: str = "local_degree", stop: Stop | None = None, mode: str = "auto") -> SubspaceResult:
    """One of :data:`BASELINES` on row-split samples; step sizes are for a covariance whose largest eigenvalue is
    about one."""
    d, spark = dimension(samples), samples.sparkSession
    q0, alone = _start(init, d, r), name.startswith("central")
    w = topology.weights(weights) if topology else np.ones((1, 1))
    if alone or topology is None:
        samples = samples.select(F.lit(0).alias("node"), "features")
    table = node_pieces(samples, 1 if alone or topology is None else topology.n, d)
    make = baseline_loop(name, w, rounds(schedule, outer), outer, q0, step, rounds_per_step)
    out = run_method(table, make, r, name, mode, truth, stop, every, topology.mean_degree() if topology and not alone else 0.0)
    return _ran(out, None if alone else topology, {"method": name, "d": d, "r": r})


def colsplit_sequential(samples: DataFrame, blocks: Sequence[np.ndarray], topology: Topology, r: int, schedule: Schedule = Fixed(50), outer: int = 200, init: int | str | np.ndarray = 7, truth: Truth = None, every: int = 1, stop: Stop | None = None, push_rounds: int | None = 50) -> SubspaceResult:
    d = dimension(samples)
    q0, w, plan = _start(init, d, r), topology.weights(), rounds(schedule, outer)
    out = run_method(_whole(samples, d, "exact"), lambda c: loops.column_sequential(c, blocks, w, plan, max(1, outer // r), q0, push_rounds), r, "column_sequential", "auto", truth, stop, every, topology.mean_degree())
    return _ran(out, topology, {"method": "column_sequential", "d": d, "r": r})


def blocksplit_subspace(samples: DataFrame, blocks: Sequence[np.ndarray], rows: Topology, columns: Topology, r: int, schedule: Schedule = Fixed(50), outer: int = 100, init: int | str | np.ndarray = 7, truth: Truth = None, every: int = 1, mode: str = "auto", stop: Stop | None = None) -> SubspaceResult:
    """Rows split over one network (``samples.node``) and columns over another."""
    d = dimension(samples)
    q0, plan = _start(init, d, r), rounds(schedule, outer)
    wr, wc = rows.weights(), columns.weights()
    out = run_method(node_pieces(samples, rows.n, d), lambda m: loops.block_split(m, blocks, wr, wc, plan, q0), r, "block", mode, truth, stop, every, rows.mean_degree())
    return _ran(out, rows, {"method": "block", "d": d, "r": r})


def exact_subspace(samples: DataFrame, r: int) -> tuple[np.ndarray, np.ndarray]:
    """All eigenvalues of the covariance and the leading basis: the ground truth."""
    return leading(moments.global_moments(samples).covariance, r)


def local_subspaces(samples: DataFrame, r: int) -> DataFrame:
    """Every node's own answer from its rows alone: (node, i, q)."""

    def own(frame: pd.DataFrame) -> pd.DataFrame:
        _, m = moments.stacked(frame)
        q = leading(m[0], r)[1]
        return pd.DataFrame({"node": frame.node.iloc[0], "i": range(len(q)), "q": list(q)})

    return moments.local_scatter(samples).groupBy("node").applyInPandas(own, BASIS)


def one_shot_average(samples: DataFrame, r: int) -> np.ndarray:
    """Leading basis of the mean of the nodes' projectors: one round of talk."""
    local = local_subspaces(samples, r)
    other = local.select("node", F.col("i").alias("j"), F.col("q").alias("p"))
    dot = F.aggregate(F.zip_with("q", "p", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    rows = local.join(other, "node").groupBy("i", "j").agg(F.avg(dot).alias("v")).toPandas()
    d = int(rows.i.max()) + 1
    p = np.zeros((d, d))
    p[rows.i, rows.j] = rows.v
    return leading(p, r)[1]
