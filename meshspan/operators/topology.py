"""Graphs, mixing weights and what they say about convergence.

Edges are a table (src, dst) with src < dst. Random graphs are drawn by md5 of (seed, src, dst), so any
engine can draw them again. The node graph is small (N up to a few thousand): its matrices pass through
the driver behind a check of N; the tables stay DataFrames for joins, costs and SQL.
"""

from __future__ import annotations

import dataclasses
import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.functions.vectors import md5_fraction

MAX_NODES = 5000


def _connected(n: int, edges: list[tuple[int, int]]) -> bool:
    near: list[list[int]] = [[] for _ in range(n)]
    for a, b in edges:
        near[a].append(b)
        near[b].append(a)
    seen, todo = {0}, [0]
    while todo:
        for b in near[todo.pop()]:
            if b not in seen:
                seen.add(b)
                todo.append(b)
    return len(seen) == n


@dataclasses.dataclass(frozen=True)
class Topology:
    """A connected undirected graph over nodes 0..n-1."""

    n: int
    edges: tuple[tuple[int, int], ...]
    kind: str = "custom"

    def __post_init__(self):
        if not 1 <= self.n <= MAX_NODES:
            raise ValueError(f"1 to {MAX_NODES} nodes")
        clean = sorted({(min(e), max(e)) for e in self.edges if e[0] != e[1]})
        object.__setattr__(self, "edges", tuple(clean))
        if any(not 0 <= a < b < self.n for a, b in clean):
            raise ValueError("an edge leaves the graph")
        if not _connected(self.n, clean):
            raise ValueError("the graph is not connected")

    @property
    def degrees(self) -> np.ndarray:
        return np.bincount(np.array(self.edges, int).ravel(), minlength=self.n) if self.edges else np.zeros(self.n, int)

    def mean_degree(self) -> float:
        return 2 * len(self.edges) / self.n

    def diameter(self) -> int:
        reach, step = np.eye(self.n, dtype=bool), 0
        near = self.adjacency() | np.eye(self.n, dtype=bool)
        while not reach.all():
            reach, step = (reach.astype(np.float32) @ near) > 0, step + 1
        return step

    def bipartite(self) -> bool:
        colour = np.full(self.n, -1)
        colour[0], todo = 0, [0]
        near = self.adjacency()
        while todo:
            a = todo.pop()
            for b in np.flatnonzero(near[a]):
                if colour[b] < 0:
                    colour[b] = 1 - colour[a]
                    todo.append(int(b))
                elif colour[b] == colour[a]:
                    return False
        return True

    def adjacency(self) -> np.ndarray:
        a = np.zeros((self.n, self.n), bool)
        for i, j in self.edges:
            a[i, j] = a[j, i] = True
        return a

    def edge_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(list(self.edges), "src int, dst int") if self.edges else spark.createDataFrame([], "src int, dst int")

    def weights(self, kind: str = "local_degree") -> np.ndarray:
        return mixing_matrix(self, kind)


def erdos_renyi(n: int, p: float, seed: int = 1, tries: int = 1000) -> Topology:
    """Each pair is an edge if its md5 fraction is below p; the seed advances until the graph is connected."""
    for own in range(seed, seed + tries):
        edges = tuple((i, j) for i in range(n) for j in range(i + 1, n) if int(hashlib.md5(f"{own}|{i}|{j}".encode()).hexdigest()[:8], 16) / (1 << 32) < p)
        if _connected(n, list(edges)):
            return Topology(n, edges, f"random(p={p:g},seed={own})")
    raise ValueError("no connected graph was drawn")


def random_edges(spark: SparkSession, n: int, p: float, seed: int) -> DataFrame:
    """The same draw as a DataFrame plan (one seed, not checked for connection)."""
    ids = spark.range(n).select(F.col("id").cast("int").alias("src"))
    pairs = ids.crossJoin(F.broadcast(ids.withColumnRenamed("src", "dst"))).where("src < dst")
    return pairs.where(md5_fraction(F.lit(str(seed)), F.col("src").cast("string"), F.col("dst").cast("string")) < p)


def traffic(rows: DataFrame, a: str, b: str, n: int, lines: str | None = None) -> DataFrame:
    """(src, dst, lines): how many rows (or the sum of a column ``lines``) lie between two of ``n`` nodes, a key's node
    being its remainder. Rows without a key, and those within one node, link nothing."""
    ends = rows.select(F.pmod(a, F.lit(n)).cast("int").alias("a"), F.pmod(b, F.lit(n)).cast("int").alias("b"), (F.col(lines) if lines else F.lit(1)).cast("long").alias("lines")).where("a <> b")
    return ends.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("lines").alias("lines"))


def drawn_edges(pairs: DataFrame, p: float, seed: int) -> DataFrame:
    """Random edges among the pairs of :func:`traffic`, drawn by md5 of (seed, src, dst, lines)."""
    parts = [F.col(c).cast("string") for c in ("src", "dst", "lines")]
    return pairs.where(md5_fraction(F.lit(str(seed)), *parts) < p).select("src", "dst")


def ring(n: int) -> Topology:
    return Topology(n, tuple((i, (i + 1) % n) for i in range(n)), "ring")


def star(n: int) -> Topology:
    return Topology(n, tuple((0, i) for i in range(1, n)), "star")


def complete(n: int) -> Topology:
    return Topology(n, tuple((i, j) for i in range(n) for j in range(i + 1, n)), "complete")


def path(n: int) -> Topology:
    return Topology(n, tuple((i, i + 1) for i in range(n - 1)), "path")


def grid(a: int, b: int) -> Topology:
    across = [(i * b + j, i * b + j + 1) for i in range(a) for j in range(b - 1)]
    down = [(i * b + j, (i + 1) * b + j) for i in range(a - 1) for j in range(b)]
    return Topology(a * b, tuple(across + down), "grid")


def from_table(edges: DataFrame, src: str = "src", dst: str = "dst") -> Topology:
    """Graph of a table's pairs, nodes numbered 0..max; loops and repeats are dropped. The number of
    distinct edges is checked before they reach the driver."""
    pairs = edges.select(F.least(src, dst).cast("int").alias("a"), F.greatest(src, dst).cast("int").alias("b")).where("a < b").distinct()
    rows = pairs.limit(MAX_NODES * 200 + 1).collect()
    if len(rows) > MAX_NODES * 200:
        raise ValueError("too many edges for a node graph")
    return Topology(max((r["b"] for r in rows), default=0) + 1, tuple((r["a"], r["b"]) for r in rows), "table")


def nation_graph(spark: SparkSession, sf_dir: str) -> Topology:
    """25 nations: those of a region know each other, and the first nations of the regions do."""
    from meshspan.sources.tables import load_table

    n = load_table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("g"))
    a, b = n.alias("a"), F.broadcast(n).alias("b")
    same = a.join(b, (F.col("a.g") == F.col("b.g")) & (F.col("a.k") < F.col("b.k"))).select(F.col("a.k").alias("src"), F.col("b.k").alias("dst"))
    heads = n.groupBy("g").agg(F.min("k").alias("k"))
    across = heads.alias("a").join(F.broadcast(heads).alias("b"), F.col("a.k") < F.col("b.k")).select(F.col("a.k").alias("src"), F.col("b.k").alias("dst"))
    return from_table(same.union(across))


# ---------------------------------------------------------------- weights


def mixing_matrix(topology: Topology, kind: str = "local_degree") -> np.ndarray:
    """Symmetric doubly stochastic weights: local_degree (one over the larger degree), metropolis (one over
    one more), max_degree, lazy (half local_degree, half identity), uniform (one over n: every node hears
    every other). What a row lacks to one stays on its diagonal."""
    n, deg = topology.n, topology.degrees
    if kind == "uniform":
        return np.full((n, n), 1 / n)
    if kind == "lazy":
        return (mixing_matrix(topology) + np.eye(n)) / 2
    w = np.zeros((n, n))
    for i, j in topology.edges:
        larger = max(deg[i], deg[j])
        w[i, j] = w[j, i] = 1 / {"local_degree": larger, "metropolis": larger + 1, "max_degree": deg.max() + 1}[kind]
    np.fill_diagonal(w, 1 - w.sum(1))
    return w


def weight_table(edges: DataFrame, n: int, kind: str = "local_degree") -> DataFrame:
    """(src, dst, w) of local-degree or Metropolis weights as a plan: both directions and the diagonal."""
    both = edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    degree = both.groupBy("src").agg(F.count("*").alias("deg"))
    more = 1 if kind == "metropolis" else 0
    off = (
        both.join(degree, "src").join(degree.select(F.col("src").alias("dst"), F.col("deg").alias("other")), "dst")
        .select("src", "dst", (F.lit(1.0) / (F.greatest("deg", "other") + more)).alias("w"))
    )
    nodes = edges.sparkSession.range(n).select(F.col("id").cast("int").alias("src"))
    own = off.groupBy("src").agg(F.sum("w").alias("given"))
    diagonal = nodes.join(own, "src", "left").select("src", F.col("src").alias("dst"), (1 - F.coalesce("given", F.lit(0.0))).alias("w"))
    return off.union(diagonal)


def check_weights(w: np.ndarray, topology: Topology | None = None, tolerance: float = 1e-9) -> None:
    """Raise unless w is non-negative, doubly stochastic and, given a graph, supported on it."""
    if (w < -tolerance).any():
        raise ValueError("a weight is negative")
    if abs(w.sum(0) - 1).max() > tolerance or abs(w.sum(1) - 1).max() > tolerance:
        raise ValueError("rows and columns must sum to one")
    if topology is not None and (w[~(topology.adjacency() | np.eye(topology.n, dtype=bool))] > tolerance).any():
        raise ValueError("a weight lies off the graph")


def second_modulus(w: np.ndarray) -> float:
    """Second largest modulus of the eigenvalues: averaging error shrinks by it per round."""
    return float(np.sort(abs(np.linalg.eigvals(w)))[-2]) if len(w) > 1 else 0.0


def spectral_gap(w: np.ndarray) -> float:
    return 1 - second_modulus(w)


def mixing_time(w: np.ndarray, threshold: float = 0.5, norm: str = "l2", cap: int = 10_000) -> int | None:
    """Fewest rounds after which every row of the power is within ``threshold`` of uniform; None if the
    cap is passed. In the l2 norm a periodic graph can pass though it never mixes: see second_modulus."""
    power = np.eye(len(w))
    for t in range(cap + 1):
        off = power - 1 / len(w)
        far = np.sqrt((off**2).sum(1)).max() if norm == "l2" else abs(off).sum(1).max() / 2
        if far <= threshold:
            return t
        power = power @ w
    return None
