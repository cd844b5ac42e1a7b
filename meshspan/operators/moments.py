"""Second moments: the one pass over the rows, after which everything is independent of their number.

Partial sums are made per task and node in numpy (blocks of a d x d matrix, flushed at a byte budget, never a row
per entry), then added per node and block. The mean is folded in afterwards by a rank-one correction, so
centring costs no second scan.
"""

from __future__ import annotations

import dataclasses

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.operators.nodes import PIECE_BYTES, added, dimension, raw_pieces, vectors_of
from meshspan.sources.tables import stored

SCATTER = "node int, i int, n long, total double, row array<double>"
DENSE_ROWS = int((PIECE_BYTES / 8) ** 0.5)  # features whose matrix is one block
_ROWS = pa.schema([("node", pa.int32()), ("i", pa.int32()), ("n", pa.int64()), ("total", pa.float64()), ("row", pa.list_(pa.float64()))])


def local_scatter(samples: DataFrame, d: int | None = None) -> DataFrame:
    """Raw moments of every node from ``samples(node, features)``: a row per node and feature i with the
    node's rows n, the feature's sum (total), and row i of the sum of outer products."""
    d = dimension(samples) if d is None else d

    def rows(batches):
        for batch in batches:
            for node, low, k, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "body")), strict=True):
                flat = pa.array(np.frombuffer(body))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (k + 1) * d, d), pa.int32()), flat)
                yield pa.RecordBatch.from_arrays([pa.array([node] * k, pa.int32()), pa.array(range(low, low + k), pa.int32()), lists], ["node", "i", "row"])

    def sums(batches):
        for batch in batches:
            for node, n, total in zip(*(batch.column(c).to_pylist() for c in ("node", "n", "total")), strict=True):
                if total is not None:
                    yield pa.RecordBatch.from_arrays([pa.array([node] * d, pa.int32()), pa.array(range(d), pa.int32()), pa.array([n] * d, pa.int64()), pa.array(np.frombuffer(total))], ["node", "i", "n", "total"])

    blocks = added(raw_pieces(samples, d, keep=False).repartition("node", "low").sortWithinPartitions("node", "low"), d)
    if d <= DENSE_ROWS:  # one block per node holds its sums too
        def both(batches):
            for batch in batches:
                for node, k, n, total, body in zip(*(batch.column(c).to_pylist() for c in ("node", "k", "n", "total", "body")), strict=True):
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (k + 1) * d, d), pa.int32()), pa.array(np.frombuffer(body)))
                    yield pa.RecordBatch.from_arrays([pa.array([node] * d, pa.int32()), pa.array(range(d), pa.int32()), pa.array([n] * d, pa.int64()), pa.array(np.frombuffer(total)), lists], schema=_ROWS)

        return blocks.mapInArrow(both, SCATTER)
    blocks = stored(blocks, "scatter")
    return blocks.mapInArrow(sums, "node int, i int, n long, total double").join(blocks.mapInArrow(rows, "node int, i int, row array<double>"), ["node", "i"]).select("node", "i", "n", "total", "row")


def narrow_scatter(samples: DataFrame, d: int) -> DataFrame:
    """The same table for few features (d <= 16) by plain aggregates, inside whole-stage code."""
    if d > 16:
        raise ValueError("for up to 16 features")
    f = [F.element_at("features", i + 1) for i in range(d)]
    sums = [F.sum(f[i]).alias(f"s{i}") for i in range(d)] + [F.sum(f[i] * f[j]).alias(f"p{i}_{j}") for i in range(d) for j in range(i, d)]
    agg = samples.groupBy("node").agg(F.count("*").alias("n"), *sums)
    rows = [F.struct(F.lit(i).alias("i"), F.col("n"), F.col(f"s{i}").alias("total"), F.array(*[F.col(f"p{min(i, j)}_{max(i, j)}") for j in range(d)]).alias("row")) for i in range(d)]
    return agg.select(F.col("node").cast("int").alias("node"), F.inline(F.array(*rows)))


@dataclasses.dataclass
class Moments:
    """n, sum and raw scatter; of all rows or of one node."""

    n: int
    total: np.ndarray
    scatter: np.ndarray

    @property
    def d(self) -> int:
        return len(self.total)

    @property
    def mean(self) -> np.ndarray:
        return self.total / max(1, self.n)

    @property
    def covariance(self) -> np.ndarray:
        return self.scatter / max(1, self.n) - np.outer(self.mean, self.mean)


def global_moments(samples: DataFrame) -> Moments:
    """Moments of all rows. A d x d matrix reaches the driver: d is checked."""
    d = dimension(samples)
    if d > 5792:
        raise ValueError("over 5,792 features: keep the scatter distributed")
    one = samples.select(F.lit(0).alias("node"), "features")
    blocks = added(raw_pieces(one, d, keep=False).repartition("node", "low").sortWithinPartitions("node", "low"), d).select("low", "n", "total", "body").toArrow().sort_by("low")
    n, total = blocks["n"][0].as_py(), np.frombuffer(blocks["total"][0].as_py())
    return Moments(n, total, np.concatenate([np.frombuffer(b) for b in blocks["body"].to_pylist()]).reshape(d, d))


def stacked(scatter, center: str = "exact", normalizer: str = "n", local_scale: str = "sum") -> tuple[np.ndarray, np.ndarray]:
    """(node ids, node matrices) from the rows of a scatter table (pandas or Arrow); the matrices add up
    to the covariance times the number of nodes.

    ``center``: exact subtracts the mean of all rows (each node's share of the correction), none does not.
    ``normalizer``: n, n-1 or none. ``local_scale``: sum keeps what makes the nodes' sum exact, mean divides
    each node by its own rows (equal weight for nodes of unequal size).
    """
    frame = scatter.sort_values(["node", "i"]) if hasattr(scatter, "sort_values") else scatter.to_pandas().sort_values(["node", "i"])
    nodes = np.unique(frame.node.to_numpy())
    d = len(frame) // len(nodes)
    raw = np.stack(frame.row.to_list()).reshape(len(nodes), d, d)
    n = frame.n.to_numpy().reshape(len(nodes), d)[:, 0].astype(float)
    total = frame.total.to_numpy().reshape(len(nodes), d)
    if center == "exact":
        mean = total.sum(0) / n.sum()
        cross = np.einsum("ni,j->nij", total, mean)
        raw = raw - cross - np.swapaxes(cross, 1, 2) + n[:, None, None] * np.outer(mean, mean)
    if local_scale == "mean":
        return nodes, raw / n[:, None, None]
    by = {"n": n.sum(), "n-1": n.sum() - 1, "none": len(nodes)}[normalizer]
    return nodes, raw * (len(nodes) / by)


def with_all_nodes(scatter: DataFrame, n: int, d: int) -> DataFrame:
    """Nodes without rows get zero moments."""
    spark = scatter.sparkSession
    grid = spark.range(n * d).select((F.col("id") / d).cast("int").alias("node"), (F.col("id") % d).cast("int").alias("i"))
    zero = F.array_repeat(F.lit(0.0), d)
    return grid.join(scatter, ["node", "i"], "left").select("node", "i", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("total", F.lit(0.0)).alias("total"), F.coalesce("row", zero).alias("row"))
