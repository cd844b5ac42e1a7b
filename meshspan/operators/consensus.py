"""Neighbour averaging.

Rounds of averaging are a linear map, so any number of them is one multiplication with a power of the
mixing matrix: one shuffle instead of one per round. The round-by-round plan is kept to prove it.
Values are a table (node, i, z ARRAY<DOUBLE>): node's row i of some matrix.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.functions.linalg import Powers, anchor_scale

VALUES = "node int, i int, z array<double>"
_ROWS = pa.schema([("node", pa.int32()), ("i", pa.int32()), ("z", pa.list_(pa.float64()))])


def run_rounds(values: DataFrame, weights: DataFrame, rounds: int) -> DataFrame:
    """``rounds`` joins with the weight table (src, dst, w), each summed per receiving node."""
    wide = values.select("node", "i", F.posexplode("z").alias("k", "v"))
    for _ in range(rounds):
        sent = wide.join(F.broadcast(weights), wide.node == weights.src)
        wide = sent.groupBy(F.col("dst").alias("node"), "i", "k").agg(F.sum(F.col("w") * F.col("v")).alias("v"))
    packed = wide.groupBy("node", "i").agg(F.array_sort(F.collect_list(F.struct("k", "v"))).alias("kv"))
    return packed.select(F.col("node").cast("int").alias("node"), "i", F.transform("kv", lambda s: s["v"]).alias("z"))


def run_fused(values: DataFrame, power: np.ndarray, scale: np.ndarray | None = None, block: int = 64) -> DataFrame:
    """All rounds at once: rows are gathered by blocks of i, and each block is one product with the power.
    ``scale`` multiplies each node's result. The matrix is broadcast: N x N, N checked by the topology."""
    spark = values.sparkSession
    shared = spark.sparkContext.broadcast((power, scale))

    def mix(key: tuple, group: pa.Table) -> pa.Table:
        w, s = shared.value
        node, i = np.asarray(group["node"]), np.asarray(group["i"])
        z = np.asarray(group["z"].combine_chunks().flatten(), float).reshape(len(node), -1)
        rows, at = np.unique(i, return_inverse=True)
        cube = np.zeros((len(w), len(rows), z.shape[1]))
        np.add.at(cube, (node, at), z)
        out = np.tensordot(w.T, cube, 1)
        if s is not None:
            out *= s[:, None, None]
        n, r = len(w), len(rows)
        return pa.table({"node": np.repeat(np.arange(n, dtype=np.int32), r), "i": np.tile(rows.astype(np.int32), n), "z": list(out.reshape(n * r, -1))}, schema=_ROWS)

    keyed = values.withColumn("block", F.floor(F.col("i") / block))
    return keyed.groupBy("block").applyInArrow(mix, VALUES)


def consensus_sum(values: DataFrame, w: np.ndarray, rounds: int, rescale: str = "safe") -> DataFrame:
    """Each node's estimate of the sum of all nodes' values after some rounds."""
    power = Powers(w)[rounds]
    return run_fused(values, power, anchor_scale(power, rescale))


def push_sum(values: np.ndarray, p: np.ndarray, rounds: int, target: str = "sum") -> np.ndarray:
    """Ratio averaging of stacked node values with a column-stochastic matrix (p[j, i]: share that i sends
    to j): values and scalar weights are mixed alike and divided. Weights of one give the mean; a single
    weight at the first node gives the sum (nodes it has not reached yet hold not-a-number)."""
    power = Powers(p)[rounds]
    start = np.ones(len(p)) if target == "mean" else np.eye(len(p))[0]
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.tensordot(power, values, 1) / (power @ start).reshape(-1, *[1] * (values.ndim - 1))


def fast_power(w: np.ndarray, rounds: int) -> np.ndarray:
    """Accelerated averaging: the Chebyshev polynomial of the mixing matrix that shrinks everything but the
    mean fastest, from the second largest modulus."""
    from meshspan.operators.topology import second_modulus

    n, rho = len(w), second_modulus(w)
    if rounds == 0 or rho < 1e-12 or rho > 1 - 1e-12:
        return Powers(w)[rounds]
    before, now = np.eye(n), w.copy()
    a, b = 1.0, 1 / rho
    for _ in range(rounds - 1):
        c = 2 * b / rho - a
        before, now = now, (2 * b / rho * (w @ now) - a * before) / c
        a, b = b, c
    return now


def mixing_error(values: np.ndarray, w: np.ndarray, rounds: int, rescale: str = "anchor") -> tuple[np.ndarray, float]:
    """Frobenius distance of every node's estimate of the sum from the true sum, and the norm of the sum of
    absolute values that bounds it up to the mixing accuracy."""
    power = Powers(w)[rounds]
    estimate = np.tensordot(power.T, values, 1) * anchor_scale(power, rescale).reshape(-1, *[1] * (values.ndim - 1))
    off = (estimate - values.sum(0)).reshape(len(values), -1)
    return np.sqrt((off**2).sum(1)), float(np.sqrt((np.abs(values).sum(0) ** 2).sum()))
