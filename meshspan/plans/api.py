"""One object to fit, encode and compare."""

from __future__ import annotations

import dataclasses

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.operators import encode as codes
from meshspan.operators import moments, partition, subspace
from meshspan.operators.topology import Topology, complete
from meshspan.plans.schedules import Fixed, Schedule


@dataclasses.dataclass
class Fitted:
    result: subspace.SubspaceResult
    moments: moments.Moments
    basis: np.ndarray

    def encode(self, samples: DataFrame) -> DataFrame:
        return codes.encode(samples, self.basis, self.moments.mean)

    def decode(self, coded: DataFrame) -> DataFrame:
        return codes.decode(coded, self.basis, self.moments.mean)

    def explained_variance(self) -> np.ndarray:
        """Share of the variance along each component inside the subspace."""
        values = np.linalg.eigvalsh(self.basis.T @ self.moments.covariance @ self.basis)[::-1]
        return values / np.trace(self.moments.covariance)


@dataclasses.dataclass
class MeshSpan:
    """``MeshSpan(spark).fit(samples, r=5)``: samples are (sample_id, features), with a node column or dealt by id."""

    spark: SparkSession
    topology: Topology | None = None
    schedule: Schedule = dataclasses.field(default_factory=Fixed)
    outer: int = 100
    seed: int = 7

    def _ready(self, samples: DataFrame) -> tuple[DataFrame, Topology]:
        topology = self.topology or complete(4)
        return (samples if "node" in samples.columns else partition.by_hash(samples, topology.n)), topology

    def fit(self, samples: DataFrame, r: int, split: str = "row", **options) -> Fitted:
        ready, topology = self._ready(samples)
        whole = moments.global_moments(samples)
        if split == "row":
            result = subspace.rowsplit_subspace(ready, topology, r, self.schedule, self.outer, self.seed, **options)
        else:
            blocks = options.pop("blocks", None) or partition.column_blocks(whole.d, topology.n)
            result = subspace.colsplit_subspace(samples, blocks, topology, r, self.schedule, self.outer, self.seed, **options)
        q = result.as_matrix(0) if split == "row" else np.stack(result.basis.orderBy("i").toPandas().q.to_list())
        return Fitted(result, whole, q)

    def compare(self, samples: DataFrame, r: int, methods: tuple[str, ...] = ("row", *subspace.BASELINES), every: int = 1) -> DataFrame:
        """Traces of several methods on the same samples, graph and start, with exact errors."""
        ready, topology = self._ready(samples)
        out = None
        for name in methods:
            if name == "row":
                own = subspace.rowsplit_subspace(ready, topology, r, self.schedule, self.outer, self.seed, truth="exact", every=every)
            else:
                own = subspace.baseline(ready, name, r, topology, self.schedule, self.outer, self.seed, truth="exact", every=every)
            trace = own.trace.withColumn("method", F.lit(name))
            out = trace if out is None else out.unionByName(trace)
        return out
