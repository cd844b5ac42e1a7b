"""Estimator and model in the style of Spark's machine learning library, over ARRAY or ML vector columns."""

from __future__ import annotations

import dataclasses

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.operators.topology import Topology
from meshspan.plans.api import Fitted, MeshSpan
from meshspan.plans.schedules import Fixed, Schedule


def _as_samples(df: DataFrame, column: str) -> tuple[DataFrame, bool]:
    vectors = "udt" in df.schema[column].dataType.typeName() or df.schema[column].dataType.simpleString() == "vector"
    features = vector_to_array(column) if vectors else F.col(column).cast("array<double>")
    return df.withColumn("features", features), vectors


@dataclasses.dataclass
class SubspaceModel:
    fitted: Fitted
    input_col: str
    output_col: str

    def transform(self, df: DataFrame) -> DataFrame:
        samples, vectors = _as_samples(df, self.input_col)
        coded = self.fitted.encode(samples)
        out = coded.withColumn(self.output_col, array_to_vector("code") if vectors else F.col("code"))
        return out.select(*[c for c in df.columns if c != self.output_col], self.output_col)


@dataclasses.dataclass
class SubspaceEstimator:
    """``SubspaceEstimator(k=5, input_col="features", output_col="code", id_col="sample_id").fit(df).transform(df)``"""

    k: int
    input_col: str = "features"
    output_col: str = "code"
    id_col: str = "sample_id"
    topology: Topology | None = None
    schedule: Schedule = dataclasses.field(default_factory=Fixed)
    outer: int = 100
    seed: int = 7

    def fit(self, df: DataFrame) -> SubspaceModel:
        samples, _ = _as_samples(df, self.input_col)
        samples = samples.select(F.col(self.id_col).alias("sample_id"), "features")
        fitted = MeshSpan(df.sparkSession, self.topology, self.schedule, self.outer, self.seed).fit(samples, self.k)
        return SubspaceModel(fitted, self.input_col, self.output_col)
