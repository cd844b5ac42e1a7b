"""Using a basis: encode, decode, what is lost, and a small classifier on codes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.functions.vectors import mat_literal, mat_vec


def encode(samples: DataFrame, q: np.ndarray, mean: np.ndarray | None = None) -> DataFrame:
    """Adds ``code`` = Qᵀ(x - mean): SQL expressions for few features, a matrix product per Arrow batch beyond."""
    d, r = q.shape
    if d * r <= 1024:
        x = F.col("features")
        if mean is not None:
            x = F.zip_with(x, F.array(*[F.lit(float(v)) for v in mean]), lambda a, b: a - b)
        return samples.withColumn("code", mat_vec(mat_literal(q.T), x))
    shared = samples.sparkSession.sparkContext.broadcast((q, np.zeros(d) if mean is None else mean))

    @F.pandas_udf("array<double>")
    def product(x: pd.Series) -> pd.Series:
        basis, shift = shared.value
        return pd.Series(list((np.stack(x.to_list()) - shift) @ basis)) if len(x) else pd.Series([], dtype=object)

    return samples.withColumn("code", product("features"))


def decode(codes: DataFrame, q: np.ndarray, mean: np.ndarray | None = None) -> DataFrame:
    """Adds ``decoded`` = Q code + mean."""
    x = mat_vec(mat_literal(q), F.col("code"))
    if mean is not None:
        x = F.zip_with(x, F.array(*[F.lit(float(v)) for v in mean]), lambda a, b: a + b)
    return codes.withColumn("decoded", x)


def reconstruction_error(samples: DataFrame, q: np.ndarray, mean: np.ndarray | None = None) -> DataFrame:
    """One row: total squared norm (about the mean), what the basis keeps, and what it loses."""
    coded = encode(samples, q, mean)
    shift = F.array(*[F.lit(float(v)) for v in (np.zeros(len(q)) if mean is None else mean)])
    norm = F.aggregate(F.zip_with("features", shift, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    kept = F.aggregate("code", F.lit(0.0), lambda s, v: s + v * v)
    return coded.agg(F.sum(norm).alias("total"), F.sum(kept).alias("kept")).withColumn("lost", F.col("total") - F.col("kept"))


def nearest_centroid_accuracy(samples: DataFrame, label: str, vector: str) -> DataFrame:
    """One row: share of samples whose label's mean vector is the nearest. The means are one row per label and
    entry; the number of labels is checked before they are broadcast."""
    wide = samples.select(F.col(label).alias("y"), F.posexplode(vector)).groupBy("y", "pos").agg(F.avg("col").alias("m"))
    means = wide.groupBy("y").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda s: s["m"]).alias("mean"))
    if means.limit(10_001).count() > 10_000:
        raise ValueError("too many labels")
    far = F.aggregate(F.zip_with(vector, "mean", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    near = samples.withColumn("_id", F.monotonically_increasing_id()).crossJoin(F.broadcast(means.withColumnRenamed("y", "guess"))).groupBy("_id").agg(F.min_by("guess", far).alias("guess"), F.first(label).alias("y"))
    return near.agg(F.avg((F.col("guess") == F.col("y")).cast("double")).alias("accuracy"), F.count("*").alias("n"))
