"""How good a basis is, as DataFrame plans over basis tables (node, i, q)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meshspan.functions.vectors import vec_dot


def truth_table(spark: SparkSession, truth: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(truth)], "i int, p array<double>")


def subspace_error(basis: DataFrame, truth: DataFrame) -> DataFrame:
    """(node, error): mean squared sine of the principal angles, 1 - |QᵀP|² / r, from r x r sums alone."""
    cells = basis.join(F.broadcast(truth), "i").select("node", F.posexplode("q").alias("a", "x"), "p").select("node", "a", "x", F.posexplode("p").alias("b", "y"))
    cross = cells.groupBy("node", "a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("c"))
    return cross.groupBy("node").agg(F.greatest(F.lit(0.0), 1 - F.sum(F.col("c") * F.col("c")) / (F.max("b") + 1)).alias("error"))


def network_error(basis: DataFrame, truth: DataFrame, how: str = "mean") -> DataFrame:
    each = subspace_error(basis, truth)
    return each.agg((F.avg if how == "mean" else F.max)("error").alias("error"))


def projector(basis: DataFrame) -> DataFrame:
    """(node, i, j, p): entries of QQᵀ, which do not depend on signs or rotations of the basis."""
    other = basis.select("node", F.col("i").alias("j"), F.col("q").alias("p"))
    return basis.join(other, "node").select("node", "i", "j", vec_dot(F.col("q"), F.col("p")).alias("p"))


def projector_distance(q: np.ndarray, p: np.ndarray, norm: str = "2") -> float:
    """Spectral or Frobenius distance of the projectors; the Frobenius one squared is 2 r times the error."""
    sines = np.sqrt(np.maximum(0, 1 - np.linalg.svd(q.T @ p, compute_uv=False) ** 2))
    return float(sines.max() if norm == "2" else np.sqrt(2 * (sines**2).sum()))


def init_angle(q: np.ndarray, truth: np.ndarray) -> float:
    """Smallest cosine between a start and the truth: it must not be zero."""
    return float(np.linalg.svd(q.T @ truth, compute_uv=False).min())


def orthonormality_defect(basis: DataFrame) -> DataFrame:
    """(node, defect): largest entry of |QᵀQ - I|."""
    cells = basis.select("node", "i", F.posexplode("q").alias("a", "x"), "q").select("node", "a", "x", F.posexplode("q").alias("b", "y"))
    gram = cells.groupBy("node", "a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("g"))
    return gram.groupBy("node").agg(F.max(F.abs(F.col("g") - F.when(F.col("a") == F.col("b"), 1.0).otherwise(0.0))).alias("defect"))


def disagreement(basis: DataFrame) -> DataFrame:
    """Largest distance of a node's basis from the mean of all: one row."""
    wide = basis.select("node", "i", F.posexplode("q").alias("a", "x"))
    off = wide.withColumn("m", F.avg("x").over(Window.partitionBy("i", "a"))).groupBy("node").agg(F.sqrt(F.sum((F.col("x") - F.col("m")) ** 2)).alias("off"))
    return off.agg(F.max("off").alias("disagreement"))


def distance_to_central(basis: DataFrame, central: DataFrame) -> DataFrame:
    """(node, distance) in Frobenius norm from one central basis (i, p)."""
    pairs = basis.join(F.broadcast(central), "i").select("node", F.aggregate(F.zip_with("q", "p", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v).alias("s"))
    return pairs.groupBy("node").agg(F.sqrt(F.sum("s")).alias("distance"))


def objective(scatter: DataFrame, basis: DataFrame) -> DataFrame:
    """(node, kept, lost) of every node's basis on every row's moments: trace(QᵀMQ) and trace(M) - that, from
    the scatter (all nodes' rows summed), without a second scan."""
    total = scatter.groupBy("i").agg(F.collect_list("row").alias("rows")).select("i", F.expr("aggregate(slice(rows, 2, size(rows)), rows[0], (a, b) -> zip_with(a, b, (x, y) -> x + y))").alias("row"))
    trace = total.agg(F.sum(F.element_at("row", F.col("i") + 1)).alias("trace"))
    wide = total.select("i", F.posexplode("row").alias("j", "m"))
    left = basis.select("node", "i", "q").join(wide, "i").join(basis.select("node", F.col("i").alias("j"), F.col("q").alias("p")), ["node", "j"])
    kept = left.groupBy("node").agg(F.sum(F.col("m") * vec_dot(F.col("q"), F.col("p"))).alias("kept"))
    return kept.crossJoin(F.broadcast(trace)).select("node", "kept", (F.col("trace") - F.col("kept")).alias("lost"))


def eigengaps(values: np.ndarray, spark: SparkSession) -> DataFrame:
    """(k, lambda, ratio): ratio of the next eigenvalue to this one; near one means that the rank k subspace is
    ill-posed."""
    rows = spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(values)], "k int, lambda double")
    return rows.withColumn("ratio", F.lead("lambda").over(Window.orderBy("k")) / F.col("lambda"))


def well_posed(values: np.ndarray, r: int, most: float = 0.99) -> bool:
    return r < len(values) and values[r] / values[r - 1] <= most


def fit_rate(trace: DataFrame, low: float = 1e-9, high: float = 1e-1) -> DataFrame:
    """(method, slope): slope of log error over outer steps while the error is between the bounds; theory
    says twice the log of the eigenvalue ratio (the error is a squared sine)."""
    mean = trace.groupBy("method", "t").agg(F.avg("error").alias("e")).where(F.col("e").between(low, high))
    return mean.groupBy("method").agg(F.regr_slope(F.log("e"), F.col("t").cast("double")).alias("slope"))


def convergence(trace: DataFrame) -> DataFrame:
    """Per method and step: mean and largest error over nodes, and the ratio to the step before."""
    each = trace.groupBy("method", "t", "inner_total").agg(F.avg("error").alias("error"), F.max("error").alias("worst"), F.percentile_approx("error", 0.5).alias("median"))
    return each.withColumn("ratio", F.col("error") / F.lag("error").over(Window.partitionBy("method").orderBy("t")))


def iterations_to(trace: DataFrame, levels: list[float]) -> DataFrame:
    """(method, level, inner_total): total rounds after which the mean error first is below each level (null:
    never)."""
    spark = trace.sparkSession
    mean = trace.groupBy("method", "t", "inner_total").agg(F.avg("error").alias("error"))
    grid = mean.select("method").distinct().crossJoin(F.broadcast(spark.createDataFrame([(v,) for v in levels], "level double")))
    hit = mean.join(F.broadcast(spark.createDataFrame([(v,) for v in levels], "level double")), F.col("error") < F.col("level"))
    return grid.join(hit.groupBy("method", "level").agg(F.min("inner_total").alias("inner_total")), ["method", "level"], "left")


def monte_carlo(trials: list[DataFrame]) -> DataFrame:
    """Mean and deviation over trials of the mean error per method and step."""
    out = None
    for k, trace in enumerate(trials):
        own = trace.groupBy("method", "t").agg(F.avg("error").alias("e")).withColumn("trial", F.lit(k))
        out = own if out is None else out.unionByName(own)
    return out.groupBy("method", "t").agg(F.avg("e").alias("mean"), F.stddev_samp("e").alias("sd"), F.count("*").alias("trials"))
