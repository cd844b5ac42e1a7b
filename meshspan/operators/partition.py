"""Which node holds which row, and which column."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def by_hash(samples: DataFrame, n: int) -> DataFrame:
    return samples.withColumn("node", F.pmod(F.col("sample_id"), F.lit(n)).cast("int"))


def by_key(samples: DataFrame, key: Column) -> DataFrame:
    return samples.withColumn("node", key.cast("int"))


def by_range(samples: DataFrame, n: int, total: int, truncate: bool = False) -> DataFrame:
    """Contiguous ranges of dense 0-based ids; ``truncate`` gives every node floor(total / n) rows and
    leaves the remainder out."""
    per = total // n
    if truncate:
        return samples.where(F.col("sample_id") < per * n).withColumn("node", F.floor(F.col("sample_id") / per).cast("int"))
    return samples.withColumn("node", F.floor(F.col("sample_id") * n / total).cast("int"))


def skewed(samples: DataFrame, n: int) -> DataFrame:
    """Node sizes grow with the square of the node's number."""
    share = F.pmod(F.xxhash64("sample_id"), F.lit(1 << 20)) / float(1 << 20)
    return samples.withColumn("node", F.least(F.floor(F.cbrt(share) * n), F.lit(n - 1)).cast("int"))


def ranked(samples: DataFrame, n: int, within: str) -> DataFrame:
    """Balanced nodes inside every group of a column (rows of one group pass one task: for small groups)."""
    return samples.withColumn("node", F.ntile(n).over(Window.partitionBy(within).orderBy("sample_id")) - 1)


def column_blocks(d: int, n: int, how: str = "contiguous") -> list[np.ndarray]:
    """Feature numbers of each node: contiguous, round_robin, or unequal (the first node has half)."""
    if not 1 <= n <= d:
        raise ValueError("every node needs a column")
    if how == "round_robin":
        return [np.arange(i, d, n) for i in range(n)]
    if how == "unequal" and n > 1:
        first = max(1, min(d // 2, d - n + 1))
        return [np.arange(first), *(b + first for b in np.array_split(np.arange(d - first), n - 1))]
    return list(np.array_split(np.arange(d), n))


def column_map(spark: SparkSession, blocks: list[np.ndarray]) -> DataFrame:
    return spark.createDataFrame([(int(f), i, k) for i, b in enumerate(blocks) for k, f in enumerate(b)], "feature int, node int, local int")
