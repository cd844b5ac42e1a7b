"""Moments over streams, and the streaming operators around them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from meshspan.operators import loops, moments
from meshspan.functions.linalg import random_basis


def accumulate(stream: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Keep the node moments of a stream of (node, features): each micro-batch writes its own sums under its
    batch number, so that a batch that runs again replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        moments.local_scatter(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def accumulated(spark: SparkSession, path: str) -> DataFrame:
    """The scatter table of all batches so far."""
    parts = spark.read.parquet(path).select("node", "i", "n", "total", "row")

    def merge(frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"node": [frame.node.iloc[0]], "i": [frame.i.iloc[0]], "n": [frame.n.sum()], "total": [frame.total.sum()], "row": [np.sum(np.stack(frame.row.to_list()), 0)]})

    return parts.groupBy("node", "i").applyInPandas(merge, moments.SCATTER)


def refreshed(scatter: DataFrame, w: np.ndarray, r: int, rounds: list[int], start: np.ndarray | None = None) -> np.ndarray:
    """Node bases after a few outer steps on accumulated moments, from the last bases (warm) or afresh."""
    _, m = moments.stacked(scatter.toPandas())
    q0 = random_basis(m.shape[1], r, 7) if start is None else start
    q = None
    for _, q in loops.row_split(m, w, rounds, q0):
        pass
    return q


def event_stream(df: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events with a true timestamp (a watermark refuses timestamps without zone) and a watermark."""
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def windowed_activity(events: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Counts and sums per user and tumbling (or sliding) window."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy(window.alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def distinct_events(events: DataFrame) -> DataFrame:
    """Each event once while the watermark remembers it."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def with_nodes(events: DataFrame, node_map: DataFrame) -> DataFrame:
    """Stream-static join with a bounded map (user_id, node)."""
    return events.join(F.broadcast(node_map), "user_id")


def forgetting(events: DataFrame, factor: float = 0.9) -> DataFrame:
    """Per node, moments of two features (value, hour) that forget the past: each micro-batch's state is the
    old one times the factor plus the batch's sums."""

    def update(key, frames, state):
        n, s, ss = state.get if state.exists else (0.0, 0.0, 0.0)
        n, s, ss = n * factor, s * factor, ss * factor
        for f in frames:
            n, s, ss = n + len(f), s + float(f.value.sum()), ss + float((f.value**2).sum())
        state.update((n, s, ss))
        yield pd.DataFrame({"node": [key[0]], "n": [n], "total": [s], "squares": [ss]})

    return events.groupBy("node").applyInPandasWithState(update, "node int, n double, total double, squares double", "n double, s double, ss double", "update", "NoTimeout")
