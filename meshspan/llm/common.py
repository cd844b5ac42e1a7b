"""Helpers shared by the training-data operators: tables, scratch storage, components."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.sources.tables import load_table as table
from meshspan.sources.tables import scratch_dir, stored

__all__ = ["WORD_PATTERN", "connected_components", "scratch_dir", "shuffle_partitions", "stored", "table"]

#: White space of the word contracts: space and U+0009 to U+000D. Everything else is part of a word.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Components of an undirected graph given as ``edges(src BIGINT, dst BIGINT)``.

    Returns ``(node, component)`` for every node that has an edge; ``component`` is the smallest
    node id that is reachable, ids in signed order. Alternates two contractions: every node hands
    its larger neighbours to its smallest neighbour, then its smaller ones, until nothing moves.
    Minima are pre-aggregated, and joined back from a stored table, so that adaptive execution can
    split a node with very many neighbours. Null ids and loops are ignored; repeated edges are
    merged; no edges give no rows. The round bound is far above what any chain needs (rounds grow
    with the logarithm of the length), and passing it raises an error.
    """
    current = stored(
        edges.where("src <> dst")
        .select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b"))
        .distinct(),
        "edges",
    )
    state = None
    for _ in range(max_rounds):
        both = current.select("a", "b").union(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        lowest = stored(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m")), "lowest")
        large = (
            both.join(lowest, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        )
        large = stored(large.where("a <> b"), "large")
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        floor = stored(down.groupBy("a").agg(F.min("b").alias("m")), "floor")
        current = stored(
            down.join(floor, "a")
            .select(F.col("b").alias("a"), F.col("m").alias("b"))
            .union(floor.select("a", F.col("m").alias("b")))
            .where("a <> b")
            .distinct(),
            "edges",
        )
        seen = current.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(seen) == state:
            break
        state = tuple(seen)
    else:
        raise RuntimeError("components did not settle")
    roots = current.select(F.col("b").alias("node")).distinct()
    return current.select(F.col("a").alias("node"), F.col("b").alias("component")).union(
        roots.select("node", F.col("node").alias("component"))
    )
