"""What a run costs on a real network: messages, volumes, arithmetic, and time with stragglers."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.functions.vectors import md5_fraction
from meshspan.operators.topology import Topology


def p2p_cost(spark: SparkSession, topology: Topology, rounds: list[int]) -> DataFrame:
    """(node, degree, role, rounds_total, sends): a node sends to every neighbour once a round."""
    total = int(sum(rounds))
    hub = topology.kind == "star"
    rows = [(i, int(g), "centre" if hub and i == 0 else "edge" if hub else "node", total, int(g) * total) for i, g in enumerate(topology.degrees)]
    return spark.createDataFrame(rows, "node int, degree int, role string, rounds_total long, sends long")


def p2p_plan(edges: DataFrame, schedules: DataFrame) -> DataFrame:
    """The same from an edge table (graph, src, dst) and a schedule table (rule, t, rounds): messages per node
    and rule, and their mean over nodes, with a rollup over rules."""
    both = edges.select("graph", F.col("src").alias("node")).union(edges.select("graph", F.col("dst").alias("node")))
    degree = both.groupBy("graph", "node").agg(F.count("*").alias("degree"))
    totals = schedules.groupBy("rule").agg(F.sum("rounds").alias("rounds_total"))
    return degree.crossJoin(F.broadcast(totals)).withColumn("sends", F.col("degree") * F.col("rounds_total"))


def by_role(cost: DataFrame) -> DataFrame:
    return cost.groupBy("role").agg(F.count("*").alias("nodes"), F.avg("sends").alias("sends"))


def flop_model(method: str, n: int, d: int, r: int, nodes: int) -> float:
    """Arithmetic of one outer step at one node: row split multiplies a d x d matrix and orthonormalises;
    column split multiplies its columns twice and shares an r x r factor."""
    if method == "row":
        return d * d * r * nodes + r * r * d * nodes
    if method == "column":
        return n * d * r + r * r * math.log2(max(2, nodes)) + r * r * d / nodes
    raise ValueError(f"unknown method {method!r}")


def volume_model(method: str, topology: Topology, rounds: list[int], n: int, d: int, r: int, push_rounds: int = 50) -> float:
    """Numbers sent in all: d x r per message for row split; n x r for column split, and r x r in its QR."""
    sends = 2 * len(topology.edges)
    if method == "row":
        return float(sends * sum(rounds) * d * r)
    return float(sends * (sum(rounds) * n * r + len(rounds) * push_rounds * r * r))


def straggler_table(spark: SparkSession, rounds: list[int], nodes: int, delay: float = 0.01, base: float = 0.0, seed: int = 1, unit: str = "round") -> DataFrame:
    """(t, round, node, delay_s): one node, drawn by md5, is late in every round (or outer step)."""
    steps = spark.createDataFrame([(t, k) for t, k in enumerate(rounds)], "t int, k int")
    each = steps.select("t", F.explode(F.sequence(F.lit(1), F.col("k"))).alias("round"))
    late = F.floor(md5_fraction(F.lit(str(seed)), F.col("t").cast("string"), F.when(F.lit(unit == "round"), F.col("round").cast("string")).otherwise("-")) * nodes).cast("int")
    grid = each.withColumn("late", late).withColumn("node", F.explode(F.sequence(F.lit(0), F.lit(nodes - 1))))
    hit = (F.col("node") == F.col("late")) & (F.lit(unit == "round") | (F.col("round") == 1))
    return grid.select("t", "round", "node", (F.lit(base) + F.when(hit, delay).otherwise(0.0)).alias("delay_s"))


def loaded_table(work: DataFrame, rounds: list[int], delay: float) -> DataFrame:
    """(t, round, node, delay_s) from a table of the nodes' work (t, node, n): a node is late by ``delay`` for each of
    its ``n`` in every round of the step."""
    steps = work.sparkSession.createDataFrame([(t, k) for t, k in enumerate(rounds)], "t int, k int")
    each = work.join(F.broadcast(steps), "t").withColumn("round", F.explode(F.sequence(F.lit(1), F.col("k"))))
    return each.select("t", "round", "node", (F.col("n") * F.lit(delay)).alias("delay_s"))


def straggler_makespan(timing: DataFrame) -> DataFrame:
    """Synchronous time: the sum over rounds of the slowest node's delay."""
    return timing.groupBy("t", "round").agg(F.max("delay_s").alias("s")).agg(F.sum("s").alias("makespan_s"))
