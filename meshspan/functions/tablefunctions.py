"""Table functions and vector functions that SQL can call."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="src int, dst int")
class TopologyEdges:
    """topology_edges('ring', 20) or topology_edges('random:0.25', 20)"""

    def eval(self, spec: str, n: int):
        from meshspan.plans.workloads import graph_of

        yield from graph_of(spec.replace("random", "er"), n).edges


@udtf(returnType="t int, rounds int")
class ScheduleRows:
    """schedule_rows(slope, offset, cap, outer): rounds of each step, rounded down."""

    def eval(self, slope: float, offset: float, cap: int, outer: int):
        for t in range(outer):
            yield t, min(cap, int(slope * t + offset))


def register(spark: SparkSession) -> None:
    """Make the table functions and the vector functions known to SQL."""
    spark.udtf.register("topology_edges", TopologyEdges)
    spark.udtf.register("schedule_rows", ScheduleRows)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, v) -> s + v * v))")
