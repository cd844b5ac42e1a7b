"""How many averaging rounds each outer step takes. Steps count from 0."""

from __future__ import annotations

import dataclasses
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclasses.dataclass(frozen=True)
class Fixed:
    rounds: int = 50

    def at(self, t: int) -> int:
        return self.rounds

    @property
    def name(self) -> str:
        return f"{self.rounds}"


@dataclasses.dataclass(frozen=True)
class Ramp:
    """min(slope * t + offset, cap), rounded up or down."""

    slope: float
    offset: float = 1
    cap: int = 50
    rounding: str = "ceil"

    def at(self, t: int) -> int:
        return min(self.cap, (math.ceil if self.rounding == "ceil" else math.floor)(self.slope * t + self.offset))

    @property
    def name(self) -> str:
        return f"min({self.slope:g}t+{self.offset:g},{self.cap})" + ("" if self.slope == int(self.slope) else self.rounding)


@dataclasses.dataclass(frozen=True)
class Explicit:
    """A list of rounds; its last entry holds for later steps. Falling lists are an error."""

    rounds: tuple[int, ...]

    def __post_init__(self):
        if any(b < a for a, b in zip(self.rounds, self.rounds[1:], strict=False)):
            raise ValueError("rounds must not fall")

    def at(self, t: int) -> int:
        return self.rounds[min(t, len(self.rounds) - 1)]

    @property
    def name(self) -> str:
        return "explicit"


@dataclasses.dataclass(frozen=True)
class TheorySchedule:
    """Rounds that the convergence theory asks for, up to an unknown constant ``const``: from the norms
    of the node matrices (alpha: their sum, gamma: root of their squares' sum), beta (largest inverse of
    a central R factor), the mixing time and the aimed factor eps."""

    kind: str
    alpha: float
    beta: float
    gamma: float
    mixing_time: float
    outer: int
    rank: int
    nodes: int
    eps: float = 0.5
    const: float = 1.0

    def at(self, t: int) -> int:
        from meshspan.operators.theory import rounds_bound

        return max(1, math.ceil(rounds_bound(self, t)))

    @property
    def name(self) -> str:
        return f"theory-{self.kind}"


Schedule = Fixed | Ramp | Explicit | TheorySchedule

#: The rules of the experiments, by name.
RULES: dict[str, Schedule] = {
    "half_floor": Ramp(0.5, rounding="floor"), "half_ceil": Ramp(0.5), "t+1": Ramp(1), "2t+1": Ramp(2), "50": Fixed(50),
    "5t+1,200": Ramp(5, cap=200), "2t+1,100": Ramp(2, cap=100), "5t+1,100": Ramp(5, cap=100), "100": Fixed(100),
}


def rounds(schedule: Schedule, outer: int) -> list[int]:
    return [schedule.at(t) for t in range(outer)]


def schedule_table(spark: SparkSession, rules: dict[str, Schedule], outer: int, steps: DataFrame | None = None) -> DataFrame:
    """(rule, t, rounds, inner_total): inner_total runs up to and including the step. ``steps``: a table of the steps
    (t, and columns to keep), numbered below ``outer``; without it all of them."""
    if steps is None:
        steps = spark.range(outer).select(F.col("id").cast("int").alias("t"))
    more = [c for c in steps.columns if c != "t"]
    out = None
    for name, rule in rules.items():
        own = steps.withColumn("rule", F.lit(name)).withColumn("rounds", _expression(rule, outer))
        out = own if out is None else out.union(own)
    from pyspark.sql import Window

    return out.select("rule", "t", *more, "rounds", F.sum("rounds").over(Window.partitionBy("rule").orderBy("t")).alias("inner_total"))


def _expression(rule: Schedule, outer: int):
    if isinstance(rule, Fixed):
        return F.lit(rule.rounds).cast("long")
    if isinstance(rule, Ramp):
        value = F.col("t") * F.lit(float(rule.slope)) + F.lit(float(rule.offset))
        return F.least((F.ceil if rule.rounding == "ceil" else F.floor)(value), F.lit(rule.cap)).cast("long")
    return F.element_at(F.array(*[F.lit(n) for n in rounds(rule, outer)]), F.col("t") + 1).cast("long")
