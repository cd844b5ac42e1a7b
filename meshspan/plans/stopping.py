"""When to stop; rules are combined with ``|``. A rule sees one step's figures."""

from __future__ import annotations

import dataclasses
from collections.abc import Callable


@dataclasses.dataclass(frozen=True)
class Step:
    t: int
    inner_total: int
    change: float = float("inf")
    residual: float = float("inf")
    disagreement: float = float("inf")
    error: float = float("inf")
    sends: float = 0.0


@dataclasses.dataclass(frozen=True)
class Stop:
    test: Callable[[Step], bool]

    def __or__(self, other: Stop) -> Stop:
        return Stop(lambda s: self.test(s) or other.test(s))

    def __call__(self, step: Step) -> bool:
        return self.test(step)


def max_outer(n: int) -> Stop:
    return Stop(lambda s: s.t + 1 >= n)


def subspace_change(tolerance: float) -> Stop:
    return Stop(lambda s: s.change < tolerance)


def rayleigh_residual(tolerance: float) -> Stop:
    return Stop(lambda s: s.residual < tolerance)


def disagreement(tolerance: float) -> Stop:
    return Stop(lambda s: s.disagreement < tolerance)


def error_below(tolerance: float) -> Stop:
    return Stop(lambda s: s.error < tolerance)


def message_budget(per_node: float) -> Stop:
    return Stop(lambda s: s.sends >= per_node)
