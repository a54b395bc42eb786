"""Node programs: what an edge hands on, how values meet, and what counts as better."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Program:
    """``extend(value, w)`` along an edge; ``least``: smaller values win, else larger; ``weighted``: whether w is read.

    ``aggregate``: how the values that reach a node meet, where that is no choice of the better one; such programs run in
    rounds of whole gathers (``engine.gather``).
    """

    name: str
    extend: Callable[[Column, Column], Column]
    least: bool = True
    weighted: bool = True
    #: Whether a node's edges may be cut into parts: what the parts give, put together, is what the whole gives.
    distributive: bool = True
    aggregate: Callable[[Column], Column] | None = None

    def combine(self, value: Column) -> Column:
        if self.aggregate:
            return self.aggregate(value)
        return F.min(value) if self.least else F.max(value)

    def better(self, new: Column, old: Column) -> Column:
        return new < old if self.least else new > old


def _middle(value: Column) -> Column:
    return F.percentile(value, F.lit(0.5))


BFS = Program("bfs", lambda d, w: d + 1, weighted=False)
SSSP = Program("sssp", lambda d, w: d + w)
COMPONENTS = Program("components", lambda d, w: d, weighted=False)
WIDEST = Program("widest", lambda d, w: F.least(d, w), least=False)
#: Sums of what the edges carry: parts may be summed first.
WEIGHTED_SUM = Program("weighted_sum", lambda d, w: d * w, aggregate=F.sum)
#: Needs all of a node's values at once, so only whole nodes may run it.
NEIGHBOUR_MEDIAN = Program("neighbour_median", lambda d, w: d, weighted=False, distributive=False, aggregate=_middle)


def violated(extend: Callable[[Column, Column], Column], combine: Callable[[Column, Column], Column], a: Column, b: Column, w: Column) -> Column:
    """Whether handing on the better of two values is not the better of both handed on."""
    return extend(combine(a, b), w) != combine(extend(a, w), extend(b, w))


def require_distributive(program: Program, strategy: str) -> None:
    if not program.distributive and strategy != "BS":
        raise ValueError(f"{program.name} is not distributive: {strategy} cuts a node's edges into parts; use BS")
