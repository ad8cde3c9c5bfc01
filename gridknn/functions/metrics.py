"""Distances between points, and the nearest and farthest distance from a point to a box."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Relative and absolute slack of overlap tests: a cell too many does no harm, one too few would.
SLACK, SLACK_ABS = 1e-9, 1e-12


class Metric:
    """A norm of per-axis differences, summed in axis order."""

    def __init__(self, name: str, p: float, combine: Callable[[Sequence[Column]], Column]):
        self.name, self.p, self.combine = name, p, combine

    def dist(self, a: Sequence[Column], b: Sequence[Column]) -> Column:
        return self.combine([x - y for x, y in zip(a, b, strict=True)])

    def box_min(self, x: Sequence[Column], lo: Sequence[Column], hi: Sequence[Column]) -> Column:
        return self.combine([F.greatest(a - v, F.lit(0.0), v - b) for v, a, b in zip(x, lo, hi, strict=True)])

    def box_max(self, x: Sequence[Column], lo: Sequence[Column], hi: Sequence[Column]) -> Column:
        return self.combine([F.greatest(F.abs(v - a), F.abs(v - b)) for v, a, b in zip(x, lo, hi, strict=True)])


def _sum(parts: Sequence[Column]) -> Column:
    return reduce(lambda a, b: a + b, parts)


def _greatest(parts: Sequence[Column]) -> Column:
    return parts[0] if len(parts) == 1 else F.greatest(*parts)


EUCLIDEAN = Metric("euclidean", 2, lambda d: F.sqrt(_sum([x * x for x in d])))
MANHATTAN = Metric("manhattan", 1, lambda d: _sum([F.abs(x) for x in d]))
CHEBYSHEV = Metric("chebyshev", float("inf"), lambda d: _greatest([F.abs(x) for x in d]))


def minkowski(p: float) -> Metric:
    return Metric(f"minkowski{float(p)!r}", float(p), lambda d: F.pow(_sum([F.pow(F.abs(x), F.lit(float(p))) for x in d]), F.lit(1.0 / p)))


def metric(which: str | Metric) -> Metric:
    if isinstance(which, Metric):
        return which
    named = {m.name: m for m in (EUCLIDEAN, MANHATTAN, CHEBYSHEV)}
    if which in named:
        return named[which]
    if which.startswith("minkowski") and float(which[9:]) >= 1:
        return minkowski(float(which[9:]))
    raise ValueError(f"unknown metric {which}")


def touches(nearest: Column, radius: Column) -> Column:
    """Whether a ball reaches a box at that distance, in doubt yes."""
    return nearest <= radius * (1 + SLACK) + SLACK_ABS
