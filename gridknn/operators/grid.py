"""Grids over the target space: equal or equal-count slices along each axis.

A cell has one index for each axis. Codes of power-of-two grids interleave the indices' bits,
so that a shift by d bits gives the enclosing cell one level up; other grids number cells in
mixed radix. Points outside the box belong to the border cells.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridSpec:
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    splits: tuple[int, ...]
    cuts: tuple[tuple[float, ...], ...] = field(default=())

    def __post_init__(self):
        if not len(self.lo) == len(self.hi) == len(self.splits) or any(m < 1 for m in self.splits):
            raise ValueError("lo, hi and splits need one entry for each axis, splits at least 1")
        if sum(max(1, (m - 1).bit_length()) for m in self.splits) > 62:
            raise ValueError("a cell code has more than 62 bits: use fewer slices or brute force")

    @classmethod
    def equal(cls, splits: Sequence[int], lo: Sequence[float] | None = None, hi: Sequence[float] | None = None) -> GridSpec:
        d = len(splits)
        return cls(tuple(lo or [0.0] * d), tuple(hi or [1.0] * d), tuple(splits))

    @classmethod
    def pow2(cls, d: int, n: int, lo: Sequence[float] | None = None, hi: Sequence[float] | None = None) -> GridSpec:
        return cls.equal([1 << n] * d, lo, hi)

    @classmethod
    def quantile(cls, train: DataFrame, splits: Sequence[int], prefix: str = "t", accuracy: int = 10_000) -> GridSpec:
        """Slices that hold about as many training points each; cut points come from one aggregate."""
        axes = [f"{prefix}{i}" for i in range(len(splits))]
        aggs = [F.percentile_approx(c, [j / m for j in range(1, m)] or [0.5], accuracy).alias(c) for c, m in zip(axes, splits, strict=True)]
        row = train.agg(*aggs, *[F.min(c).alias("lo" + c) for c in axes], *[F.max(c).alias("hi" + c) for c in axes]).first()
        cuts = tuple(tuple(sorted(set(row[c] or []))) if m > 1 else () for c, m in zip(axes, splits, strict=True))
        return cls(tuple(row["lo" + c] or 0.0 for c in axes), tuple(row["hi" + c] or 0.0 for c in axes), tuple(len(c) + 1 for c in cuts), cuts)

    @property
    def d(self) -> int:
        return len(self.splits)

    @property
    def levels(self) -> int:
        """How often all axes can be halved until one cell is left."""
        return max((m - 1).bit_length() for m in self.splits)

    @property
    def is_pow2(self) -> bool:
        return not self.cuts and len(set(self.splits)) == 1 and self.splits[0] & (self.splits[0] - 1) == 0

    @property
    def total_cells(self) -> int:
        return math.prod(self.splits)

    def width(self) -> float:
        """The narrowest mean slice width that isn't zero."""
        widths = [(b - a) / m for a, b, m in zip(self.lo, self.hi, self.splits, strict=True)]
        return min((w for w in widths if w > 0), default=1.0)

    def index(self, axis: int, x: Column) -> Column:
        """Slice number of a coordinate; rises with the coordinate and stays inside the grid."""
        m, lo, hi = self.splits[axis], self.lo[axis], self.hi[axis]
        if self.cuts:
            return F.size(F.filter(F.array(*[F.lit(c) for c in self.cuts[axis]]), lambda c: c <= x)) if self.cuts[axis] else F.lit(0)
        if hi <= lo:
            return F.lit(0)
        return F.least(F.greatest(F.floor((x - lo) * m / (hi - lo)), F.lit(0)), F.lit(m - 1)).cast("int")

    def walls(self, axis: int, index: Column) -> tuple[Column, Column]:
        """Where a slice begins and ends."""
        lo, hi, m = self.lo[axis], self.hi[axis], self.splits[axis]
        if self.cuts:
            edges = F.array(*[F.lit(float(c)) for c in (lo, *self.cuts[axis], hi)])
            return F.element_at(edges, index + 1), F.element_at(edges, index + 2)
        step = (hi - lo) / m
        return lo + index * F.lit(step), lo + (index + 1) * F.lit(step)

    def code(self, index: Sequence[Column], up: int | Column = 0) -> Column:
        """One bigint for the cell, or for its ancestor `up` levels above."""
        if self.is_pow2:
            bits = (self.splits[0] - 1).bit_length()
            code = F.lit(0).cast("long")
            for axis, i in enumerate(index):
                for b in range(bits):
                    code = code.bitwiseOR(F.shiftleft(F.shiftright(i, b).bitwiseAND(1).cast("long"), b * self.d + axis))
            return code if isinstance(up, int) and up == 0 else F.call_function("shiftright", code, (F.lit(up) if isinstance(up, int) else up) * self.d)
        code = F.lit(0).cast("long")
        for i, m in zip(index, self.splits, strict=True):
            step = i if isinstance(up, int) and up == 0 else F.call_function("shiftright", i, F.lit(up) if isinstance(up, int) else up)
            code = code * m + step
        return code

    def assign(self, points: DataFrame, prefix: str) -> DataFrame:
        """points with the column cell."""
        return points.withColumn("cell", self.code([self.index(i, F.col(f"{prefix}{i}")) for i in range(self.d)]))


def bounds(train: DataFrame, query: DataFrame, d: int) -> tuple[tuple[float, ...], tuple[float, ...]]:
    """Corners of the box around both tables: 2 d numbers from one aggregate."""
    rows = train.select([F.col(f"t{i}").alias(f"x{i}") for i in range(d)]).unionByName(query.select([F.col(f"q{i}").alias(f"x{i}") for i in range(d)]))
    row = rows.agg(*[f(f"x{i}").alias(f"{n}{i}") for i in range(d) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return tuple(row[f"lo{i}"] or 0.0 for i in range(d)), tuple(row[f"hi{i}"] or 0.0 for i in range(d))


def suggest(n_train: int, d: int, per_cell: float = 8.0, lo: Sequence[float] | None = None, hi: Sequence[float] | None = None) -> GridSpec | None:
    """A power-of-two grid of about per_cell training points a cell; None where brute force is the better choice."""
    if d >= 8 or n_train < 4 * per_cell:
        return None
    return GridSpec.pow2(d, min(60 // d, max(1, round(math.log2(n_train / per_cell) / d))), lo, hi)
