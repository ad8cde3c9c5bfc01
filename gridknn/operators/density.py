"""How the training points are spread over the cells; computed once for a training set."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .grid import GridSpec


def cell_counts(train: DataFrame, grid: GridSpec) -> DataFrame:
    """cell, idx0.., n, and the tight box lo0.., hi0.. of its points; occupied cells only.

    The tight box holds even where points lie outside the grid's box, and prunes better than
    the cell's own walls.
    """
    axes = range(grid.d)
    placed = train.select(*[F.col(f"t{i}") for i in axes], *[grid.index(i, F.col(f"t{i}")).alias(f"idx{i}") for i in axes])
    boxes = [f(f"t{i}").alias(f"{n}{i}") for i in axes for n, f in (("lo", F.min), ("hi", F.max))]
    counts = placed.groupBy(*[f"idx{i}" for i in axes]).agg(F.count("*").alias("n"), *boxes)
    return counts.select(grid.code([F.col(f"idx{i}") for i in axes]).alias("cell"), "*")


def with_walls(counts: DataFrame, grid: GridSpec) -> DataFrame:
    """counts with the cells' own walls in place of the tight boxes; border cells reach out to their points."""
    boxes = {}
    for i in range(grid.d):
        low, high = grid.walls(i, F.col(f"idx{i}"))
        boxes |= {f"lo{i}": F.least(f"lo{i}", low), f"hi{i}": F.greatest(f"hi{i}", high)}
    return counts.withColumns(boxes)


def pyramid(counts: DataFrame, grid: GridSpec) -> DataFrame:
    """up, code, n and boxes of the occupied cells of every level, the root last."""
    axes = range(grid.d)
    raised = counts.select(F.explode(F.sequence(F.lit(0), F.lit(grid.levels))).alias("up"), "*")
    code = grid.code([F.col(f"idx{i}") for i in axes], F.col("up"))
    boxes = [f(f"{n}{i}").alias(f"{n}{i}") for i in axes for n, f in (("lo", F.min), ("hi", F.max))]
    return raised.groupBy("up", code.alias("code")).agg(F.sum("n").alias("n"), *boxes)


def merge_counts(old: DataFrame, new: DataFrame, grid: GridSpec) -> DataFrame:
    """Counts of two disjoint training sets: they add up, so appended data needs no recount."""
    axes = range(grid.d)
    boxes = [f(f"{n}{i}").alias(f"{n}{i}") for i in axes for n, f in (("lo", F.min), ("hi", F.max))]
    return old.unionByName(new).groupBy("cell", *[f"idx{i}" for i in axes]).agg(F.sum("n").alias("n"), *boxes)
