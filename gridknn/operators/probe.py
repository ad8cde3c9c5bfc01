"""Balls around queries: how far they must reach, and which occupied cells they touch."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import metric, touches
from .density import pyramid
from .grid import GridSpec

STEPS = ("half_cell", "cell", "double", "continuous")


def _box(prefix: str, d: int) -> list[Column]:
    return [F.col(f"{prefix}{i}") for i in range(d)]


def overlapped(balls: DataFrame, counts: DataFrame, grid: GridSpec, which: str = "euclidean", beyond: str | None = None) -> DataFrame:
    """balls (pid, q0.., r, ...) times the occupied cells they touch: cell, n, near (its nearest distance).

    Index ranges of the ball along each axis are exploded and equi-joined with the counts, at
    the pyramid level whose cells are about as wide as the ball, so that a wide ball doesn't
    name every base cell. beyond: a column; only cells farther than it.
    """
    d = grid.d
    q = _box("q", d)
    low = [grid.index(i, q[i] - F.col("r") * (1 + 1e-9) - 1e-12) for i in range(d)]
    high = [grid.index(i, q[i] + F.col("r") * (1 + 1e-9) + 1e-12) for i in range(d)]
    ranged = balls.withColumns({f"a{i}": low[i] for i in range(d)} | {f"b{i}": high[i] for i in range(d)})
    # the level at which no axis has more than four indices in range
    span = F.greatest(*[F.col(f"b{i}") - F.col(f"a{i}") for i in range(d)], F.lit(0))
    up = F.when(span < 4, 0).otherwise(F.least(F.ceil(F.log2((span + 1) / 3)), F.lit(grid.levels))).cast("int")
    ranged = ranged.withColumn("up", up)
    for i in range(d):
        a, b = F.call_function("shiftright", F.col(f"a{i}"), F.col("up")), F.call_function("shiftright", F.col(f"b{i}"), F.col("up"))
        ranged = ranged.withColumn(f"k{i}", F.explode(F.sequence(a, b))).drop(f"a{i}", f"b{i}")
    keyed = ranged.withColumn("node", _node([F.col(f"k{i}") for i in range(d)], grid)).drop(*[f"k{i}" for i in range(d)])
    raised = counts.select(F.explode(F.sequence(F.lit(0), F.lit(grid.levels))).alias("up"), "*")
    raised = raised.withColumn("node", _node([F.call_function("shiftright", F.col(f"idx{i}"), F.col("up")) for i in range(d)], grid)).drop(*[f"idx{i}" for i in range(d)])
    hit = keyed.drop("cell").join(raised, ["up", "node"])
    near = metric(which).box_min(q, _box("lo", d), _box("hi", d))
    hit = hit.withColumn("near", near).filter(touches(F.col("near"), F.col("r")))
    if beyond:
        hit = hit.filter(F.col("near") > F.col(beyond))
    return hit.drop("up", "node")


def _node(index: list[Column], grid: GridSpec) -> Column:
    code = F.lit(0).cast("long")
    for i, m in zip(index, grid.splits, strict=True):
        code = code * m + i
    return code


def safe_radius(short: DataFrame, counts: DataFrame, grid: GridSpec, k: int, which: str = "euclidean") -> DataFrame:
    """short (pid, q0.., cell, ...) with far: a radius whose ball surely holds k training points (all, if there are fewer).

    For each query cell the pyramid is searched for the lowest level where the cell's ancestor
    and its neighbours hold k points; far is the farthest distance to their joint box. Levels
    and neighbours are bounded in number, and everything is equi-joined: no loop, no broadcast
    that grows with the data.
    """
    d = grid.d
    q = _box("q", d)
    index = {f"idx{i}": grid.index(i, q[i]) for i in range(d)}
    placed = short.withColumns(index)
    cells = placed.select(*index).distinct().withColumn("up", F.explode(F.sequence(F.lit(0), F.lit(grid.levels))))
    offsets = F.array(*[F.struct(*[F.lit(o).alias(f"o{i}") for i, o in enumerate(off)]) for off in itertools.product((-1, 0, 1), repeat=d)])
    around = cells.withColumn("o", F.explode(offsets))
    inside = F.lit(True)
    for i, m in enumerate(grid.splits):
        around = around.withColumn(f"k{i}", F.call_function("shiftright", F.col(f"idx{i}"), F.col("up")) + F.col(f"o.o{i}"))
        inside = inside & F.col(f"k{i}").between(F.lit(0), F.call_function("shiftright", F.lit(m - 1), F.col("up")))
    around = around.filter(inside).withColumn("node", _node([F.col(f"k{i}") for i in range(d)], grid))
    levels = pyramid_nodes(counts, grid)
    boxes = [f(f"{n}{i}").alias(f"{n}{i}") for i in range(d) for n, f in (("lo", F.min), ("hi", F.max))]
    blocks = around.join(levels, ["up", "node"]).groupBy(*index, "up").agg(F.sum("n").alias("held"), *boxes)
    enough = blocks.filter((F.col("held") >= k) | (F.col("up") == grid.levels))
    first = Window.partitionBy(*index).orderBy("up")
    block = enough.withColumn("rank", F.row_number().over(first)).filter("rank = 1").drop("rank", "up", "held")
    far = metric(which).box_max(q, _box("lo", d), _box("hi", d))
    joined = placed.join(block, list(index), "left").withColumn("far", F.coalesce(far, F.lit(0.0)))
    return joined.drop(*index, *[f"{n}{i}" for i in range(d) for n in ("lo", "hi")])


def pyramid_nodes(counts: DataFrame, grid: GridSpec) -> DataFrame:
    d = grid.d
    raised = counts.select(F.explode(F.sequence(F.lit(0), F.lit(grid.levels))).alias("up"), "*")
    node = _node([F.call_function("shiftright", F.col(f"idx{i}"), F.col("up")) for i in range(d)], grid)
    boxes = [f(f"{n}{i}").alias(f"{n}{i}") for i in range(d) for n, f in (("lo", F.min), ("hi", F.max))]
    return raised.groupBy("up", node.alias("node")).agg(F.sum("n").alias("n"), *boxes)


def reach(short: DataFrame, counts: DataFrame, grid: GridSpec, k: int, which: str = "euclidean", contain: bool = False) -> DataFrame:
    """short with `need`: the least distance at which the touched (or wholly contained) cells hold k points.

    short carries far from safe_radius; no cell beyond it can matter.
    """
    d = grid.d
    balls = short.withColumn("r", F.col("far"))
    cells = overlapped(balls, counts, grid, which)
    order = metric(which).box_max(_box("q", d), _box("lo", d), _box("hi", d)) if contain else F.col("near")
    running = Window.partitionBy("pid").orderBy("at").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    summed = cells.select("pid", order.alias("at"), "n").withColumn("held", F.sum("n").over(running))
    need = summed.groupBy("pid").agg(F.coalesce(F.min(F.when(F.col("held") >= k, F.col("at"))), F.max("at")).alias("need"))
    return short.join(need, "pid", "left").withColumn("need", F.coalesce("need", "far"))


def stepped(r0: Column, need: Column, grid: GridSpec, step: str = "half_cell") -> tuple[Column, Column]:
    """The grown radius and the number of growths, for a start r0 and the distance needed."""
    if step not in STEPS:
        raise ValueError(f"unknown step {step}")
    missing = F.greatest(F.lit(0.0), need - r0)
    if step == "continuous":
        return F.greatest(r0, need), (missing > 0).cast("long")
    if step == "double":
        times = F.when(missing > 0, F.ceil(F.log2(need / r0))).otherwise(0)
        return r0 * F.pow(F.lit(2.0), times), times.cast("long")
    s = grid.width() / (2 if step == "half_cell" else 1)
    times = F.ceil(missing / s)
    return r0 + s * times, times.cast("long")


__all__ = ["STEPS", "overlapped", "pyramid", "pyramid_nodes", "reach", "safe_radius", "stepped"]
