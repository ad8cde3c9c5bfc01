"""Neighbour operators for users: one point, all points, self, joins, ranges, cloaks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import metric
from ..plans import pipeline
from . import probe
from .density import cell_counts
from .grid import GridSpec
from .points import as_query, as_train, gathered


def knn(point: Sequence[float], train: DataFrame, k: int, which: str = "euclidean") -> DataFrame:
    """rank, tid, dist, cls of the k nearest to one point: a top-k sort, no shuffle of the table."""
    q = [F.lit(float(x)) for x in point]
    dist = metric(which).dist(q, [F.col(f"t{i}") for i in range(len(q))])
    nearest = train.select("tid", dist.alias("dist"), "cls").orderBy("dist", "tid").limit(k)
    return nearest.withColumn("rank", F.row_number().over(Window.orderBy("dist", "tid"))).select("rank", "tid", "dist", "cls")


def all_knn_self(points: DataFrame, d: int, k: int, grid: GridSpec | None, exclude_self: bool = True, **options) -> DataFrame:
    """Neighbours of every point (pid, x0.., cls) inside its own table."""
    return pipeline.all_knn(as_query(points, d), as_train(points, d), k, grid, exclude_self=exclude_self, **options)


def knn_join(left: DataFrame, right: DataFrame, left_id: str, right_id: str, on: Sequence[tuple[str, str]], k: int, grid: GridSpec | None, **options) -> DataFrame:
    """Rows of left with their k nearest rows of right: columns l_*, r_*, rank, dist."""
    q = left.select(F.col(left_id).cast("long").alias("pid"), *[F.col(a).cast("double").alias(f"q{i}") for i, (a, _) in enumerate(on)])
    t = right.select(F.col(right_id).cast("long").alias("tid"), *[F.col(b).cast("double").alias(f"t{i}") for i, (_, b) in enumerate(on)], F.lit(None).cast("string").alias("cls"))
    found = pipeline.all_knn(q, t, k, grid, **options).select("pid", "tid", "rank", "dist")
    named_left = left.select([F.col(c).alias(f"l_{c}") for c in left.columns])
    named_right = right.select([F.col(c).alias(f"r_{c}") for c in right.columns])
    return found.join(named_left, F.col("pid") == F.col(f"l_{left_id}")).join(named_right, F.col("tid") == F.col(f"r_{right_id}")).drop("pid", "tid")


def within(query: DataFrame, train: DataFrame, radius: float, grid: GridSpec, which: str = "euclidean") -> DataFrame:
    """pid, tid, dist of all pairs no farther than radius: an equi-join on touched cells with a residual test.

    Places are joined, not points: those at one place go with it, and are paired only as rows leave.
    """
    d = grid.d
    q, t = [f"q{i}" for i in range(d)], [f"t{i}" for i in range(d)]
    balls = gathered(query, q, "pid", ["pid"], "ps").withColumn("r", F.lit(float(radius)))
    train = grid.assign(train, "t")
    cells = probe.overlapped(balls.withColumn("cell", F.lit(0).cast("long")), cell_counts(train, grid), grid, which)
    dist = metric(which).dist([F.col(c) for c in q], [F.col(c) for c in t])
    places = grid.assign(gathered(train, t, "tid", ["tid", "cls"], "ts"), "t")
    pairs = cells.select("ps", *q, "cell").join(places, "cell").withColumn("dist", dist).filter(F.col("dist") <= radius)
    return pairs.select(F.explode("ps").alias("p"), "ts", "dist").select("p.pid", F.explode("ts").alias("t"), "dist").select("pid", "t.tid", "dist", "t.cls")


def cloak(points: DataFrame, d: int, k: int, grid: GridSpec, **options) -> DataFrame:
    """pid, lo0.., hi0..: the box around each user and the k nearest others, all that a server would see."""
    near = all_knn_self(points, d, k, grid, **options).select("pid", "tid")
    members = near.unionByName(points.select("pid", F.col("pid").alias("tid")))
    placed = members.join(points.select(F.col("pid").alias("tid"), *[f"x{i}" for i in range(d)]), "tid")
    return placed.groupBy("pid").agg(*[f(f"x{i}").alias(f"{n}{i}") for i in range(d) for n, f in (("lo", F.min), ("hi", F.max))])


def nearest_1d(query: DataFrame, train: DataFrame, slices: int = 64) -> DataFrame:
    """pid, tid, dist: the nearest training point on a line, by two-sided as-of scans of sorted slices.

    Slices are cut at equal counts; the last point before and the first point after each slice
    travel as one row per slice, so the scans need no single sorted partition.
    """
    grid = GridSpec.quantile(train, [slices])
    t = train.select(grid.index(0, F.col("t0")).alias("slice"), F.col("t0").alias("x"), "tid", F.lit(None).cast("long").alias("pid"))
    q = query.select(grid.index(0, F.col("q0")).alias("slice"), F.col("q0").alias("x"), F.lit(None).cast("long").alias("tid"), "pid")
    ends = t.groupBy("slice").agg(F.min(F.struct("x", "tid")).alias("first"), F.max(F.struct("x", (-F.col("tid")).alias("m"))).alias("last"))
    by_slice = Window.orderBy("slice")
    bounds = F.broadcast(ends_filled(ends, by_slice, grid.splits[0]))
    every = t.unionByName(q)
    back = Window.partitionBy("slice").orderBy("x", F.col("tid").desc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    # backwards: a frame that ends with the partition would be gone through anew for each row
    ahead = Window.partitionBy("slice").orderBy(F.col("x").desc(), F.col("pid").isNull().desc(), F.col("tid").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    point = F.when(F.col("tid").isNotNull(), F.struct("x", "tid"))
    seen = every.withColumn("before", F.last(point, True).over(back)).withColumn("after", F.last(point, True).over(ahead)).filter("pid is not null").join(bounds, "slice", "left")
    sides = [F.coalesce("before", "left"), F.coalesce("after", "right")]
    hit = lambda c: F.when(c.isNotNull(), F.struct(F.abs(F.col("x") - c["x"]).alias("dist"), c["tid"].alias("tid")))
    best = F.array_min(F.array_compact(F.array(*[hit(c) for c in sides])))
    return seen.withColumn("b", best).select("pid", "b.tid", "b.dist")


def ends_filled(ends: DataFrame, by_slice, n: int) -> DataFrame:
    """For each of the n slices the last point of earlier ones and the first of later ones."""
    whole = ends.sparkSession.range(n).select(F.col("id").cast("int").alias("slice")).join(ends, "slice", "left")
    back, ahead = by_slice.rowsBetween(Window.unboundedPreceding, -1), by_slice.rowsBetween(1, Window.unboundedFollowing)
    last = F.last("last", True).over(back)
    return whole.select("slice", F.when(last.isNotNull(), F.struct(last["x"].alias("x"), (-last["m"]).alias("tid"))).alias("left"), F.first("first", True).over(ahead).alias("right"))


__all__ = ["all_knn_self", "cloak", "knn", "knn_join", "nearest_1d", "within"]
