"""The methods for SQL users: views of results, and table and scalar functions."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from ..operators.grid import GridSpec
from .pipeline import all_knn, classify


class CellsInBall:
    """cells_in_ball(x, r, lo, hi, m): index vectors of the cells that the ball's bounding box meets."""

    def eval(self, x: list, r: float, lo: list, hi: list, m: list):
        ranges = []
        for v, a, b, n in zip(x, lo, hi, m):  # noqa: B905
            place = lambda y: min(max(int((y - a) * n // (b - a)), 0), n - 1) if b > a else 0  # noqa: B023, E731
            ranges.append(range(place(v - r), place(v + r) + 1))
        for index in itertools.product(*ranges):
            yield (list(index),)


def register(spark: SparkSession) -> None:
    """cells_in_ball as a table function; euclidean(a, b) of two arrays as a SQL function."""
    spark.udtf.register("cells_in_ball", udtf(CellsInBall, returnType="idx array<int>"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION euclidean(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v))")


def create_views(spark: SparkSession, query: DataFrame, train: DataFrame, k: int, grid: GridSpec, prefix: str = "knn", **options) -> None:
    """Views <prefix>_neighbours (pid, rank, tid, dist, cls) and <prefix>_classes (pid, cls_pred, votes, best_rank)."""
    all_knn(query, train, k, grid, **options).createOrReplaceTempView(f"{prefix}_neighbours")
    classify(query, train, k, grid, **options).createOrReplaceTempView(f"{prefix}_classes")


def lateral_knn(spark: SparkSession, query_view: str, train_view: str, d: int, k: int) -> DataFrame:
    """A readable statement of the search, for small views: each query with its k nearest by a lateral join."""
    dist = "sqrt(" + " + ".join(f"(q.q{i} - t.t{i}) * (q.q{i} - t.t{i})" for i in range(d)) + ")"
    return spark.sql(f"SELECT q.pid, n.tid, n.dist FROM {query_view} q, LATERAL (SELECT t.tid, {dist} AS dist FROM {train_view} t ORDER BY {dist}, t.tid LIMIT {int(k)}) n")
