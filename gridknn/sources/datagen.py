"""Generated point sets, uniform and power-law, for tests and scaling runs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.points import banded


def uniform(spark: SparkSession, n: int, d: int, seed: int = 42) -> DataFrame:
    """pid, x0.., cls; made where it is used, nothing is shipped."""
    axes = {f"x{i}": F.rand(seed + i) for i in range(d)}
    return spark.range(n).withColumnRenamed("id", "pid").withColumns(axes).withColumn("cls", banded(F.col("x0"), (1 / 3, 2 / 3), ("low", "mid", "high")))


def power_law(spark: SparkSession, n: int, d: int, seed: int = 42, power: int = 4) -> DataFrame:
    """The same with coordinates that are products of `power` uniform numbers: dense near the origin."""
    axis = lambda i: reduce(lambda a, b: a * b, [F.rand(seed + 97 * i + j) for j in range(power)])
    return spark.range(n).withColumnRenamed("id", "pid").withColumns({f"x{i}": axis(i) for i in range(d)}).withColumn("cls", banded(F.col("x0"), (0.01, 0.1), ("low", "mid", "high")))
