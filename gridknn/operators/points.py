"""Point tables: queries (pid, q0..), training points (tid, t0.., cls)."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PointSpec:
    """Which columns of a table are the id, the coordinates and the class."""

    id: str
    coords: tuple[str, ...]
    cls: str | None = None


def canonical(df: DataFrame, spec: PointSpec) -> DataFrame:
    """pid, x0.., cls with coordinates as doubles."""
    cls = F.col(spec.cls).cast("string") if spec.cls else F.lit(None).cast("string")
    return df.select(F.col(spec.id).cast("long").alias("pid"), *[F.col(c).cast("double").alias(f"x{i}") for i, c in enumerate(spec.coords)], cls.alias("cls"))


def from_arrays(df: DataFrame, d: int, id: str = "pid", coords: str = "coords", cls: str | None = "cls") -> DataFrame:
    """pid, x0.., cls from an array column; rows of another length get null coordinates, which validate() sets apart."""
    fits = F.size(coords) == d
    label = F.col(cls).cast("string") if cls else F.lit(None).cast("string")
    return df.select(F.col(id).cast("long").alias("pid"), *[F.when(fits, F.get(coords, F.lit(i)).cast("double")).alias(f"x{i}") for i in range(d)], label.alias("cls"))


def _sound(d: int) -> Column:
    each = [F.col(f"x{i}").isNotNull() & ~F.isnan(f"x{i}") & (F.abs(f"x{i}") < F.lit(float("inf"))) for i in range(d)]
    return F.coalesce(reduce(lambda a, b: a & b, each), F.lit(False)) & F.col("pid").isNotNull()


def validate(points: DataFrame, d: int) -> tuple[DataFrame, DataFrame]:
    """Sound points, and those with a null, NaN or infinite coordinate or a null id, never silently dropped."""
    return points.filter(_sound(d)), points.filter(~_sound(d))


def normalise(points: DataFrame, lo: Sequence[float], hi: Sequence[float]) -> DataFrame:
    """Each axis to [0, 1]; a flat axis to 0."""
    scaled = {f"x{i}": (F.col(f"x{i}") - a) / (b - a) if b > a else F.lit(0.0) for i, (a, b) in enumerate(zip(lo, hi, strict=True))}
    return points.withColumns(scaled)


def as_train(points: DataFrame, d: int) -> DataFrame:
    return points.select(F.col("pid").alias("tid"), *[F.col(f"x{i}").alias(f"t{i}") for i in range(d)], "cls")


def as_query(points: DataFrame, d: int) -> DataFrame:
    return points.select("pid", *[F.col(f"x{i}").alias(f"q{i}") for i in range(d)])


def split(points: DataFrame, d: int, tenth: int = 0, query_includes_train: bool = False) -> tuple[DataFrame, DataFrame]:
    """(train, query): a reproducible tenth trains, the rest (or all) are queries."""
    chosen = F.pmod("pid", F.lit(10)) == tenth
    return as_train(points.filter(chosen), d), as_query(points if query_includes_train else points.filter(~chosen), d)


def gathered(points: DataFrame, axes: Sequence[str], id: str, carried: Sequence[str], name: str, most: int = 1024) -> DataFrame:
    """One row for the points at one place: the axes, and an array `name` of structs of the carried columns.

    An array has at most `most` points; a place of more has several rows.
    """
    part = F.floor((F.row_number().over(Window.partitionBy(*axes).orderBy(id)) - 1) / most)
    return points.withColumn("part", part).groupBy(*axes, "part").agg(F.collect_list(F.struct(*carried)).alias(name)).drop("part")


def places(query: DataFrame, d: int) -> DataFrame:
    """pid, q0.., copies: one row for the queries at one place, with the smallest of their ids and their number."""
    axes = [f"q{i}" for i in range(d)]
    return query.groupBy(*axes).agg(F.min("pid").alias("pid"), F.count("*").alias("copies")).select("pid", *axes, "copies")


def at_places(found: DataFrame, seen: DataFrame, query: DataFrame, d: int) -> DataFrame:
    """found (pid of a place, ...) for each query at that place; seen: places(query)."""
    axes = [f"q{i}" for i in range(d)]
    placed = found.join(seen.select("pid", *[F.col(c).alias(f"at_{c}") for c in axes]), "pid").drop("pid")
    same = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"at_{c}")) for c in axes])
    return query.select("pid", *axes).join(placed, same).drop(*axes, *[f"at_{c}" for c in axes])


def fraction(points: DataFrame, f: float) -> DataFrame:
    """The part F of the points that the scalability workload runs on."""
    return points.filter(F.pmod("pid", F.lit(100)) < round(100 * f))


def banded(x: Column, cuts: Sequence[float], names: Sequence[str]) -> Column:
    """Classes from a coordinate: names[i] below cuts[i], the last name from the last cut on."""
    out = F.lit(names[-1])
    for c, n in reversed(list(zip(cuts, names, strict=False))):
        out = F.when(x < c, n).otherwise(out)
    return out
