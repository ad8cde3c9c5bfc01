"""Points and results in files: parquet, delimited text, JSON, and tables clustered by cell."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.grid import GridSpec
from ..operators.points import PointSpec, canonical


def read_parquet(spark: SparkSession, path: str, spec: PointSpec) -> DataFrame:
    """pid, x0.., cls; only the named columns are read."""
    return canonical(spark.read.parquet(path), spec)


def read_text(spark: SparkSession, path: str, d: int, sep: str = ",", has_class: bool = True) -> DataFrame:
    """pid, x0.., cls from lines `id, coordinates, class`; what isn't a number becomes null, for validate() to set apart."""
    f = F.split("value", sep)
    cls = F.trim(F.get(f, F.lit(d + 1))) if has_class else F.lit(None).cast("string")
    number = lambda i, kind: F.trim(F.get(f, F.lit(i))).try_cast(kind)
    return spark.read.text(path).select(number(0, "long").alias("pid"), *[number(i + 1, "double").alias(f"x{i}") for i in range(d)], cls.alias("cls"))


def read_json(spark: SparkSession, path: str, spec: PointSpec) -> DataFrame:
    """pid, x0.., cls from JSON lines with the spec's fields."""
    kinds = [(spec.id, "long"), *((c, "double") for c in spec.coords), *([(spec.cls, "string")] if spec.cls else [])]
    return canonical(spark.read.schema(", ".join(f"`{n}` {t}" for n, t in kinds)).json(path), spec)


def as_text(lists: DataFrame, sep: str = ",") -> DataFrame:
    """value: one line for each query, pid and its neighbours as tid:dist:cls."""
    one = F.transform("nn", lambda x: F.concat_ws(":", x["tid"].cast("string"), x["dist"].cast("string"), x["cls"]))
    return lists.select(F.concat_ws(sep, F.col("pid").cast("string"), F.array_join(one, sep)).alias("value"))


def write(df: DataFrame, path: str, form: str = "parquet", mode: str = "overwrite", partition_by: Sequence[str] = ()) -> None:
    """Results as parquet, json, csv or text (of as_text)."""
    if form not in ("parquet", "json", "csv", "text"):
        raise ValueError(f"unknown form {form}")
    writer = df.write.mode(mode).format(form)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_clustered(train: DataFrame, grid: GridSpec, path: str, partitions: int | None = None) -> None:
    """Training points sorted by cell code, so that a reader's filter on cell skips row groups."""
    placed = grid.assign(train, "t")
    dealt = placed.repartitionByRange(partitions, "cell") if partitions else placed.repartitionByRange("cell")
    dealt.sortWithinPartitions("cell").write.mode("overwrite").parquet(path)


def write_bucketed(train: DataFrame, grid: GridSpec, table: str, buckets: int) -> None:
    """Training points as a table bucketed by cell: joins on cell need no shuffle of it."""
    grid.assign(train, "t").write.mode("overwrite").bucketBy(buckets, "cell").sortBy("cell").saveAsTable(table)
