"""The point sets that stand for the experiments' data, from the given tables.

Coordinates are normalised by constants, so every engine sees the same numbers.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.points import banded, split

BANDS, BAND_NAMES = (35.0, 115.0, 1000.0, 1500.0), ("A", "B", "C", "D", "E")


def _seconds(c: str) -> Column:
    return (F.hour(c) * 3600 + F.minute(c) * 60 + F.second(c)) / F.lit(86400.0)


_SKEW = (
    [None, lambda: F.col("value") / F.lit(1000.0), lambda: _seconds("ts"), lambda: F.regexp_extract("props", '"k": *([0-9]+)', 1).cast("double") / F.lit(100.0)],
    ["value / 1000.0::double", "(hour(ts) * 3600 + minute(ts) * 60 + second(ts)) / 86400.0::double", """regexp_extract(props, '"k": *([0-9]+)', 1)::double / 100.0::double"""],
)
_UNIF = (
    [None, lambda: (F.col("o_totalprice") - 1000.0) / F.lit(500000.0), lambda: F.date_diff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")) / F.lit(2405.0), lambda: F.pmod(F.col("o_custkey") * 7919, F.lit(1000)) / F.lit(1000.0)],
    ["(o_totalprice - 1000.0::double) / 500000.0::double", "date_diff('day', DATE '1995-01-01', o_orderdate::date) / 2405.0::double", "((o_custkey * 7919) % 1000) / 1000.0::double"],
)


@dataclass(frozen=True)
class Profile:
    """A point set: source table, id, coordinates as expressions and as SQL, class as both."""

    name: str
    table: str
    id: str
    d: int

    @property
    def kind(self) -> str:
        return self.name.rstrip("0123456789_")

    def coords(self) -> list[Column]:
        if self.kind == "skew":
            return [f() for f in _SKEW[0][1 : 1 + self.d]]
        if self.kind == "unif":
            return [f() for f in _UNIF[0][1 : 1 + self.d]]
        if self.kind == "part":
            return [(F.col("p_size") - 1) / F.lit(50.0), (F.col("p_retailprice") - 900.0) / F.lit(100.0)]
        if self.kind == "doc":
            return [F.col("n_chars") / F.lit(65536.0)]
        return [(F.col("embedding")[i].cast("double") + 1.0) / F.lit(2.0) for i in range(self.d)]

    def coords_sql(self) -> list[str]:
        if self.kind == "skew":
            return _SKEW[1][: self.d]
        if self.kind == "unif":
            return _UNIF[1][: self.d]
        if self.kind == "part":
            return ["(p_size - 1) / 50.0::double", "(p_retailprice - 900.0::double) / 100.0::double"]
        if self.kind == "doc":
            return ["n_chars / 65536.0::double"]
        return [f"(embedding[{i + 1}]::double + 1.0::double) / 2.0::double" for i in range(self.d)]

    def cls(self) -> Column:
        if self.kind == "skew":
            return banded(F.col("value"), BANDS, BAND_NAMES)
        if self.kind == "unif":
            return banded(F.col("x0"), (1 / 3, 2 / 3), ("low", "mid", "high"))
        if self.kind == "part":
            return F.col("p_type")
        if self.kind == "doc":
            return F.col("source")
        x = [F.col("embedding")[i] for i in range(3)]
        return F.when((x[0] >= x[1]) & (x[0] >= x[2]), "0").when(x[1] >= x[2], "1").otherwise("2")

    def cls_sql(self) -> str:
        if self.kind == "skew":
            return "CASE " + " ".join(f"WHEN value < {c} THEN '{n}'" for c, n in zip(BANDS, BAND_NAMES, strict=False)) + " ELSE 'E' END"
        if self.kind == "unif":
            return f"CASE WHEN {self.coords_sql()[0]} < {1 / 3!r}::double THEN 'low' WHEN {self.coords_sql()[0]} < {2 / 3!r}::double THEN 'mid' ELSE 'high' END"
        if self.kind == "part":
            return "p_type"
        if self.kind == "doc":
            return "source"
        return "CASE WHEN embedding[1] >= embedding[2] AND embedding[1] >= embedding[3] THEN '0' WHEN embedding[2] >= embedding[3] THEN '1' ELSE '2' END"

    def points(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """pid, x0.., cls."""
        source = spark.read.parquet(f"{sf_dir}/{self.table}.parquet")
        axes = {f"x{i}": c for i, c in enumerate(self.coords())}
        return source.withColumns(axes).select(F.col(self.id).cast("long").alias("pid"), *axes, self.cls().alias("cls"))

    def split(self, spark: SparkSession, sf_dir: str, **options) -> tuple[DataFrame, DataFrame]:
        return split(self.points(spark, sf_dir), self.d, **options)

    def sql(self) -> str:
        """A SELECT of pid, x0.., cls."""
        return f"SELECT {self.id}::bigint AS pid, " + ", ".join(f"{c} AS x{i}" for i, c in enumerate(self.coords_sql())) + f", {self.cls_sql()} AS cls FROM {self.table}"


PROFILES = {p.name: p for p in [*(Profile(f"skew{d}", "events", "event_id", d) for d in (1, 2, 3)), *(Profile(f"unif{d}", "orders", "o_orderkey", d) for d in (1, 2, 3)), Profile("part2", "part", "p_partkey", 2), Profile("doc1", "documents", "doc_id", 1), *(Profile(f"emb_{d}", "embeddings", "vec_id", d) for d in (4, 5, 6, 8))]}

#: Slices per axis, as a power of two, that give a few training points a cell at small scale.
DEFAULT_N = {"skew1": 8, "skew2": 4, "skew3": 3, "unif1": 7, "unif2": 4, "unif3": 3, "part2": 3, "doc1": 6, "emb_4": 1, "emb_5": 1, "emb_6": 1, "emb_8": 1}
