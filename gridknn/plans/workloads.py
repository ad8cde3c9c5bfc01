"""The experiments, each as a table of measures over its parameters."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import merge, quality
from ..operators.grid import GridSpec, bounds
from ..operators.points import fraction, normalise, split
from . import cost
from .pipeline import classify, fitted_grid, search, shared_places
from .profiles import DEFAULT_N, PROFILES

KS = (5, 10, 15, 20)
FRACTIONS = (0.2, 0.4, 0.6, 0.8, 1.0)


def _tagged(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(c) for c, v in tags.items()], "*")


def _union(parts: Iterable[DataFrame]) -> DataFrame:
    parts = list(parts)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def measured(spark: SparkSession, sf_dir: str, name: str, k: int, n: int, strategy: str = "grow", f: float = 1.0, limit: int | None = None) -> DataFrame:
    """All counted measures of one run; a run over the limit of pairs gives one row `failed`."""
    p = PROFILES[name]
    train, query = split(fraction(p.points(spark, sf_dir), f), p.d)
    grid = GridSpec.pow2(p.d, n)
    tags = {"profile": name, "method": strategy, "k": k, "n": n, "f": f}
    if limit and not cost.guard(query, train, grid, k, limit, strategy):
        return _tagged(spark.range(1).select(F.lit("failed").alias("measure"), F.lit(1).cast("long").alias("value")), **tags)
    seen = shared_places(query, p.d)
    return _tagged(cost.measures(search(query if seen is None else seen.drop("copies"), train, k, grid, strategy=strategy), seen), **tags)


def own_cell_pairs(spark, sf_dir, name: str, ns, k: int = 5) -> DataFrame:
    """n, method, pairs: distances of the own-cell step over the number of slices, from counts alone."""
    p, out = PROFILES[name], []
    train, query = p.split(spark, sf_dir)
    for n in ns:
        grid = GridSpec.pow2(p.d, n)
        t, q = grid.assign(train, "t"), grid.assign(query, "q")
        found = merge.regions(t, q, grid, k)
        united = cost.primitive_pairs(merge.relabel(q, found), merge.relabel(t, found))
        out += [_tagged(cost.primitive_pairs(q, t), n=n, method="grow"), _tagged(united, n=n, method="merge")]
    return _union(out)


def granularity(spark, sf_dir, name: str = "skew2", ns=range(1, 8), k: int = 5, strategies=("grow", "merge"), limit=None) -> DataFrame:
    """Cost over the number of slices (2**n an axis)."""
    return _union(measured(spark, sf_dir, name, k, n, s, limit=limit) for n in ns for s in strategies)


def neighbours(spark, sf_dir, name: str = "skew2", ks=KS, strategies=("grow", "merge"), limit=None) -> DataFrame:
    """Cost over k."""
    return _union(measured(spark, sf_dir, name, k, DEFAULT_N[name], s, limit=limit) for k in ks for s in strategies)


def dimensions(spark, sf_dir, kind: str = "skew", k: int = 20, strategies=("grow", "merge"), limit=None) -> DataFrame:
    """Cost over d = 1, 2, 3."""
    return _union(measured(spark, sf_dir, f"{kind}{d}", k, DEFAULT_N[f"{kind}{d}"], s, limit=limit) for d in (1, 2, 3) for s in strategies)


def high_dimensions(spark, sf_dir, ds=(4, 5, 6, 8), k: int = 5) -> DataFrame:
    """Cost beyond three dimensions."""
    return _union(measured(spark, sf_dir, f"emb_{d}", k, 1) for d in ds)


def scale(spark, sf_dir, name: str = "unif3", fs=FRACTIONS, k: int = 5, strategies=("grow", "merge"), limit=None) -> DataFrame:
    """Cost over the fraction of the data, the grid unchanged."""
    return _union(measured(spark, sf_dir, name, k, DEFAULT_N[name], s, f, limit) for f in fs for s in strategies)


def merge_statistics(spark, sf_dir, name: str = "skew3", ks=KS, fs=(1.0,), n: int | None = None) -> DataFrame:
    """What the merge step unites, over k or over the fraction of the data."""
    p, out = PROFILES[name], []
    grid = GridSpec.pow2(p.d, n or DEFAULT_N[name])
    for f in fs:
        train, query = split(fraction(p.points(spark, sf_dir), f), p.d)
        train, query = grid.assign(train, "t"), grid.assign(query, "q")
        out += [_tagged(merge.stats(merge.regions(train, query, grid, k), grid), profile=name, k=k, f=f) for k in ks]
    return _union(out)


def phase_times(spark, sf_dir, name: str = "unif2", ks=KS, strategies=("grow", "merge")) -> DataFrame:
    """Seconds of each phase over k."""
    p, rows = PROFILES[name], []
    train, query = p.split(spark, sf_dir)
    for k in ks:
        for s in strategies:
            rows += [(name, s, k, phase, sec) for phase, sec in cost.phases(query, train, k, GridSpec.pow2(p.d, DEFAULT_N[name]), s).items()]
    return spark.createDataFrame(rows, "profile string, method string, k int, phase string, seconds double")


def total_times(spark, sf_dir, name: str = "unif2", k: int = 5, n: int | None = None, strategies=("grow", "merge", "brute"), **options) -> DataFrame:
    """Seconds of whole classifications by method; with sessions of other sizes, the speedup experiment."""
    p = PROFILES[name]
    train, query = p.split(spark, sf_dir)
    grid = GridSpec.pow2(p.d, n or DEFAULT_N[name])
    rows = [(name, s, k, spark.sparkContext.defaultParallelism, cost.timed(lambda s=s: classify(query, train, k, grid, strategy=s, **options))) for s in strategies]
    return spark.createDataFrame(rows, "profile string, method string, k int, cores int, seconds double")


def speedup(times: DataFrame) -> DataFrame:
    """Times of several sessions (cores, seconds by profile and method): seconds relative to the fewest cores."""
    from pyspark.sql import Window

    w = Window.partitionBy("profile", "method", "k").orderBy("cores")
    return times.withColumn("speedup", F.first("seconds").over(w) / F.col("seconds")).withColumn("step", F.lag("seconds").over(w) / F.col("seconds"))


def quality_rates(spark, sf_dir, name: str = "skew3", k: int = 10, **options) -> DataFrame:
    """tp, fn, fp, tn of each class, and their mean as the class `average`; every axis scaled to the whole target space."""
    p = PROFILES[name]
    points = p.points(spark, sf_dir)
    train, query = split(points, p.d)
    lo, hi = bounds(train, query, p.d)
    train, query = split(normalise(points, lo, hi), p.d)
    pred = classify(query, train, k, fitted_grid(query, train), **options)
    each = quality.rates(quality.confusion(pred, points))
    return each.unionByName(_tagged(quality.macro(each), cls="average"))


def distributions(spark, sf_dir, k: int = 5, per_cell: float = 8.0) -> DataFrame:
    """How unevenly skewed and uniform points load the cells of grids that fit their number."""
    out = []
    for name in ("skew2", "unif2", "skew3", "unif3"):
        train, query = PROFILES[name].split(spark, sf_dir)
        grid = fitted_grid(query, train, per_cell)
        out.append(_tagged(cost.balance(grid.assign(query, "q"), grid.assign(train, "t")), profile=name))
    return _union(out)
