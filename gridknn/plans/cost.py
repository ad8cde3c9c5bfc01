"""What a search costs: pairs, overlaps, growths, updates, balance, bytes, and time by phase."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import merge
from ..operators.grid import GridSpec
from . import pipeline
from .pipeline import Run


def _measure(df: DataFrame, name: str, value) -> DataFrame:
    return df.agg(F.coalesce(value, F.lit(0)).cast("long").alias("value")).select(F.lit(name).alias("measure"), "value")


def primitive_pairs(query: DataFrame, train: DataFrame) -> DataFrame:
    """pairs: sum over cells of queries times training points, from counts only (both tables carry cell).

    A query counts as often as its column copies says, if it has one.
    """
    u = query.groupBy("cell").agg((F.sum("copies") if "copies" in query.columns else F.count("*")).alias("u"))
    t = train.groupBy("cell").agg(F.count("*").alias("t"))
    return u.join(t, "cell").agg(F.coalesce(F.sum(F.col("u") * F.col("t")), F.lit(0)).alias("pairs"))


def placed(run: Run) -> tuple[DataFrame, DataFrame]:
    """Queries and training points with the cell (or region) they were searched by."""
    if run.regions is None:
        return run.query, run.train
    return merge.relabel(run.query, run.regions), merge.relabel(run.train, run.regions)


def _weighed(df: DataFrame, copies: DataFrame | None) -> DataFrame:
    return df.withColumn("copies", F.lit(1).cast("long")) if copies is None else df.join(copies.select("pid", "copies"), "pid")


def measures(run: Run, copies: DataFrame | None = None) -> DataFrame:
    """measure, value: distance pairs of both steps, touched cells, growths, list updates and stage sizes.

    copies: pid, copies where a query stands for several, each of which counts.
    """
    if run.own is None:
        n = _weighed(run.query, copies).agg(F.sum("copies").alias("a")).crossJoin(run.train.agg(F.count("*").alias("b")))
        return n.select(F.lit("pairs_primitive").alias("measure"), (F.col("a") * F.col("b")).alias("value"))
    query, train = placed(run)
    weighed = lambda df: _weighed(df, copies)
    probes, balls, own = weighed(run.probes), weighed(run.balls), weighed(run.own)
    extra = weighed(run.extra[0] if run.extra else run.probes.filter("false"))
    if_ = lambda c: F.sum(F.when(c, F.col("copies")))
    parts = [
        primitive_pairs(weighed(query), train).select(F.lit("pairs_primitive").alias("measure"), F.col("pairs").alias("value")),
        _measure(probes, "pairs_probe", F.sum(F.col("n") * F.col("copies"))),
        _measure(extra, "pairs_recheck", F.sum(F.col("n") * F.col("copies"))),
        _measure(probes, "overlaps", F.sum("copies")),
        _measure(balls, "growths", F.sum(F.col("growths") * F.col("copies"))),
        _measure(own, "short_queries", if_(F.col("held") < run.k)),
        _measure(balls, "done_queries", if_(F.col("done"))),
        _measure(weighed(updated(run)), "updates", F.sum("copies")),
        _measure(run.counts, "occupied_cells", F.count("*")),
        _measure(own, "list_entries", F.sum(F.col("held") * F.col("copies"))),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def updated(run: Run) -> DataFrame:
    """pid for each update of its list: by its own cell and by each that it probes, in however many chunks their points lie."""
    return run.own.select("pid").unionByName(run.probes.select("pid"))


def updates_per_point(run: Run) -> DataFrame:
    return updated(run).groupBy("pid").agg(F.count("*").alias("updates"))


def balance(query: DataFrame, train: DataFrame) -> DataFrame:
    """cells, mean and largest pairs of a cell, and their ratio: 1 is even."""
    u, t = (df.groupBy("cell").agg(F.count("*").alias(c)) for df, c in ((query, "u"), (train, "t")))
    each = u.join(t, "cell").select((F.col("u") * F.col("t")).alias("p"))
    return each.agg(F.count("*").alias("cells"), F.avg("p").alias("mean_pairs"), F.max("p").alias("max_pairs"), (F.max("p") / F.avg("p")).alias("unevenness"))


def record_bytes(k: int, d: int) -> int:
    """Bytes of an intermediate record: id, coordinates, cell, and k entries of distance, id and class."""
    return 8 + 8 * d + 8 + k * (8 + 8 + 8)


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to make all rows, sent nowhere."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def phases(query: DataFrame, train: DataFrame, k: int, grid: GridSpec, strategy: str = "grow", **options) -> dict[str, float]:
    """Seconds of each phase, each made on its own from stored inputs; their sum isn't the total time."""
    from ..functions.vote import majority
    from ..operators import probe
    from ..operators.density import cell_counts
    from ..operators.local import lists, train_blocks, unify

    d, out = grid.d, {}
    q, t = grid.assign(query, "q"), grid.assign(train, "t")
    out["distribution"] = timed(lambda: cell_counts(t, grid))
    if strategy == "merge":
        out["merging"] = timed(lambda: merge.regions(t, q, grid, k))
    run = pipeline.search(query, train, k, grid, strategy=strategy, **options)
    q, t = placed(run)
    blocks = train_blocks(t, d)
    out["primitive"] = timed(lambda: unify(lists(q, blocks, d, k, keep_empty=True), k, ["cell"]))
    balls = run.balls.select("pid", *[f"q{i}" for i in range(d)], "cell", "r")
    probes = lambda: probe.overlapped(balls.drop("cell").withColumn("cell", F.lit(0).cast("long")), run.counts, grid)
    out["overlap"] = timed(probes)
    out["update"] = timed(lambda: lists(run.probes, blocks, d, k, within=True))
    out["integrate"] = timed(lambda: unify(run.updates, k, []))
    out["classification"] = timed(lambda: run.final.select("pid", majority(F.col("nn")).alias("v")))
    return out


def predicted_pairs(query: DataFrame, train: DataFrame, grid: GridSpec, k: int, strategy: str = "grow") -> int:
    """Pairs of the own-cell step before anything is run."""
    q, t = grid.assign(query, "q"), grid.assign(train, "t")
    if strategy == "brute":
        return query.count() * train.count()
    if strategy == "merge":
        found = merge.regions(t, q, grid, k)
        q, t = merge.relabel(q, found), merge.relabel(t, found)
    return int(primitive_pairs(q, t).first()["pairs"])


def guard(query: DataFrame, train: DataFrame, grid: GridSpec, k: int, limit: int, strategy: str = "grow") -> bool:
    """Whether a run stays within a budget of pairs; those beyond are reported as failing, not run."""
    return predicted_pairs(query, train, grid, k, strategy) <= limit
