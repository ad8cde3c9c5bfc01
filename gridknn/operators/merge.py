"""The merging baseline: sparse cells are united with their siblings before any search.

The original's merge step isn't printed; this is a reconstruction, of which only the
aggregate behaviour can be compared. In a pyramid of 2**d-ary nodes, a node that queries
enter but that holds fewer than k training points is triggered, and unites with its siblings
into its parent. A cell's region is its coarsest ancestor with a triggered child; that has
a closed form over one grouped count for each level, so no round-by-round merging is needed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .grid import GridSpec


def _up(d: int):
    return F.call_function("shiftright", F.col("cell"), F.col("up") * d)


def regions(train: DataFrame, query: DataFrame, grid: GridSpec, k: int) -> DataFrame:
    """cell, region, up, region_cells for each cell that holds training points or queries."""
    if not grid.is_pow2:
        raise ValueError("merging needs a power-of-two grid with equal slices")
    d, n = grid.d, grid.levels
    held = train.groupBy("cell").agg(F.count("*").alias("t")).withColumn("i", F.lit(0).cast("long"))
    entered = query.groupBy("cell").agg(F.count("*").alias("i")).withColumn("t", F.lit(0).cast("long"))
    cells = held.unionByName(entered).groupBy("cell").agg(F.sum("t").alias("t"), F.sum("i").alias("i"))
    levels = cells.withColumn("up", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))) if n else cells.withColumn("up", F.lit(0)).filter("false")
    nodes = levels.groupBy("up", _up(d).alias("node")).agg(F.sum("t").alias("t"), F.sum("i").alias("i"))
    united = nodes.filter((F.col("i") > 0) & (F.col("t") < k)).select((F.col("up") + 1).alias("up"), F.shiftright("node", d).alias("node")).distinct()
    lifted = cells.select("cell").withColumn("up", F.explode(F.sequence(F.lit(0), F.lit(n)))).withColumn("node", _up(d))
    coarsest = lifted.join(united.withColumn("merged", F.lit(True)), ["up", "node"], "left").groupBy("cell").agg(F.coalesce(F.max(F.when(F.col("merged"), F.col("up"))), F.lit(0)).alias("up"))
    region = _up(d) * 64 + F.col("up")
    return coarsest.select("cell", region.alias("region"), "up", F.call_function("shiftleft", F.lit(1).cast("long"), F.col("up") * d).alias("region_cells"))


def stats(found: DataFrame, grid: GridSpec) -> DataFrame:
    """merged_cells, pct_of_cells, largest_merged, merged_regions: unoccupied base cells of a region count."""
    each = found.filter("up > 0").groupBy("region").agg(F.max("region_cells").alias("n"))
    total = F.coalesce(F.sum("n"), F.lit(0))
    return each.agg(total.cast("long").alias("merged_cells"), (F.lit(100.0) * total / F.lit(float(grid.total_cells))).alias("pct_of_cells"), F.coalesce(F.max("n"), F.lit(1)).cast("long").alias("largest_merged"), F.count("*").alias("merged_regions"))


def relabel(df: DataFrame, found: DataFrame) -> DataFrame:
    """cell replaced by the region it belongs to."""
    return df.join(found.select("cell", "region"), "cell").drop("cell").withColumnRenamed("region", "cell")


def largest_first(found: DataFrame) -> DataFrame:
    """Regions by size, for a look at how uneven they are."""
    rank = Window.orderBy(F.col("region_cells").desc(), "region")
    each = found.groupBy("region").agg(F.max("region_cells").alias("region_cells"), F.count("*").alias("occupied"))
    return each.orderBy(F.col("region_cells").desc(), "region").limit(100).withColumn("rank", F.row_number().over(rank))
