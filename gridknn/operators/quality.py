"""Accuracy of predicted classes and of neighbour lists."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def confusion(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """truth, pred, n; pred is null where no class was found."""
    joined = truth.select("pid", F.col("cls").alias("truth")).join(pred.select("pid", F.col("cls_pred").alias("pred")), "pid")
    return joined.groupBy("truth", "pred").agg(F.count("*").alias("n"))


def confusion_wide(cells: DataFrame, classes: list[str]) -> DataFrame:
    """The matrix with a column for each class."""
    return cells.groupBy("truth").pivot("pred", classes).agg(F.sum("n"))


def rates(cells: DataFrame) -> DataFrame:
    """cls, tp, fn, fp, tn: rates over a class's own and over all other points, one against the rest."""
    total = F.broadcast(cells.agg(F.sum("n").alias("total")))
    own = cells.groupBy(F.col("truth").alias("cls")).agg(F.sum("n").alias("actual"), F.sum(F.when(F.col("truth") == F.col("pred"), F.col("n")).otherwise(0)).alias("hit"))
    said = cells.groupBy(F.col("pred").alias("cls")).agg(F.sum("n").alias("said"))
    both = own.join(said, "cls", "left").crossJoin(total).withColumn("said", F.coalesce("said", F.lit(0)))
    tp, fp = F.col("hit") / F.col("actual"), (F.col("said") - F.col("hit")) / F.nullif(F.col("total") - F.col("actual"), F.lit(0))
    return both.select("cls", tp.alias("tp"), (1 - tp).alias("fn"), fp.alias("fp"), (1 - fp).alias("tn"))


def macro(each: DataFrame) -> DataFrame:
    """Unweighted means over the classes that occur."""
    return each.agg(*[F.avg(c).alias(c) for c in ("tp", "fn", "fp", "tn")])


def accuracy(cells: DataFrame) -> DataFrame:
    return cells.agg((F.sum(F.when(F.col("truth") == F.col("pred"), F.col("n")).otherwise(0)) / F.sum("n")).alias("accuracy"))


def recall(nn: DataFrame, exact: DataFrame, copies: DataFrame | None = None) -> DataFrame:
    """queries, exact_lists (equal to the brute-force list), mean share of true neighbours found.

    copies: pid, copies where a query stands for several.
    """
    ids = lambda c: F.transform(c, lambda x: x["tid"])
    both = nn.select("pid", ids("nn").alias("a")).join(exact.select("pid", ids("nn").alias("b")), "pid")
    share = F.when(F.size("b") > 0, F.size(F.array_intersect("a", "b")) / F.size("b")).otherwise(1.0)
    both = both.withColumn("copies", F.lit(1).cast("long")) if copies is None else both.join(copies.select("pid", "copies"), "pid")
    queries, same = F.sum("copies"), F.sum(F.when(F.col("a") == F.col("b"), F.col("copies")).otherwise(0))
    return both.agg(F.coalesce(queries, F.lit(0)).alias("queries"), F.coalesce(same, F.lit(0)).alias("exact_lists"), (F.sum(share * F.col("copies")) / queries).alias("recall"))
