"""The class of a neighbour list, in array functions only: no shuffle."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def majority(nn: Column, tie: str = "nearest", weighted: bool = False) -> Column:
    """struct(cls_pred, votes, best_rank) of the winning class; null for an empty list.

    nn: array of struct(dist, tid, cls), nearest first. Ties go to the class whose best rank
    is smallest (nearest) or whose name is smallest (class). weighted: a vote counts
    1 / (distance + 1e-12).
    """
    if tie not in ("nearest", "class"):
        raise ValueError(f"unknown tie rule {tie}")
    classes = F.array_distinct(F.transform(nn, lambda x: x["cls"]))

    def ballot(c: Column) -> Column:
        mine = F.filter(nn, lambda x: x["cls"] == c)
        weight = F.aggregate(mine, F.lit(0.0), lambda s, x: s + 1 / (x["dist"] + 1e-12)) if weighted else F.size(mine).cast("double")
        rank = F.array_position(F.transform(nn, lambda x: x["cls"]), c)
        order = rank.cast("string") if tie == "class" else F.lpad(rank.cast("string"), 12, "0")
        key = c.cast("string") if tie == "class" else order
        return F.struct((-weight).alias("w"), key.alias("k"), c.alias("cls_pred"), F.size(mine).alias("votes"), rank.alias("best_rank"))

    best = F.element_at(F.array_sort(F.transform(classes, ballot)), 1)
    return F.when(F.size(nn) > 0, F.struct(best["cls_pred"].alias("cls_pred"), best["votes"].alias("votes"), best["best_rank"].alias("best_rank")))
