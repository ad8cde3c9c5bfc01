"""Connected components of an edge table by hooking and shortcutting, one stored label table a round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import discard, saved


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, label) for the nodes of the edges; label: the smallest node reachable.

    In each round every node looks at its neighbours' labels, the smallest seen by any node
    of a tree hooks the tree's root, and labels jump to their labels' labels; trees shrink to
    stars in a number of rounds that grows with the logarithm of their size.
    """
    both = saved(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).unionByName(edges.select(F.col(b).alias("u"), F.col(a).alias("v"))).distinct(), "edges")
    labels = saved(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("node"), F.least("u", "m").alias("label")), "labels")
    while True:
        seen = both.join(labels.select(F.col("node").alias("v"), F.col("label").alias("l")), "v").groupBy("u").agg(F.min("l").alias("best"))
        near = saved(labels.join(seen.withColumnRenamed("u", "node"), "node").select("node", "label", F.least("label", "best").alias("best")), "near")
        hooks = near.groupBy("label").agg(F.min("best").alias("hook"))
        hooked = saved(near.join(hooks, "label").select("node", F.least("best", "hook").alias("label"), F.col("label").alias("old")), "hooked")
        jump = hooked.select(F.col("node").alias("label"), F.col("label").alias("next"))
        after = saved(hooked.join(jump, "label", "left").select("node", F.coalesce("next", "label").alias("label"), "old"), "labels")
        discard(near, hooked, labels)
        labels = after
        if after.filter("label <> old").isEmpty():
            discard(both)
            return after.select("node", "label")
