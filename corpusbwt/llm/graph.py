"""Connected components of an edge table, distributed: nothing but a count of changes reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.session import release, written


def components(edges: DataFrame) -> DataFrame:
    """``(node, component)`` for every node of undirected edges ``(a, b)``; a component is named by its smallest node.

    Every round takes the smallest name among a node and its neighbours and then follows names one step (pointer
    doubling). A node with very many edges costs one partial aggregate, never a collected list. No edges: no rows.
    """
    both = written(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    names = written(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("component")))
    while True:
        near = both.join(names.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("low"))
        lower = names.join(near, "node").select("node", F.col("component").alias("was"), F.least("component", "low").alias("component"))
        jump = names.select(F.col("node").alias("component"), F.col("component").alias("beyond"))
        after = written(lower.join(jump, "component").select("node", F.least("component", "beyond").alias("component"), "was"))
        changed = after.where("component <> was").limit(1).count()
        release(names)
        names = after.select("node", "component")
        if not changed:
            release(both)
            return names
