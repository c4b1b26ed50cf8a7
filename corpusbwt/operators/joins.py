"""Joins that Spark lacks: the last row at or before a key, and the range that holds a point."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusbwt.operators.numbering import ordered


def as_of(left: DataFrame, right: DataFrame, on: str, by: str | None = None) -> DataFrame:
    """``left`` with ``found``, the struct of the last ``right`` row whose ``on`` is at most its own (of the same ``by``).

    Both sides are sorted together; each partition's last right row is carried to the next ones by a join of one row a
    partition, so no window spans all rows.
    """
    group = F.col(by) if by else F.lit(0)
    one = left.select(group.alias("_by"), F.col(on).alias("_on"), F.lit(1).alias("_side"), F.struct("*").alias("_left"), F.lit(None).cast(right.select(F.struct("*")).schema[0].dataType).alias("_right"))
    two = right.select(group.alias("_by"), F.col(on).alias("_on"), F.lit(0).alias("_side"), F.lit(None).cast(left.select(F.struct("*")).schema[0].dataType).alias("_left"), F.struct("*").alias("_right"))
    laid = ordered(one.union(two), ["_by", "_on", "_side"])
    inside = Window.partitionBy("_part", "_by").orderBy("_place").rowsBetween(Window.unboundedPreceding, 0)
    last = laid.where("_side = 0").groupBy("_by", "_part").agg(F.max_by("_right", "_place").alias("_carry"))
    parts = laid.where("_side = 1").select("_by", "_part").distinct().withColumnRenamed("_part", "_to")
    carried = parts.join(last, "_by").where("_part < _to").groupBy("_by", "_to").agg(F.max_by("_carry", "_part").alias("_carry")).withColumnRenamed("_to", "_part")
    seen = laid.withColumn("_near", F.last("_right", ignorenulls=True).over(inside)).where("_side = 1")
    return seen.join(carried, ["_by", "_part"], "left").select("_left.*", F.coalesce("_near", "_carry").alias("found"))


def in_range(points: DataFrame, ranges: DataFrame, point: str, start: str, end: str, *, cell: int = 1 << 16) -> DataFrame:
    """Points with the columns of the range that holds each (start <= point < end): an equi-join on cells of the axis."""
    cells = F.explode(F.sequence(F.floor(F.col(start) / cell), F.floor((F.col(end) - 1) / cell)))
    split = ranges.where(F.col(end) > F.col(start)).withColumn("_cell", cells)
    return points.withColumn("_cell", F.floor(F.col(point) / cell)).join(split, "_cell").where((F.col(start) <= F.col(point)) & (F.col(point) < F.col(end))).drop("_cell")
