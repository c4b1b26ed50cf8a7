"""Dense numbers and running sums over a global order, without a single-task window.

Rows are range-sorted and stored with their partition and place in it; one count (or sum) a partition reaches the driver,
and its prefix sums come back as a literal map, so a row's number is its partition's base and its place.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusbwt.session import written

_PLACE_BITS = 33


def ordered(df: DataFrame, keys: Sequence[str | Column]) -> DataFrame:
    """``df`` range-sorted by ``keys`` and stored, with ``_part`` and ``_place`` of every row."""
    place = F.monotonically_increasing_id()
    laid = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", place)
    return written(laid.withColumns({"_part": F.shiftright("_at", _PLACE_BITS).cast("int"), "_place": F.col("_at").bitwiseAND((1 << _PLACE_BITS) - 1)}).drop("_at"))


def _bases(sums: dict[int, int]) -> Column:
    """The sum of all partitions before a row's own."""
    at, pairs = 0, []
    for part in sorted(sums):
        pairs += [F.lit(part), F.lit(at)]
        at += sums[part]
    if not pairs:
        return F.lit(0).cast("long")
    return F.element_at(F.create_map(*pairs), F.col("_part")).cast("long")


def with_row_index(df: DataFrame, keys: Sequence[str | Column], name: str = "pos") -> DataFrame:
    """``df`` with ``name``, the dense 0-based place of each row in the order of ``keys`` (ties in no set order)."""
    laid = ordered(df, keys)
    counts = {r["_part"]: r["n"] for r in laid.groupBy("_part").agg((F.max("_place") + 1).alias("n")).collect()}
    return laid.withColumn(name, _bases(counts) + F.col("_place")).drop("_part", "_place")


def running_sum(df: DataFrame, keys: Sequence[str | Column], value: str, name: str) -> DataFrame:
    """``df`` with ``name``, the sum of ``value`` over all rows before each row in the order of ``keys``."""
    laid = ordered(df, keys)
    sums = {r["_part"]: r["n"] for r in laid.groupBy("_part").agg(F.sum(value).alias("n")).collect()}
    before = Window.partitionBy("_part").orderBy("_place").rowsBetween(Window.unboundedPreceding, -1)
    return laid.withColumn(name, _bases(sums) + F.coalesce(F.sum(value).over(before), F.lit(0)).cast("long")).drop("_part", "_place")
