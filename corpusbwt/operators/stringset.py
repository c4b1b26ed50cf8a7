"""Ordered string sets, their suffixes and their cut into blocks."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.operators.numbering import running_sum, with_row_index


def string_set(df: DataFrame, text_col: str, order_cols: Sequence[str]) -> DataFrame:
    """``(keys…, s, len, sid)``: strings numbered densely in the order of ``order_cols``; a null text is empty."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = df.select(*order_cols, text.alias("s"), F.length(text).alias("len"))
    return with_row_index(rows, order_cols, "sid")


def suffixes(strings: DataFrame, *, with_text: bool = True) -> DataFrame:
    """``(sid, k, sym[, suf])``: every suffix with the symbol before it (its code point; 0 before a whole string)."""
    rows = strings.select("sid", "s", F.explode(F.sequence(F.lit(0), F.col("len"))).alias("k"))
    before = F.when(F.col("k") == 0, 0).otherwise(F.ascii(F.substring("s", F.col("k"), F.lit(1)))).cast("int")
    own = [F.substring("s", F.col("k") + 1, F.length("s")).alias("suf")] if with_text else []
    return rows.select("sid", "k", before.alias("sym"), *own)


def assign_blocks(strings: DataFrame, m_suffixes: int | None = None, *, blocks: int | None = None) -> DataFrame:
    """Adds ``block_id``: consecutive strings of about ``m_suffixes`` suffixes, or so many blocks, or (1) one a string.

    A block starts with the string before which the suffixes so far fill whole multiples of ``m_suffixes``.
    """
    sized = strings.withColumn("_n", (F.col("len") + 1).cast("long"))
    if blocks is not None:
        total = sized.agg(F.sum("_n")).first()[0] or 1
        m_suffixes = max(1, math.ceil(total / blocks))
    if m_suffixes == 1:
        return strings.withColumn("block_id", F.col("sid").cast("long"))
    summed = running_sum(sized, ["sid"], "_n", "_before")
    return summed.withColumn("block_id", F.floor(F.col("_before") / m_suffixes)).drop("_n", "_before")
