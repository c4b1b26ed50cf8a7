"""SQL functions over an index: ``bwt_rank(c, k)``, ``bwt_count(pattern)``, and table functions on texts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from corpusbwt.operators.fm import _codes, intervals
from corpusbwt.operators.ranking import shared_engine
from corpusbwt.plans.store import StoredIndex


@F.udtf(returnType="k int, suffix string")
class Suffixes:
    """All suffixes of a text, the empty one last."""

    def eval(self, text: str) -> Iterator[tuple[int, str]]:
        for k in range(len(text or "") + 1):
            yield k, (text or "")[k:]


@F.udtf(returnType="window int, s string")
class Windows:
    """Consecutive windows of a text; an empty text has one empty window."""

    def eval(self, text: str, width: int) -> Iterator[tuple[int, str]]:
        for w, at in enumerate(range(0, max(1, len(text or "")), width)):
            yield w, (text or "")[at : at + width]


def register(spark: SparkSession, index: StoredIndex | None = None) -> None:
    """Register the table functions and, with an index, its scalar functions."""
    spark.udtf.register("suffixes", Suffixes)
    spark.udtf.register("read_windows", Windows)
    if index is None:
        return
    engine, points = shared_engine(index), np.array(index.manifest.points, np.int64)

    @F.pandas_udf("long")
    def bwt_count(patterns: pd.Series) -> pd.Series:
        low, high = intervals(engine(), *_codes([p or "" for p in patterns], points))
        return pd.Series(high - low)

    @F.pandas_udf("long")
    def bwt_rank(symbols: pd.Series, rows: pd.Series) -> pd.Series:
        codes, _ = _codes([s[:1] for s in symbols], points)
        at = np.clip(rows.to_numpy(np.int64), 0, len(engine().symbols))
        return pd.Series(np.where(codes > 0, engine().rank(codes, at), 0))

    spark.udf.register("bwt_count", bwt_count)
    spark.udf.register("bwt_rank", bwt_rank)
