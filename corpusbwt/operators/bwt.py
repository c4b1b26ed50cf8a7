"""Transforms in row form, ``(pos, sym)`` with ``sym`` a code point and 0 for every terminator, and what follows from them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.operators.joins import as_of
from corpusbwt.operators.numbering import running_sum, with_row_index
from corpusbwt.operators.suffixsort import suffix_array
from corpusbwt.session import release, ship, written


def bwt_symbols(sa: DataFrame) -> DataFrame:
    """Symbols in suffix order; the symbol has travelled with the sort, so nothing is joined back."""
    return sa.select("pos", "sym")


def bwt_once(strings: DataFrame, method: str = "direct") -> DataFrame:
    """The transform of the whole set by one sort."""
    return bwt_symbols(suffix_array(strings, method))


def c_table(bwt: DataFrame) -> DataFrame:
    """``(sym, cnt, c_before)``: each symbol's count and the number of smaller symbols. Terminators count as symbols."""
    return running_sum(bwt.groupBy("sym").agg(F.count("*").alias("cnt")), ["sym"], "cnt", "c_before")


def occ_sampled(bwt: DataFrame, spacing: int) -> DataFrame:
    """``(block, sym, n, before)``: occurrences in each block of rows that has the symbol, and before the block."""
    cells = bwt.groupBy(F.floor(F.col("pos") / spacing).alias("block"), "sym").agg(F.count("*").alias("n"))
    summed = running_sum(cells, ["sym", "block"], "n", "_all")
    base = summed.groupBy("sym").agg(F.min("_all").alias("_base"))
    return summed.join(F.broadcast(base), "sym").select("block", "sym", "n", (F.col("_all") - F.col("_base")).alias("before"))


def lf(bwt: DataFrame) -> DataFrame:
    """Adds ``lf``: the row of the suffix one symbol longer. It is a row's place in the order of (symbol, row)."""
    return with_row_index(bwt, ["sym", "pos"], "lf")


def rank(bwt: DataFrame, queries: DataFrame) -> DataFrame:
    """Queries ``(c, k)`` with ``rank``: occurrences of code point ``c`` in the first ``k`` rows. An as-of join by symbol."""
    numbered = lf(bwt).join(F.broadcast(c_table(bwt).select("sym", "c_before")), "sym")
    seen = numbered.select(F.col("sym").alias("c"), F.col("pos").alias("_last"), (F.col("lf") - F.col("c_before") + 1).alias("_n"))
    asked = queries.withColumn("_last", F.col("k") - 1)
    return as_of(asked, seen, "_last", "c").select(*queries.columns, F.coalesce("found._n", F.lit(0)).cast("long").alias("rank"))


def lf_step(bwt: DataFrame, queries: DataFrame) -> DataFrame:
    """Queries ``(c, k)`` with ``row``: suffixes smaller than ``c`` before a suffix that is larger than ``k`` suffixes."""
    ranked = rank(bwt, queries)
    smaller = F.broadcast(c_table(bwt).select(F.col("sym").alias("c"), "c_before"))
    return ranked.join(smaller, "c", "left").select(*queries.columns, (F.coalesce("c_before", F.lit(0)) + F.col("rank")).alias("row"))


def runs(bwt: DataFrame) -> DataFrame:
    """``(run, sym, start, len)``: maximal runs of equal symbols, found by joining each row with the one before."""
    before = bwt.select((F.col("pos") + 1).alias("pos"), F.col("sym").alias("_prior"))
    heads = bwt.join(before, "pos", "left").where(F.col("_prior").isNull() | (F.col("_prior") != F.col("sym"))).select(F.col("pos").alias("start"), "sym")
    numbered = written(with_row_index(heads, ["start"], "run"))
    after = numbered.select((F.col("run") - 1).alias("run"), F.col("start").alias("_next"))
    size = bwt.agg(F.count("*").alias("_n"))
    return numbered.join(after, "run", "left").join(F.broadcast(size)).select("run", "sym", "start", (F.coalesce("_next", "_n") - F.col("start")).alias("len"))


def walks(bwt: DataFrame) -> DataFrame:
    """``(pos, sid, far, sym)``: each row's string and its steps from that string's terminator, by pointer doubling.

    The terminator's row is the string's number. ⌈log2 of the longest⌉ joins of all rows, each round stored.
    """
    mapped = written(lf(bwt))
    up = mapped.where("sym <> 0").select(F.col("lf").alias("pos"), F.col("pos").alias("above"), F.lit(1).cast("long").alias("far"))
    roots = mapped.where("true").join(up.select("pos"), "pos", "left_anti").select("pos", F.col("pos").alias("above"), F.lit(0).cast("long").alias("far"))
    held = written(up.union(roots))
    while True:
        jump = held.select(F.col("pos").alias("above"), F.col("above").alias("_above"), F.col("far").alias("_far"))
        after = written(held.join(jump, "above").select("pos", F.col("_above").alias("above"), (F.col("far") + F.col("_far")).alias("far"), (F.col("_far") > 0).alias("moved")))
        more = after.where("moved").limit(1).count()
        release(held)
        held = after.drop("moved")
        if not more:
            return held.join(mapped, "pos").select("pos", F.col("above").alias("sid"), "far", "sym")


def invert_rows(bwt: DataFrame) -> DataFrame:
    """``(sid, s)``: the strings, read off their rows' walks."""
    letters = F.decode(F.unhex(F.lpad(F.hex("sym"), 8, "0")), "UTF-32")
    rows = walks(bwt).select("sid", "far", F.when(F.col("sym") == 0, "").otherwise(letters).alias("c"))
    lists = rows.groupBy("sid").agg(F.sort_array(F.collect_list(F.struct("far", "c")), asc=False).alias("all"))
    return lists.select("sid", F.array_join(F.transform("all", lambda x: x["c"]), "").alias("s"))


def neighbours(sa: DataFrame) -> DataFrame:
    """Rows of a suffix array with ``sid0, k0`` of the suffix before (null for the first)."""
    before = sa.select((F.col("pos") + 1).alias("pos"), F.col("sid").alias("sid0"), F.col("k").alias("k0"))
    return sa.select("pos", "sid", "k").join(before.hint("merge"), "pos", "left")


def lcp(sa: DataFrame, strings: DataFrame) -> DataFrame:
    """``(pos, lcp)``: symbols that each suffix shares with the one before it; 0 for the first."""
    ship(strings.sparkSession)
    text = strings.select("sid", "s")
    # Spark estimates suffixes as large as their strings, and would broadcast them
    both = neighbours(sa).hint("merge").join(text, "sid").join(text.select(F.col("sid").alias("sid0"), F.col("s").alias("s0")), "sid0", "left")

    @F.pandas_udf("int")
    def common(a: pd.Series, i: pd.Series, b: pd.Series, j: pd.Series) -> pd.Series:
        out = np.zeros(len(a), np.int32)
        for n, (x, p, y, q) in enumerate(zip(a, i, b, j, strict=True)):
            if y is None or q != q:
                continue
            x, y = x[int(p) :], y[int(q) :]
            low, high = 0, min(len(x), len(y))
            while low < high:
                middle = (low + high + 1) // 2
                low, high = (middle, high) if x[:middle] == y[:middle] else (low, middle - 1)
            out[n] = low
        return pd.Series(out)

    return both.select("pos", common("s", "k", "s0", "k0").alias("lcp"))


def export_text(bwt: DataFrame, path: str) -> None:
    """The transform as text files of one symbol a line, in order; terminators are empty lines."""
    letter = F.when(F.col("sym") == 0, "").otherwise(F.decode(F.unhex(F.lpad(F.hex("sym"), 8, "0")), "UTF-32"))
    bwt.repartitionByRange("pos").sortWithinPartitions("pos").select(letter.alias("value")).write.mode("overwrite").text(path)


def export_runs(bwt: DataFrame, path: str) -> None:
    """The transform's runs as Parquet, sorted by their starts."""
    runs(bwt).repartitionByRange("start").sortWithinPartitions("start").write.mode("overwrite").parquet(path)


def from_blocks(function, strings: DataFrame) -> DataFrame:
    """A transform that one task makes of the whole set by array code: ``function(codes, bounds)`` gives symbols in order.

    For the sequential baselines, whose sets must fit one task; symbols pass as dense codes and come back as code points.
    """
    ship(strings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from corpusbwt.functions import kernels

        held = [b for b in batches if b.num_rows]
        if not held:
            return
        points, bounds = kernels.flat_codes(pa.Table.from_batches(held).sort_by("sid").column("s").to_pylist())
        alphabet, codes = np.unique(points, return_inverse=True)
        made = np.concatenate([[0], alphabet])[function(codes + 1, bounds)]
        for lo in range(0, len(made), 1 << 18):
            part = made[lo : lo + (1 << 18)]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + len(part))), pa.array(part.astype(np.int32))], ["pos", "sym"])

    return strings.select("sid", "s").coalesce(1).mapInArrow(run, "pos long, sym int")
