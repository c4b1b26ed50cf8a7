"""Given tables, text and sequence files, and the string sets made of them."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def windows_of(text: Column, width: int) -> Column:
    """Consecutive windows of a text as an array of (window, s); an empty text has one empty window."""
    cut = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{width}}}"), F.lit(0))  # one pass, where substrings count from the start
    return F.transform(F.when(F.length(text) > 0, cut).otherwise(F.array(F.lit(""))), lambda s, w: F.struct(w.cast("long").alias("window"), s.alias("s")))


def read_windows(df: DataFrame, id_cols: list[str], text_col: str, width: int) -> DataFrame:
    """``(ids…, window, s)``: texts cut into reads of ``width`` symbols; null texts give none."""
    return df.where(F.col(text_col).isNotNull()).select(*id_cols, F.inline(windows_of(F.col(text_col), width)))


def dna_projection(df: DataFrame, text_col: str) -> DataFrame:
    """The text as four letters: a to z in turn become a, c, g, t; all else is dropped.

    An operator of its own, so that nothing above it takes the projection a second time.
    """
    letters, at = b"abcdefghijklmnopqrstuvwxyz", df.columns.index(text_col)
    table = bytes.maketrans(letters, (b"acgt" * 7)[:26])
    dropped = bytes(sorted({*range(256)} - {*letters}))  # bytes of other symbols are never letters

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).cast(pa.binary()).to_pylist()
            made = pa.array([None if t is None else t.translate(table, dropped) for t in texts], pa.binary()).cast(batch.column(at).type)
            yield batch.set_column(at, batch.schema.field(at), made)

    return df.withColumn(text_col, F.lower(text_col)).mapInArrow(run, df.withColumn(text_col, F.lower(text_col)).schema)


def symbol_streams(df: DataFrame, key: str, order: list[str], symbol: Column, name: str = "s") -> DataFrame:
    """``(key, s)``: one string a key, its rows' symbols in order. A key's rows must fit a task, as its string must."""
    pairs = F.sort_array(F.collect_list(F.struct(*order, symbol.alias("_symbol"))))
    return df.groupBy(key).agg(F.array_join(F.transform(pairs, lambda x: x["_symbol"]), "").alias(name))


def quality_filter(docs: DataFrame, labels: DataFrame, quality: int = 1, toxic: int = 0) -> DataFrame:
    """Documents with the wanted labels."""
    return docs.join(labels.where((F.col("quality") == quality) & (F.col("toxic") == toxic)).select("doc_id"), "doc_id", "left_semi")


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """``(s)``: one string a line."""
    return spark.read.text(path).select(F.col("value").alias("s"))


def read_sequences(spark: SparkSession, path: str, fmt: str = "fasta") -> DataFrame:
    """``(name, s)`` of sequence files: ``fasta`` (a header line, sequence lines) or ``fastq`` (four lines a read).

    Records are split by their header sign, so a file is read in parallel and no line number is needed.
    """
    if fmt == "fasta":
        records = spark.read.option("lineSep", ">").text(path).where(F.length("value") > 0)
        lines = F.split("value", "\n")
        return records.select(F.trim(F.get(lines, F.lit(0))).alias("name"), F.array_join(F.transform(F.slice(lines, 2, F.size(lines)), F.trim), "").alias("s"))
    records = spark.read.option("lineSep", "\n@").text(path)
    lines = F.split("value", "\n")
    # a quality line that starts with the header sign is cut off as a record of its own, which has no third line of a read
    return records.where(F.get(lines, F.lit(2)).startswith("+")).select(F.trim(F.regexp_replace(F.get(lines, F.lit(0)), "^@", "")).alias("name"), F.trim(F.get(lines, F.lit(1))).alias("s"))


def except_new(strings: DataFrame, indexed: DataFrame) -> DataFrame:
    """Strings whose text isn't indexed yet."""
    known = indexed.select(F.xxhash64("s").alias("_h"), F.col("s").alias("_s")).distinct()
    return strings.join(known, (F.xxhash64("s") == F.col("_h")) & (F.col("s") == F.col("_s")), "left_anti")


def runs_summary(runs: DataFrame, by: list[str], mode: str = "rollup") -> DataFrame:
    """Runs, symbols and mean run length by groups: ``rollup``, ``cube``, or ``sets`` (each column alone, and all)."""
    agg = [F.count("*").alias("runs"), F.sum("len").alias("symbols")]
    if mode == "sets":
        runs.createOrReplaceTempView("_runs_summary")
        cols = ", ".join(by)
        sets = ", ".join(f"({c})" for c in by)
        return runs.sparkSession.sql(f"SELECT {cols}, count(*) AS runs, sum(len) AS symbols FROM _runs_summary GROUP BY GROUPING SETS ({sets}, ())")
    return (runs.rollup(*by) if mode == "rollup" else runs.cube(*by)).agg(*agg)
