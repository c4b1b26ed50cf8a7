"""The corpus pipeline: quality, boilerplate lines, near duplicates, packing; each stage reads what the one before wrote."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from corpusbwt.llm import line_dedup, near_dedup, packing, quality
from corpusbwt.llm.common import table
from corpusbwt.session import ship, written


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine, trained on the labelled ones among them, accepts.

    Null and empty texts are scored as empty ones; rows with a null id are scored but never learnt from; repeated rows are
    judged alike; an empty table stays empty.
    """
    ship(spark)
    model = quality.train(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return quality.accepted(docs, model)


def cut_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without cross-site boilerplate lines.

    A null text stays null, a null source is a site of its own, repeated rows lose the same lines; an empty table stays empty.
    """
    return line_dedup.without_boilerplate(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates.

    Texts without words and rows with a null id stay; rows that repeat an id stay or go together; an empty table stays empty.
    """
    ship(spark)
    return near_dedup.without_near_duplicates(docs)


def pack_along_curve(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents left, in sequences of 2048 ids along a Hilbert curve.

    A null or empty text is its end id alone; rows with a null id and repeated rows are packed as they come; an empty table
    gives no rows.
    """
    ship(spark)
    return packing.pack(docs)


STAGES = [("quality", keep_quality), ("line_dedup", cut_lines), ("near_dedup", drop_near_duplicates), ("packing", pack_along_curve)]
#: Scores, shingle links and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each result but the last stored as Parquet in the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
