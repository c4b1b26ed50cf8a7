"""Queries over the given tables, one for each operator, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusbwt.llm import byte_bpe, licenses, line_dedup, media, near_dedup, packing, quality, token_counts, url_filter, vector_graph
from corpusbwt.llm.common import table


def op1_factorisation_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every document, learnt from the labelled ones outside the held-out fold."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "n_chars")
    return quality.scored(docs, quality.train(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licences of all documents, filed by source and hundreds of ids, with inheritance from directories."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "source")
    path = F.concat(F.lit("/"), F.coalesce("source", F.lit("")), F.lit("/"), F.floor(F.col("doc_id") / 100), F.lit("/"), F.col("doc_id"))
    return licenses.scan(docs.select("doc_id", path.alias("path"), "text"))


def op3_curve_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 2048 ids along a Hilbert curve."""
    return packing.pack(table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_site_spread_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without the lines that stand on many sites."""
    return line_dedup.line_report(table(spark, sf_dir, "documents", "doc_id", "text", "source"))


def op5_lossless_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document stored as lossless WebP, read back and described."""
    return media.media_columns(table(spark, sf_dir, "documents", "doc_id", "text"))


def op6_transducer_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every document by the lower-casing vocabulary with word ends."""
    return token_counts.token_counts(table(spark, sf_dir, "documents", "doc_id", "text"))


def op7_pruned_graph_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 nearest rows of every twentieth embedding."""
    return vector_graph.nearest(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))


def op8_hamming_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate components of all documents."""
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


def op9_recursive_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded by the byte-level ranks and decoded again."""
    return byte_bpe.round_trip(table(spark, sf_dir, "documents", "doc_id", "text"))


def op10_segmented_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A verdict on every page's URL."""
    return url_filter.judged(table(spark, sf_dir, "pages", "page_id", "url", "html"))


_ALL = (
    op1_factorisation_quality,
    op2_license_scan,
    op3_curve_packing,
    op4_site_spread_lines,
    op5_lossless_webp,
    op6_transducer_token_counts,
    op7_pruned_graph_neighbours,
    op8_hamming_near_duplicates,
    op9_recursive_byte_bpe,
    op10_segmented_url_filter,
)
QUERIES = {f.__name__: f for f in _ALL}
SQL: dict[str, str] = {"op4_site_spread_lines": line_dedup.LINE_REPORT_SQL}
