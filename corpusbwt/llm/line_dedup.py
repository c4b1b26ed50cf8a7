"""Cross-site boilerplate lines by distinct-site spread, in DataFrame functions alone.

Lines on one site alone, by far the most, are told by the least and greatest site of their hash. Every other line's hash
gathers a HyperLogLog sketch of the sites it stands on; sketches merge in the aggregation, so a line on every page costs a
sketch a task. Lines whose estimate lies near the threshold get exact distinct counts. A line on ``min_sites`` sites or
more is removed everywhere but at its first place (least document id, then position).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.session import written

#: At sf0.1 lines of over 50 words stand on three sites at most, as copied documents do, or on eleven and more; a line on
#: five sites keeps its first place, so nothing is lost if a copy took it there.
MIN_SITES = 5
#: Estimates within this share of the threshold are counted exactly: six standard errors of a sketch of 2**12 registers.
BAND = 0.1
REGISTERS = 12
#: Parts to which the rows of one line are dealt.
SALTS = 16


def _lines(df: DataFrame, id_col: str, text_col: str, site_col: str) -> DataFrame:
    """Non-blank lines: document key, position, hash of the trimmed lower-cased line, site."""
    held = df.select(F.col(id_col).alias("doc"), F.xxhash64(text_col).alias("version"), F.coalesce(F.col(site_col).cast("string"), F.lit("")).alias("site"), F.posexplode(F.split(text_col, "\n")).alias("pos", "line"))
    bare = F.lower(F.trim("line"))
    return held.where(bare != "").select("doc", "version", "site", "pos", F.xxhash64(bare).alias("hash"))


def boilerplate(lines: DataFrame, min_sites: int) -> DataFrame:
    """Hashes of lines on ``min_sites`` sites or more, each with its first place."""
    place = F.min(F.struct("doc", "version", "pos"))
    if min_sites > 1:
        site = F.xxhash64("site")
        several = lines.groupBy("hash").agg(F.min(site).alias("low"), F.max(site).alias("high")).where("low < high").select("hash")
        # salted: a line on a third of all rows is dealt out, and partly aggregated before rows meet by hash alone
        dealt = several.select("hash", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
        salt = F.pmod(F.xxhash64("doc", "version"), F.lit(SALTS)).cast("int")
        lines = lines.withColumn("salt", salt).join(dealt, ["hash", "salt"], "left_semi").drop("salt")
    spread = lines.groupBy("hash").agg(F.hll_sketch_agg("site", F.lit(REGISTERS)).alias("sketch"), place.alias("first"))
    guessed = written(spread.select("hash", "first", F.hll_sketch_estimate("sketch").alias("sites")).where(F.col("sites") >= min_sites * (1 - BAND)))
    near = guessed.where(F.col("sites") <= min_sites * (1 + BAND))
    counted = lines.join(near.select("hash"), "hash", "left_semi").select("hash", "site").distinct().groupBy("hash").agg(F.count("*").alias("exact"))
    sure = guessed.where(F.col("sites") > min_sites * (1 + BAND)).select("hash", "first")
    return sure.union(near.join(counted.where(F.col("exact") >= min_sites), "hash").select("hash", "first"))


def cleaned(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", *, min_sites: int = MIN_SITES) -> DataFrame:
    """``df``'s rows as a struct ``row``, with ``lines``, ``removed`` (positions, null where none) and ``kept`` (the text left).

    A null text has no lines and stays null; blank lines are never boilerplate. A null site is a site of its own. Rows that
    repeat an id and text are one document and lose the same lines. An empty table gives no rows.
    """
    lines = _lines(df, id_col, text_col, site_col)
    marked = written(boilerplate(lines, min_sites))
    found = lines.select("doc", "version", "pos", "hash").join(marked, "hash")
    again = found.where(~F.struct("doc", "version", "pos").eqNullSafe(F.col("first")))
    gone = again.groupBy("doc", "version").agg(F.sort_array(F.collect_set("pos")).alias("removed"))
    rows = df.select(F.struct("*").alias("row"), F.col(id_col).alias("own_doc"), F.xxhash64(text_col).alias("own_version"))
    joined = rows.join(gone, F.col("own_doc").eqNullSafe(F.col("doc")) & (F.col("own_version") == F.col("version")), "left")
    joined = joined.select("row", "removed", F.split(f"row.`{text_col}`", "\n").alias("lines"))  # behind the shuffle: it moves texts once
    edges = F.concat(F.array(F.lit(-1)), F.col("removed"), F.array(F.size("lines")))
    runs = F.transform(F.sequence(F.lit(1), F.size("removed") + 1), lambda j: F.slice("lines", F.get(edges, j - 1) + 2, F.get(edges, j) - F.get(edges, j - 1) - 1))
    kept = F.when(F.col("removed").isNull(), F.col(f"row.`{text_col}`")).otherwise(F.array_join(F.flatten(runs), "\n"))
    return joined.select("row", "lines", "removed", kept.alias("kept"))


def line_report(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", *, min_sites: int = MIN_SITES) -> DataFrame:
    """Per row: doc_id, n_lines, n_removed and the text that is left."""
    out = cleaned(df, id_col, text_col, site_col, min_sites=min_sites)
    return out.select(F.col(f"row.`{id_col}`").alias("doc_id"), F.greatest(F.coalesce(F.size("lines"), F.lit(0)), F.lit(0)).cast("long").alias("n_lines"), F.greatest(F.coalesce(F.size("removed"), F.lit(0)), F.lit(0)).cast("long").alias("n_removed"), F.col("kept").alias("text"))


def without_boilerplate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", *, min_sites: int = MIN_SITES) -> DataFrame:
    """``docs`` with all its columns and boilerplate lines cut out; documents of which no line is left are gone.

    Such a document's lines all stand elsewhere, at their first places. Documents that came without text stay.
    """
    out = cleaned(docs, id_col, text_col, site_col, min_sites=min_sites)
    bare = F.col("removed").isNotNull() & (F.trim(F.regexp_replace("kept", "\n", "")) == "")
    return out.where(~bare).select(*(F.col("kept").alias(c) if c == text_col else F.col(f"row.`{c}`").alias(c) for c in docs.columns))


LINE_REPORT_SQL = f"""
WITH lines AS (
    SELECT doc_id, coalesce(source, '') AS site, unnest(range(len(parts))) AS pos, unnest(parts) AS line
    FROM (SELECT doc_id, source, string_split(text, chr(10)) AS parts FROM documents)),
bare AS (SELECT *, lower(trim(line)) AS norm FROM lines),
marked AS (
    SELECT norm, min((doc_id, pos)) AS first FROM bare WHERE norm <> '' GROUP BY norm HAVING count(DISTINCT site) >= {MIN_SITES}),
flagged AS (SELECT bare.*, marked.norm IS NOT NULL AND (doc_id, pos) <> first AS gone FROM bare LEFT JOIN marked USING (norm))
SELECT doc_id, count(*) AS n_lines, count_if(gone) AS n_removed, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS text
FROM (SELECT doc_id, pos, line, coalesce(gone, false) AS gone FROM flagged) GROUP BY doc_id
UNION ALL SELECT doc_id, 0, 0, text FROM documents WHERE text IS NULL
"""
