"""Ranks and searches on an index that stays in its shards: questions travel, pages don't.

A round sends each open question ``(key, i, c)`` to the shard that holds row ``i``, where the page's stored counters answer:
symbols before the shard come from the manifest, before the page from its 64-bit counters, before the spacing block from the
sampled ones, and the rest from a scan of less than a block. Places of suffixes come from pointer doubling over the rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusbwt.operators import bwt
from corpusbwt.plans.store import PageCodec, StoredIndex, locate
from corpusbwt.session import release, written

ANSWER = pa.schema([("key", pa.int64()), ("side", pa.int32()), ("j", pa.int64())])


def page_rank(codec: PageCodec, symbols: np.ndarray, sampled: np.ndarray, code: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Occurrences of codes before offsets of one page, from its sampled counters and a scan behind the last of them."""
    if not len(symbols):
        return np.zeros(len(at), np.int64)
    cell = np.minimum(at // codec.spacing, len(sampled) - 1)
    rest = at - cell * codec.spacing
    out = sampled[cell, code].astype(np.int64)
    offset = np.arange(codec.spacing)
    for lo in range(0, len(at), max(1, (1 << 21) // codec.spacing)):
        own = slice(lo, lo + max(1, (1 << 21) // codec.spacing))
        place = (cell[own] * codec.spacing)[:, None] + offset
        seen = symbols[np.minimum(place, len(symbols) - 1)]
        out[own] += ((seen == code[own, None]) & (offset < rest[own, None])).sum(1)
    return out


def stepped(index: StoredIndex, asked: DataFrame) -> DataFrame:
    """Questions ``(key, side, i, c)``, c a code, with ``j``: rows smaller than the suffix that c begins, given i for the
    suffix behind it. One exchange of the questions by shard."""
    codec, shards = index.codec, index.manifest.shards
    occ = np.array([s.occ for s in shards], np.int64).reshape(len(shards), -1)
    totals = occ.sum(0)
    smaller, ahead = np.cumsum(totals) - totals, np.cumsum(occ, axis=0) - occ
    before = {s.shard_id: smaller + ahead[n] for n, s in enumerate(shards)}
    begins = {s.shard_id: int(b) for s, b in zip(shards, index.starts, strict=True)}
    routed = locate(asked, "i", index.starts, [s.shard_id for s in shards], "shard_id")

    def answer(key: tuple, rows: pa.Table, pages: pa.Table) -> pa.Table:
        if not rows.num_rows:  # a shard without questions
            return ANSWER.empty_table()
        shard, pages = rows.column("shard_id")[0].as_py(), pages.sort_by("page_no")
        at, code = rows.column("i").to_numpy() - begins[shard], rows.column("c").to_numpy()
        starts = pages.column("start_in_shard").to_numpy()
        page = np.maximum(np.searchsorted(starts, at, "right") - 1, 0)
        order = np.argsort(page, kind="stable")
        out = before[shard][code]
        for mine in np.split(order, np.flatnonzero(np.diff(page[order])) + 1):
            held = pages.slice(page[mine[0]], 1).to_pylist()[0]
            symbols = codec.symbols(held["payload"], held["n_sym"])
            sampled = np.frombuffer(held["occ_rel"], np.int32).reshape(-1, codec.sigma + 1)
            out[mine] += np.array(held["occ_in_shard"], np.int64)[code[mine]] + page_rank(codec, symbols, sampled, code[mine], at[mine] - held["start_in_shard"])
        return pa.table([rows.column("key"), rows.column("side").cast(pa.int32()), pa.array(out)], schema=ANSWER)

    pages = index.pages().select("shard_id", "page_no", "start_in_shard", "n_sym", "payload", "occ_in_shard", "occ_rel")
    return routed.groupBy("shard_id").cogroup(pages.groupBy("shard_id")).applyInArrow(answer, "key long, side int, j long")


def code_of(index: StoredIndex, symbol: Column) -> Column:
    """A symbol's code, null for one that the index lacks."""
    pairs = [F.lit(x) for n, p in enumerate(index.manifest.points) for x in (p, n + 1)]
    return F.element_at(F.create_map(*pairs), F.ascii(symbol)) if pairs else F.lit(None).cast("int")


def intervals(index: StoredIndex, patterns: DataFrame) -> DataFrame:
    """``(pid, low, high)``: rows of the suffixes that each pattern begins, one round a symbol from the patterns' ends.

    Patterns that occur nowhere leave as soon as that shows; null patterns count as empty ones.
    """
    text = written(patterns.select(F.col("pid").cast("long"), F.coalesce("pattern", F.lit("")).alias("pattern")))
    state = written(text.select("pid", F.length("pattern").alias("left"), F.lit(0).cast("long").alias("low"), F.lit(index.manifest.n).cast("long").alias("high")))
    while state.where("left > 0 and low < high").limit(1).count():
        live = state.where("left > 0 and low < high").join(text, "pid")
        coded = live.select("pid", "left", "low", "high", code_of(index, F.substring("pattern", F.col("left"), F.lit(1))).alias("c"))
        asked = coded.where("c is not null").select(F.col("pid").alias("key"), "c", F.posexplode(F.array("low", "high")).alias("side", "i"))
        ends = stepped(index, asked).groupBy(F.col("key").alias("pid")).agg(F.min("j").alias("to_low"), F.max("j").alias("to_high"))
        on = coded.join(ends, "pid", "left").select("pid", F.when(F.col("c").isNull(), 0).otherwise(F.col("left") - 1).alias("left"), F.coalesce("to_low", "low").alias("low"), F.coalesce("to_high", "low").alias("high"))
        after = written(on.union(state.where("left = 0 or low >= high")))
        release(state)
        state = after
    return state.select("pid", "low", F.greatest("low", "high").alias("high"))


def count(index: StoredIndex, patterns: DataFrame) -> DataFrame:
    """``(pid, n)``: occurrences of each pattern in all strings."""
    return intervals(index, patterns).select("pid", (F.col("high") - F.col("low")).alias("n"))


def places(index: StoredIndex) -> DataFrame:
    """``(row, sid, k)`` of every suffix, by pointer doubling: as many joins of all rows as the longest string has bits."""
    walked = written(bwt.walks(index.rows()))
    sizes = walked.groupBy("sid").agg(F.max("far").alias("size"))
    return walked.join(sizes, "sid").select(F.col("pos").alias("row"), "sid", (F.col("size") - F.col("far")).cast("int").alias("k"))


def find(index: StoredIndex, patterns: DataFrame, *, at: DataFrame | None = None) -> DataFrame:
    """``(pid, sid, k)`` of every occurrence; ``at`` are stored ``places`` of this version of the index."""
    step = 4096  # an interval is listed in parts, so a pattern found everywhere costs no long array
    part = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("high") - F.col("low") - 1) / step)))
    parts = intervals(index, patterns).where("low < high").select("pid", "low", "high", part.alias("part"))
    first = F.col("low") + F.col("part") * step
    listed = parts.select("pid", F.explode(F.sequence(first, F.least(first + step, "high") - 1)).alias("row"))
    return listed.join(at if at is not None else places(index), "row").select("pid", "sid", "k")
