"""Suffix sorters. All give ``(pos, sid, k, sym)`` in the order of suffix text and, between equal ones, of strings."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusbwt.functions import kernels
from corpusbwt.functions.alphabet import Alphabet
from corpusbwt.operators.numbering import running_sum, with_row_index
from corpusbwt.operators.stringset import suffixes
from corpusbwt.session import release, ship, written

SA_SCHEMA = "pos long, sid long, k int, sym int"


def sort_direct(strings: DataFrame) -> DataFrame:
    """One range sort of the suffix texts; for strings of bounded length, as its rows carry the texts."""
    return with_row_index(suffixes(strings), ["suf", "sid"], "pos").select("pos", "sid", "k", "sym")


def sort_gather(strings: DataFrame, *, prefix: int = 16, bucket: str = "sampled", buckets: int = 256) -> DataFrame:
    """Suffixes dealt by prefix, so equal prefixes stay together, and sorted by text inside: a scale-out sorter.

    Splitters are sampled, or (``bucket='prefix'``) fixed ranges of the first two symbols. Its rows carry suffix texts; see
    ``sort_ranged`` for sets whose texts don't fit the disk.
    """
    rows = suffixes(strings)
    if bucket == "prefix":
        point = lambda i: F.least(F.when(F.length("suf") >= i, F.ascii(F.substring("suf", i, 1))).otherwise(0), F.lit(1023))
        rows = rows.withColumn("_deal", F.floor((point(1) * 1024 + point(2)) * buckets / (1 << 20)))
    else:
        rows = rows.withColumn("_deal", F.substring("suf", 1, prefix))
    return with_row_index(rows, ["_deal", "suf", "sid"], "pos").select("pos", "sid", "k", "sym")


def _regrouped(active: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Active rows with ``start``, the first position of their (group, keys), and ``members``, its size.

    Sizes are counted before anything is sorted, so a group of a third of all rows costs one row a task; prefix sums run
    over distinct keys only.
    """
    cells = active.groupBy("group", *keys).agg(F.count("*").alias("members"))
    summed = running_sum(cells, ["group", *keys], "members", "_before")
    base = summed.groupBy("group").agg(F.min("_before").alias("_base"))
    placed = summed.join(base, "group").select("group", *keys, "members", (F.col("group") + F.col("_before") - F.col("_base")).alias("start"))
    return active.join(placed, ["group", *keys])


def sort_msd_sieve(strings: DataFrame, words: Sequence[int] = (8, 8, 16, 32), *, sieve: bool = True, alphabet: Alphabet | None = None) -> DataFrame:
    """Word by word from the front; suffixes alone in their group leave after each round (unless ``sieve`` is off).

    ``words`` are the symbols of each round's word, the last one for all further rounds. With an alphabet, words of at most
    63 bits are packed into numbers. A suffix that ends inside a word is told apart by its terminator, that is by its string.
    """
    text = strings.select("sid", "s")
    active = suffixes(strings, with_text=False).withColumns({"group": F.lit(0).cast("long"), "n": F.lit(0)})
    done, depth, r = [], 0, 0
    while True:
        per = words[min(r, len(words) - 1)]
        if alphabet is not None:
            per = min(per, alphabet.symbols_per_word(64))
        rows = active.join(text, "sid")
        start = F.col("k") + 1 + depth
        key = F.substring("s", start, F.lit(per)) if alphabet is None else alphabet.packed_words("s", start, per)
        ended = F.length("s") - F.col("k") - depth < per
        rows = rows.withColumns({"word": key, "tie": F.when(ended, F.col("sid")).otherwise(F.lit(-1))}).drop("s")
        placed = written(_regrouped(rows, ["word", "tie"]))
        single = F.col("members") == 1
        done.append(placed.where(single).select(F.col("start").alias("pos"), "sid", "k", "sym"))
        rest = placed.where(~single) if sieve else placed
        active = rest.select("sid", "k", "sym", F.col("start").alias("group"), F.lit(0).alias("n"))
        depth, r = depth + per, r + 1
        if not placed.where(~single).limit(1).count():
            break
    if not sieve:
        return done[-1]
    out = done[0]
    for part in done[1:]:
        out = out.union(part)
    return out


def sort_doubling(strings: DataFrame) -> DataFrame:
    """Rank doubling: each round ranks pairs of ranks ``h`` apart, then doubles ``h``; for strings of any length."""
    symbol = F.ascii(F.substring("s", F.col("k") + 1, F.lit(1)))
    rows = suffixes(strings, with_text=False).join(strings.select("sid", "s", "len"), "sid")
    rows = rows.select("sid", "k", "sym", F.lit(0).cast("long").alias("group"), F.when(F.col("k") == F.col("len"), F.lit(0)).otherwise(symbol).alias("one"), F.when(F.col("k") == F.col("len"), F.col("sid")).otherwise(F.lit(-1)).alias("two"))
    ranked, h = written(_regrouped(rows, ["one", "two"]).select("sid", "k", "sym", F.col("start").alias("group"), "members")), 1
    while ranked.where("members > 1").limit(1).count():
        ahead = F.lead("group", h, -1).over(Window.partitionBy("sid").orderBy("k"))
        pairs = ranked.select("sid", "k", "sym", "group", ahead.alias("ahead"))
        after = written(_regrouped(pairs, ["ahead"]).select("sid", "k", "sym", F.col("start").alias("group"), "members"))
        release(ranked)
        ranked, h = after, 2 * h
    return ranked.select(F.col("group").alias("pos"), "sid", "k", "sym")


def _gathered(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None:
    """String numbers, code points, bounds and suffix order of all strings of a task; nothing without any."""
    held = [b for b in batches if b.num_rows]
    if not held:
        return None
    table = pa.Table.from_batches(held).sort_by("sid")
    points, bounds = kernels.flat_codes(table.column("s").to_pylist())
    return table.column("sid").to_numpy(), points, bounds, kernels.suffix_order(points, bounds)[0]


def sort_local(strings: DataFrame) -> DataFrame:
    """One task sorts one block by array kernels; for blocks that fit a task's memory (see ``planner``)."""
    ship(strings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if (got := _gathered(batches)) is None:
            return
        names, points, bounds, order = got
        _, owner = kernels.with_terminators(points, bounds)
        k = order - (bounds[:-1] + np.arange(len(bounds) - 1))[owner[order]]
        sid, sym = names[owner[order]], kernels.symbols_before(points, bounds)[order]
        for lo in range(0, len(order), 1 << 18):
            part = slice(lo, lo + (1 << 18))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(order))[part]), pa.array(sid[part]), pa.array(k[part].astype(np.int32)), pa.array(sym[part].astype(np.int32))], ["pos", "sid", "k", "sym"])

    return strings.select("sid", "s").coalesce(1).mapInArrow(run, SA_SCHEMA)


def places_local(strings: DataFrame) -> DataFrame:
    """``(sid, pos, sym)``: as ``sort_local``, in text order: arrays by k of each suffix's place and the symbol before it.

    A string's ranks join to one row, so a block's order and ranks meet without a row for each suffix.
    """
    ship(strings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if (got := _gathered(batches)) is None:
            return
        names, points, bounds, order = got
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        sym = kernels.symbols_before(points, bounds).astype(np.int32)
        edges = bounds + np.arange(len(bounds))
        for lo, hi in kernels.row_ranges(edges, 1 << 20):
            cut = pa.array((edges[lo : hi + 1] - edges[lo]).astype(np.int32))
            own = slice(edges[lo], edges[hi])
            yield pa.RecordBatch.from_arrays([pa.array(names[lo:hi]), pa.ListArray.from_arrays(cut, pa.array(place[own])), pa.ListArray.from_arrays(cut, pa.array(sym[own]))], ["sid", "pos", "sym"])

    return strings.select("sid", "s").coalesce(1).mapInArrow(run, "sid long, pos array<long>, sym array<int>")


def sort_ranges(strings: DataFrame) -> DataFrame:
    """Range by range from packed strings (see ``ranged``); for strings of bounded length, however many."""
    from corpusbwt.operators.ranged import sort_ranged

    return sort_ranged(strings, places=True).suffix_array()


SORTERS = {"ranges": sort_ranges, "direct": sort_direct, "gather": sort_gather, "sieve": sort_msd_sieve, "doubling": sort_doubling, "local": sort_local}


def suffix_array(strings: DataFrame, method: str = "direct") -> DataFrame:
    return SORTERS[method](strings)


def sieve_curve(strings: DataFrame, lengths: Sequence[int] = (4, 8, 16, 32, 64)) -> DataFrame:
    """``(symbols, unresolved, suffixes)``: suffixes that still share their first symbols, by number of symbols."""
    rows = suffixes(strings)
    out = None
    for w in lengths:
        word = F.substring("suf", 1, w)
        tie = F.when(F.length("suf") < w, F.col("sid")).otherwise(F.lit(-1))
        sizes = rows.groupBy(word.alias("word"), tie.alias("tie")).agg(F.count("*").alias("n"))
        one = sizes.agg(F.lit(w).alias("symbols"), F.coalesce(F.sum(F.when(F.col("n") > 1, F.col("n"))), F.lit(0)).alias("unresolved"), F.coalesce(F.sum("n"), F.lit(0)).alias("suffixes"))
        out = one if out is None else out.union(one)
    return out
