"""Ranks of new suffixes among old ones, by four strategies: ``(sid, k, g)``.

``replicated`` sends the old transform to every task and chains string by string, backwards; ``rounds`` leaves it in its
shards and moves the strings, one exchange a symbol; ``merge`` sorts old and new suffixes together and counts; ``theta``
compares all pairs and is for tests alone. ``start`` is the rank of a new terminator: the number of old strings where
new strings come last, 0 where they come first.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.functions.kernels import RankEngine, chain_ranks, flat_codes, row_ranges
from corpusbwt.operators.numbering import running_sum
from corpusbwt.operators.stringset import suffixes
from corpusbwt.plans.store import StoredIndex
from corpusbwt.session import written

_ENGINES: dict[str, RankEngine] = {}
#: Rows up to which a worker lists positions (8 bytes each) in place of counters; listing takes 24 bytes a row for a while.
MOST_LISTED = 1 << 26
#: The same where pairs of symbols are listed as well.
MOST_LISTED_PAIRS = 1 << 22


def shared_engine(index: StoredIndex, q: int = 1):
    """A function that gives the rank engine inside a task: symbols are broadcast once, counters built once a worker."""
    sent = index.spark.sparkContext.broadcast((index.symbols, index.alphabet.sigma, index.codec.spacing))
    key = sent._id if getattr(sent, "_id", None) is not None else sent._jbroadcast.id()  # a broadcast's number is its own
    key = f"{index.spark.sparkContext.applicationId}/{key}"

    def engine() -> RankEngine:
        if key not in _ENGINES:
            _ENGINES.clear()
            symbols, sigma, spacing = sent.value
            _ENGINES[key] = RankEngine(symbols, sigma, spacing, positions=len(symbols) <= (MOST_LISTED if q == 1 else MOST_LISTED_PAIRS))
        return _ENGINES[key]

    return engine


def chained(strings: DataFrame, index: StoredIndex, *, start: int | None = None, q: int = 1) -> DataFrame:
    """``(sid, g)``: all ranks of each string as an array by k, from the replicated index."""
    engine, alphabet = shared_engine(index, q), index.alphabet
    first = index.manifest.m if start is None else start

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            sizes = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])])
            for lo, hi in row_ranges(sizes, 1 << 20):
                points, bounds = flat_codes(texts[lo:hi])
                g = chain_ranks(engine(), alphabet.codes(points), bounds, first, q)
                edges = bounds + np.arange(len(bounds))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(edges.astype(np.int32)), pa.array(g))], ["sid", "g"])

    parts = strings.sparkSession.sparkContext.defaultParallelism  # chains are long work on few bytes: deal them to all tasks
    return strings.select("sid", "s").repartition(parts, "sid").mapInArrow(run, "sid long, g array<long>")


def ranks_replicated(strings: DataFrame, index: StoredIndex, *, start: int | None = None, q: int = 1) -> DataFrame:
    return chained(strings, index, start=start, q=q).select("sid", F.posexplode("g").alias("k", "g"))


def ranks_rounds(strings: DataFrame, index: StoredIndex, *, start: int | None = None) -> DataFrame:
    """The same chains with the index left in its shards: every round sends each live string's state to the shard that
    holds its row, where stored counters answer; strings leave when their first symbol is done."""
    from corpusbwt.operators.sharded import code_of, stepped

    first = index.manifest.m if start is None else start
    text = strings.select("sid", "s")
    state = written(strings.select("sid", F.col("len").alias("k"), F.lit(first).cast("long").alias("i")))
    parts = [state]
    while state.where("k > 0").limit(1).count():
        live = state.where("k > 0").join(text, "sid")
        asked = live.select(F.col("sid").alias("key"), (F.col("k") - 1).cast("int").alias("side"), "i", code_of(index, F.substring("s", F.col("k"), F.lit(1))).alias("c"))
        state = written(stepped(index, asked).select(F.col("key").alias("sid"), F.col("side").alias("k"), F.col("j").alias("i")))
        parts.append(state)
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return out.select("sid", "k", F.col("i").alias("g"))


def ranks_merge(old: DataFrame, new: DataFrame) -> DataFrame:
    """One range sort of old and new suffixes and a running count of old ones; equal texts are in the order of strings."""
    rows = suffixes(old).select("sid", "k", "suf", F.lit(1).alias("old")).union(suffixes(new).select("sid", "k", "suf", F.lit(0)))
    return running_sum(rows, ["suf", "sid"], "old", "g").where("old = 0").select("sid", "k", "g")


def ranks_theta(old: DataFrame, new: DataFrame) -> DataFrame:
    """By comparing every new suffix with every old one; for fixtures of a few hundred suffixes."""
    a = suffixes(new).select("sid", "k", "suf")
    b = suffixes(old).select(F.col("sid").alias("sid0"), F.col("suf").alias("suf0"))
    less = (F.col("suf0") < F.col("suf")) | ((F.col("suf0") == F.col("suf")) & (F.col("sid0") < F.col("sid")))
    return a.join(b, less, "left").groupBy("sid", "k").agg(F.count("sid0").alias("g"))


def compute_ranks(strings: DataFrame, index: StoredIndex, strategy: str = "auto", *, old: DataFrame | None = None, start: int | None = None, q: int = 1) -> DataFrame:
    """Ranks of all suffixes of ``strings`` in ``index``; ``merge`` also needs the ``old`` strings."""
    from corpusbwt.plans.planner import choose_ranker

    if strategy == "auto":
        strategy = choose_ranker(index, strings, old is not None)
    if strategy == "replicated":
        return ranks_replicated(strings, index, start=start, q=q)
    if strategy == "rounds":
        return ranks_rounds(strings, index, start=start)
    if strategy == "merge":
        return ranks_merge(old, strings)
    return ranks_theta(old, strings)


def reorder(ranks: DataFrame, sa: DataFrame) -> DataFrame:
    """Ranks in suffix order: ``(pos, sid, k, sym, g)``."""
    return sa.hint("merge").join(ranks, ["sid", "k"])


def insert_rows(bwt: DataFrame, new: DataFrame) -> DataFrame:
    """Row-form insertion of ``(ord, g, sym)``: new row i goes to g + i, an old row moves by the new ones up to it.

    Shifts come from one running sum over old and new rows in order, so nothing is compared pairwise.
    """
    rows = bwt.select(F.col("pos").alias("at"), F.lit(1).alias("kind"), F.lit(0).cast("long").alias("ord"), "sym", F.lit(0).alias("one"))
    rows = rows.union(new.select(F.col("g").alias("at"), F.lit(0).alias("kind"), F.col("ord").cast("long"), "sym", F.lit(1)))
    summed = running_sum(rows, ["at", "kind", "ord"], "one", "shift")
    return summed.select((F.col("at") + F.col("shift")).alias("pos"), "sym")


def ordered_new(strings: DataFrame, ranks: DataFrame) -> DataFrame:
    """New suffixes ``(ord, g, sym)`` in suffix order; the rank leads the sort, which it never contradicts."""
    from corpusbwt.operators.numbering import with_row_index

    rows = suffixes(strings).hint("merge").join(ranks, ["sid", "k"])  # Spark estimates suffixes as large as their strings, and would broadcast them
    return with_row_index(rows, ["g", "suf", "sid"], "ord").select("ord", "g", "sym", "sid", "k")
