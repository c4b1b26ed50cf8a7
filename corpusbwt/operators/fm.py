"""Searches in an FM-index: count, locate, containing strings, extraction and shared passages.

Patterns run in the tasks that hold them, against the replicated engine, while the index fits every task; beyond it (or with
``strategy="sharded"``) the index stays in its shards and the patterns' states travel, see ``operators/sharded.py``. The chain
of a pattern is that of a new string twice over, for the lower and the upper end of its interval of rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.functions.kernels import RankEngine, read_back
from corpusbwt.operators import sharded
from corpusbwt.operators.bwt import invert_rows
from corpusbwt.operators.ranking import shared_engine
from corpusbwt.plans.store import MOST_REPLICATED, StoredIndex
from corpusbwt.session import written


def _codes(texts: list[str], points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Dense codes of patterns (0 for what the alphabet lacks) and their bounds."""
    bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
    raw = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")
    if not len(points):
        return np.zeros(len(raw), np.int64), bounds
    at = np.minimum(np.searchsorted(points, raw), len(points) - 1)
    return np.where(points[at] == raw, at + 1, 0), bounds


def intervals(engine: RankEngine, codes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the suffixes that each pattern begins: from low to high. An empty interval leaves the rounds at once."""
    n, sizes = len(engine.symbols), np.diff(bounds)
    low, high = np.zeros(len(sizes), np.int64), np.full(len(sizes), n, np.int64)
    t = 1
    while True:
        on = np.flatnonzero((sizes >= t) & (low < high))
        if not len(on):
            return low, np.maximum(low, high)
        c = codes[bounds[on + 1] - t]
        known = c > 0
        both = engine.step(np.concatenate([c[known], c[known]]), np.concatenate([low[on[known]], high[on[known]]]))
        half = len(both) // 2
        low[on[known]], high[on[known]] = both[:half], both[half:]
        high[on[~known]] = low[on[~known]]
        t += 1


def _patterns(index: StoredIndex, patterns: DataFrame, answer, schema: str) -> DataFrame:
    """Runs ``answer(engine, ids, texts)``, which yields record batches, over ``(pid, pattern)``."""
    engine = shared_engine(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield from answer(engine(), batch.column(0), [p or "" for p in batch.column(1).to_pylist()])

    return patterns.select(F.col("pid").cast("long"), "pattern").mapInArrow(run, schema)


def _sharded(index: StoredIndex, strategy: str) -> bool:
    return strategy == "sharded" or (strategy == "auto" and index.manifest.n * index.codec.dtype().itemsize > MOST_REPLICATED)


def count(index: StoredIndex, patterns: DataFrame, *, strategy: str = "auto") -> DataFrame:
    """``(pid, n)``: occurrences of each pattern in all strings; an empty pattern occurs at every suffix."""
    if _sharded(index, strategy):
        return sharded.count(index, patterns)
    points = np.array(index.manifest.points, np.int64)

    def answer(engine, ids, texts):
        low, high = intervals(engine, *_codes(texts, points))
        yield pa.RecordBatch.from_arrays([ids, pa.array(high - low)], ["pid", "n"])

    return _patterns(index, patterns, answer, "pid long, n long")


def samples(index: StoredIndex, rate: int = 32) -> DataFrame:
    """``(row, sid, k)`` of every suffix with k divisible by ``rate``: strings read back once, in step.

    Row j (j below the number of strings) is string j's terminator, so sids are known where the walks start and need no
    column that insertions would have to move. k = 0 is always among them.
    """
    engine, m = shared_engine(index), index.manifest.m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            first = batch.column(0).to_numpy()
            for lo in range(0, len(first), 4096):
                sids = first[lo : lo + 4096]
                rows, owners = read_back(engine(), sids)
                size = np.zeros(len(sids), np.int64)
                for t, own in enumerate(owners):
                    size[own] = t
                row, own = np.concatenate(rows), np.concatenate(owners)
                k = size[own] - np.repeat(np.arange(len(rows)), [len(r) for r in rows])
                keep = k % rate == 0
                yield pa.RecordBatch.from_arrays([pa.array(row[keep]), pa.array(sids[own[keep]]), pa.array(k[keep].astype(np.int32))], ["row", "sid", "k"])

    return index.spark.range(m).select("id").mapInArrow(run, "row long, sid long, k int")


def locate(index: StoredIndex, patterns: DataFrame, *, rate: int = 32, sampled: DataFrame | None = None, strategy: str = "auto") -> DataFrame:
    """``(pid, sid, k)`` of every occurrence: rows of the interval walk back to a sampled row, then one join on rows."""
    if _sharded(index, strategy):
        return sharded.find(index, patterns)
    points, sampled = np.array(index.manifest.points, np.int64), sampled if sampled is not None else written(samples(index, rate))
    rows = sampled.select("row").where(F.col("row").isNotNull())
    engine = shared_engine(index)
    marks = np.zeros(index.manifest.n, bool)
    marks[np.asarray(rows.toArrow().column(0), np.int64)] = True  # a bit a row of a replicated index, rate times fewer set
    sent = index.spark.sparkContext.broadcast(np.packbits(marks))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stop = np.unpackbits(sent.value).view(bool)
        for batch in batches:
            if not batch.num_rows:
                continue
            held = engine()
            low, high = intervals(held, *_codes([p or "" for p in batch.column(1).to_pylist()], points))
            owner = np.repeat(np.arange(len(low)), high - low)
            row = np.concatenate([np.arange(a, b) for a, b in zip(low, high, strict=True)]) if len(owner) else np.zeros(0, np.int64)
            far = np.zeros(len(row), np.int32)
            live = np.flatnonzero(~stop[row]) if len(row) else row
            while len(live):
                row[live] = held.step(held.symbols[row[live]].astype(np.int64), row[live])
                far[live] += 1
                live = live[~stop[row[live]]]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owner)), pa.array(row), pa.array(far)], ["pid", "row", "far"])

    hits = patterns.select(F.col("pid").cast("long"), "pattern").mapInArrow(run, "pid long, row long, far int")
    return hits.join(sampled, "row").select("pid", "sid", (F.col("k") + F.col("far")).alias("k"))


def documents_with(index: StoredIndex, patterns: DataFrame, **options) -> DataFrame:
    """``(pid, sid)``: the strings that hold each pattern."""
    return locate(index, patterns, **options).select("pid", "sid").distinct()


def absent(index: StoredIndex, patterns: DataFrame, *, strategy: str = "auto") -> DataFrame:
    """Patterns that occur nowhere."""
    return patterns.join(count(index, patterns, strategy=strategy).where("n > 0").select("pid"), "pid", "left_anti")


def invert(index: StoredIndex, *, strategy: str = "auto") -> DataFrame:
    """``(sid, s)``: all strings, read back from their terminators in step, or by pointer doubling over sharded rows."""
    if _sharded(index, strategy):
        return invert_rows(index.rows())
    engine, points = shared_engine(index), np.array((0, *index.manifest.points), "<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            first = batch.column(0).to_numpy()
            for lo in range(0, len(first), 4096):
                sids = first[lo : lo + 4096]
                rows, owners = read_back(engine(), sids)
                row, own = np.concatenate(rows), np.concatenate(owners)
                step = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
                order = np.lexsort((-step, own))
                symbols = points[engine().symbols[row[order]]]
                cuts = np.concatenate([[0], np.cumsum(np.bincount(own, minlength=len(sids)))])
                # the walk of a string ends on a terminator, which stands first in text order
                texts = [symbols[a + 1 : b].tobytes().decode("utf-32-le", "surrogatepass") for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(sids), pa.array(texts)], ["sid", "s"])

    return index.spark.range(index.manifest.m).select("id").mapInArrow(run, "sid long, s string")


def shared(index: StoredIndex, patterns: DataFrame, min_len: int) -> DataFrame:
    """``(pid, start, len, n)``: maximal passages of each pattern, of ``min_len`` symbols or more, that occur in the index.

    From every end the match grows to the left until its interval is empty; those inside another match are dropped.
    """
    points = np.array(index.manifest.points, np.int64)

    def answer(engine, ids, texts):
        codes, bounds = _codes(texts, points)
        of = np.repeat(np.arange(len(texts)), np.diff(bounds))
        end = np.arange(len(codes)) + 1
        start, low, high = end.copy(), np.zeros(len(codes), np.int64), np.full(len(codes), len(engine.symbols), np.int64)
        live = np.arange(len(codes))
        while len(live):
            live = live[start[live] > bounds[of[live]]]
            c = codes[start[live] - 1]
            live, c = live[c > 0], c[c > 0]
            both = engine.step(np.concatenate([c, c]), np.concatenate([low[live], high[live]]))
            half = len(both) // 2
            good = both[:half] < both[half:]
            live = live[good]
            low[live], high[live], start[live] = both[:half][good], both[half:][good], start[live] - 1
        inner = np.zeros(len(codes), bool)
        inner[:-1] = (of[1:] == of[:-1]) & (start[1:] <= start[:-1])
        keep = ~inner & (end - start >= min_len)
        yield pa.RecordBatch.from_arrays([ids.take(pa.array(of[keep])), pa.array((start - bounds[of])[keep]), pa.array((end - start)[keep]), pa.array((high - low)[keep])], ["pid", "start", "len", "n"])

    return _patterns(index, patterns, answer, "pid long, start long, len long, n long")


def kgrams(strings: DataFrame, k: int) -> DataFrame:
    """``(gram, n)``: how often each run of k symbols occurs."""
    at = F.explode(F.sequence(F.lit(1), F.col("len") - k + 1))
    return strings.where(F.col("len") >= k).select("s", at.alias("at")).groupBy(F.substring("s", F.col("at"), F.lit(k)).alias("gram")).agg(F.count("*").alias("n"))


def top_kgrams(strings: DataFrame, k: int, n: int) -> DataFrame:
    """The n most frequent runs of k symbols, ties in order of the run."""
    return kgrams(strings, k).orderBy(F.desc("n"), "gram").limit(n)
