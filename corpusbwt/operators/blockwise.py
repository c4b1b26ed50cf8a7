"""Searches over blocks of strings that are indexed side by side, each by one task, for a set that need not be one transform.

A block has a transform and an alphabet of its own and the places of every ``RATE``-th suffix; it is stored as one row. Blocks
share nothing: counts add up, places and strings are those of all blocks, and the longest match is the longest of any block.
So nothing is ranked in what was indexed before, inserted, or sent to tasks but the patterns.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusbwt.functions.kernels import RankEngine, flat_codes, suffix_order, symbols_before, with_terminators
from corpusbwt.operators.fm import _codes, intervals
from corpusbwt.session import ship, written

#: Symbols of a block (about 70 bytes each while it is sorted); a longer string is a block of its own.
BLOCK = 1 << 20
RATE = 32
#: Symbols of patterns that one pass over the blocks answers.
MOST_PATTERNS = 1 << 24


class Block:
    """A stored block: strings' ids, code points, symbols in suffix order, and which rows have known places."""

    def __init__(self, ids: pa.Array, points: bytes, width: int, symbols: bytes, marks: bytes, owners: bytes, places: bytes):
        self.ids, self.points = ids, np.frombuffer(points, "<u4")
        self.symbols = np.frombuffer(symbols, f"<u{width}")
        self.known = np.unpackbits(np.frombuffer(marks, np.uint8), count=len(self.symbols)).view(bool)
        self.owners, self.places = np.frombuffer(owners, np.int32), np.frombuffer(places, np.int32)

    def engine(self) -> RankEngine:
        """Counters as near as they stay within eight bytes a symbol."""
        sigma = len(self.points)
        return RankEngine(self.symbols, sigma, max(64, 1 << (sigma // 2).bit_length()))

    def located(self, engine: RankEngine, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """String and place of the suffixes in some rows, which walk back to rows of known places."""
        row, far = row.copy(), np.zeros(len(row), np.int64)
        live = np.flatnonzero(~self.known[row])
        while len(live):
            row[live] = engine.step(self.symbols[row[live]].astype(np.int64), row[live])
            far[live] += 1
            live = live[~self.known[row[live]]]
        at = np.cumsum(self.known)[row] - 1
        return self.owners[at], self.places[at] + far

    def strings(self) -> list[str]:
        """All strings: their ends are read from the terminators' rows back to known places, the rest from these on."""
        n, m = len(self.symbols), len(self.ids)
        order = np.argsort(self.symbols, kind="stable")
        back = np.empty(n, np.int64)
        back[order] = np.arange(n)
        row, far, live, tails = np.arange(m), np.zeros(m, np.int64), np.arange(m), []
        while len(live := live[~self.known[row[live]]]):
            tails.append((live, self.symbols[row[live]]))
            row[live] = back[row[live]]
            far[live] += 1
        size = self.places[np.cumsum(self.known)[row] - 1] + far
        first = np.cumsum(size) - size
        text = np.zeros(n - m, self.symbols.dtype)
        for t, (own, symbol) in enumerate(tails):
            text[first[own] + size[own] - 1 - t] = symbol
        inner = self.places > 0
        row, at = np.flatnonzero(self.known)[inner], (first[self.owners] + self.places)[inner]
        for t in range(1, RATE + 1):
            text[at - t] = self.symbols[row]
            row = back[row]
        whole = np.concatenate([np.zeros(1, "<u4"), self.points])[text].tobytes().decode("utf-32-le", "surrogatepass")
        return [whole[a : a + s] for a, s in zip(first.tolist(), size.tolist(), strict=True)]


def _indexed(ids: list, texts: list[str]) -> list:
    """The columns of one block."""
    raw, bounds = flat_codes(texts)
    seen = np.zeros(int(raw.max(initial=0)) + 1, bool)
    seen[raw] = True
    points = np.flatnonzero(seen)
    codes = np.cumsum(seen)[raw]
    order = suffix_order(codes, bounds)[0]
    starts = bounds[:-1] + np.arange(len(texts))
    own = with_terminators(codes, bounds)[1][order]
    k = order - starts[own]
    known = k % RATE == 0
    symbols = symbols_before(codes, bounds)[order].astype(f"<u{np.min_scalar_type(len(points)).itemsize}")
    return [ids, points.astype("<u4").tobytes(), symbols.itemsize, symbols.tobytes(), np.packbits(known).tobytes(), own[known].astype(np.int32).tobytes(), k[known].astype(np.int32).tobytes()]


def block_index(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The stored blocks of a table's texts, null ones as empty; a task cuts its rows into blocks, so none is moved."""
    ship(df.sparkSession)
    kind, most = df.schema[id_col].dataType.simpleString(), BLOCK

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts, held, schema = [], [], 0, None

        def made() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(_indexed(ids, texts), (pa.list_(schema.types[0]), pa.binary(), pa.int32(), *[pa.binary()] * 4), strict=True)], ["ids", "points", "width", "symbols", "marks", "owners", "places"])

        for batch in batches:
            schema = batch.schema
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                size = len(text or "") + 1
                if ids and held + size > most:
                    yield made()
                    ids, texts, held = [], [], 0
                ids.append(i)
                texts.append(text or "")
                held += size
        if ids:
            yield made()

    return written(df.select(id_col, text_col).mapInArrow(run, f"ids array<{kind}>, points binary, width int, symbols binary, marks binary, owners binary, places binary"))


def _each(blocks: DataFrame, answer: Callable, schema: str, last: Callable | None = None) -> DataFrame:
    """Runs ``answer(block)``, which gives a record batch or nothing, over all blocks; ``last()`` after a task's last one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                if (made := answer(Block(batch.column(0)[i].values, *(batch.column(j)[i].as_py() for j in range(1, batch.num_columns))))) is not None:
                    yield made
        if last is not None:
            yield last()

    return blocks.mapInArrow(run, schema)


def _asked(patterns: DataFrame) -> tuple[DataFrame, list[tuple[int, list[str]]]]:
    """Patterns numbered by ``at``, and parts of them: the first one's number and their texts (a null one as empty)."""
    held = patterns.select("pid", "pattern").toArrow()
    texts = [t or "" for t in held.column(1).to_pylist()]
    parts, lo, size = [], 0, 0
    for i, text in enumerate(texts):
        if i > lo and size + len(text) > MOST_PATTERNS:
            parts.append((lo, texts[lo:i]))
            lo, size = i, 0
        size += len(text)
    parts.append((lo, texts[lo:]))
    rows = list(enumerate(held.column(0).to_pylist()))
    return patterns.sparkSession.createDataFrame(rows, f"at long, pid {patterns.schema['pid'].dataType.simpleString()}"), parts


def _answers(parts: list, answered: Callable[[int, list[str]], DataFrame]) -> DataFrame:
    out = None
    for part in parts:
        out = answered(*part) if out is None else out.union(answered(*part))
    return out


def count(blocks: DataFrame, patterns: DataFrame) -> DataFrame:
    """``(pid, n)``: occurrences of each pattern in all strings; an empty pattern occurs at every suffix."""
    asked, parts = _asked(patterns)

    def answered(first: int, texts: list[str]) -> DataFrame:
        total = np.zeros(len(texts), np.int64)

        def answer(block: Block) -> None:
            low, high = intervals(block.engine(), *_codes(texts, block.points))
            total[:] += high - low

        def last() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(first + np.arange(len(total))), pa.array(total)], ["at", "n"])

        return _each(blocks, answer, "at long, n long", last)

    sums = _answers(parts, answered).groupBy("at").agg(F.sum("n").alias("n"))
    return asked.join(sums, "at", "left").select("pid", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def locate(blocks: DataFrame, patterns: DataFrame) -> DataFrame:
    """``(pid, id, k)`` of every occurrence."""
    asked, parts = _asked(patterns)
    kind = blocks.schema["ids"].dataType.elementType.simpleString()

    def answered(first: int, texts: list[str]) -> DataFrame:
        def answer(block: Block) -> pa.RecordBatch | None:
            engine = block.engine()
            low, high = intervals(engine, *_codes(texts, block.points))
            found = np.repeat(np.arange(len(low)), high - low)
            if not len(found):
                return None
            edges = np.cumsum(high - low)
            row = np.arange(len(found)) + np.repeat(low - (edges - (high - low)), high - low)
            own, k = block.located(engine, row)
            return pa.RecordBatch.from_arrays([pa.array(first + found), block.ids.take(pa.array(own)), pa.array(k)], ["at", "id", "k"])

        return _each(blocks, answer, f"at long, id {kind}, k long")

    return _answers(parts, answered).join(asked, "at").select("pid", "id", "k")


def absent(blocks: DataFrame, patterns: DataFrame) -> DataFrame:
    """Patterns that occur nowhere."""
    return patterns.join(count(blocks, patterns).where("n > 0").select("pid").distinct(), "pid", "left_anti")


def invert(blocks: DataFrame) -> DataFrame:
    """``(id, s)``: all strings, read back from their transforms."""
    kind = blocks.schema["ids"].dataType.elementType.simpleString()
    return _each(blocks, lambda block: pa.RecordBatch.from_arrays([block.ids, pa.array(block.strings(), pa.string())], ["id", "s"]), f"id {kind}, s string")


def shared(blocks: DataFrame, patterns: DataFrame, min_len: int) -> DataFrame:
    """``(pid, start, len, n)``: maximal passages of each pattern, of ``min_len`` symbols or more, that occur in a string.

    In every block a match grows from every end to the left until its interval is empty. The longest of all blocks stays,
    with its occurrences in those that have it; matches inside the one of the next end are dropped.
    """
    asked, parts = _asked(patterns)

    def answered(first: int, texts: list[str]) -> DataFrame:
        def answer(block: Block) -> pa.RecordBatch | None:
            engine = block.engine()
            codes, bounds = _codes(texts, block.points)
            of, end = np.repeat(np.arange(len(texts)), np.diff(bounds)), np.arange(len(codes)) + 1
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
            keep = np.flatnonzero((end - start >= min_len) & (end > start))
            if not len(keep):
                return None
            base = bounds[of[keep]]
            return pa.RecordBatch.from_arrays([pa.array(first + of[keep]), pa.array(end[keep] - base), pa.array(start[keep] - base), pa.array((high - low)[keep])], ["at", "end", "start", "n"])

        return _each(blocks, answer, "at long, end long, start long, n long")

    sums = _answers(parts, answered).groupBy("at", "end", "start").agg(F.sum("n").alias("n"))
    longest = sums.groupBy("at", "end").agg(F.min(F.struct("start", "n")).alias("x")).select("at", "end", "x.start", "x.n")
    after = Window.partitionBy("at").orderBy("end")
    told = longest.select("*", F.lead("end").over(after).alias("_end"), F.lead("start").over(after).alias("_start"))
    outer = told.where(~F.coalesce((F.col("_end") == F.col("end") + 1) & (F.col("_start") <= F.col("start")), F.lit(False)))
    return outer.join(asked, "at").select("pid", "start", (F.col("end") - F.col("start")).alias("len"), "n")
