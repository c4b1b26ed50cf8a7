"""Streams of strings appended to an index, dense numbers across batches, and windows over symbol events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.plans import builder
from corpusbwt.plans.store import StoredIndex


def append_stream(stream: DataFrame, index_path: str, checkpoint: str, *, text_col: str, order_cols: list[str], watermark: tuple[str, str] | None = None, ids: list[str] | None = None, available_now: bool = True):
    """A query that appends every micro-batch as a block; its checkpoint and the batch's number in the manifest
    make a replay do nothing.

    Strings count in order of arrival, late ones included; with a watermark and ids, repeats within it are dropped.
    """
    if watermark:
        stream = stream.withWatermark(*watermark)
        if ids:
            stream = stream.dropDuplicatesWithinWatermark(ids)

    def apply(batch: DataFrame, batch_id: int) -> None:
        index = StoredIndex.open(batch.sparkSession, index_path)
        builder.append(index, batch, text_col, order_cols, batch_id=batch_id, source=checkpoint)

    writer = stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def symbol_windows(events: DataFrame, kind: str = "tumbling", *, ts: str = "ts", symbol: str = "event_type", size: str = "1 hour", slide: str = "15 minutes", gap: str = "10 minutes", watermark: str | None = None) -> DataFrame:
    """``(start, end, symbol, n)`` in tumbling, sliding or session windows; session windows are kept for each symbol."""
    if watermark:
        events = events.withWatermark(ts, watermark)
    at = {"tumbling": lambda: F.window(ts, size), "sliding": lambda: F.window(ts, size, slide), "session": lambda: F.session_window(ts, gap)}[kind]()
    return events.groupBy(at.alias("_at"), F.col(symbol).alias("symbol")).agg(F.count("*").alias("n")).select(F.col("_at.start").alias("start"), F.col("_at.end").alias("end"), "symbol", "n")


def assign_sid(stream: DataFrame, source_col: str, text_col: str) -> DataFrame:
    """``(source, sid, s)``: dense numbers by source across batches, from a counter kept as state."""
    import pandas as pd

    def number(key, frames, state):
        at = state.get[0] if state.exists else 0
        for frame in frames:
            n = len(frame)
            yield pd.DataFrame({"source": key[0], "sid": range(at, at + n), "s": frame[text_col]})
            at += n
        state.update((at,))

    return stream.groupBy(source_col).applyInPandasWithState(number, "source string, sid long, s string", "next long", "append", "NoTimeout")
