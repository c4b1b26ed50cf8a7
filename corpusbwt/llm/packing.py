"""Packing along a space-filling curve: neighbouring documents share training sequences.

Each document's hashed bag of pieces is projected to a few dimensions, standardised by corpus-wide moments and turned
into a Hilbert key. Documents are range-sorted by that key and laid end to end; every ``limit`` ids make a sequence. The
rest of a sorted partition is cut into sequences whose lengths are powers of two, so nothing is padded at all.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.taskcontext import TaskContext

from corpusbwt.llm import textscan, vocabularies
from corpusbwt.llm.common import batch_of, texts_of, trimmed
from corpusbwt.llm.piece_tokens import tokenizer
from corpusbwt.session import written

DIMENSIONS, BITS, BUCKETS = 3, 10, 1024


def hilbert_key(axes: np.ndarray, bits: int) -> np.ndarray:
    """Position along the Hilbert curve of integer points (n, dimensions), each coordinate below 2**bits."""
    x = axes.astype(np.uint64).T.copy()
    n = len(x)
    top = 1 << (bits - 1)
    q = top
    while q > 1:
        low = np.uint64(q - 1)
        for i in range(n):
            high = (x[i] & np.uint64(q)) != 0
            swap = np.where(high, np.uint64(0), (x[0] ^ x[i]) & low)
            x[0] = np.where(high, x[0] ^ low, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    flip = np.zeros(x.shape[1], np.uint64)
    q = top
    while q > 1:
        flip = np.where((x[n - 1] & np.uint64(q)) != 0, flip ^ np.uint64(q - 1), flip)
        q >>= 1
    x ^= flip
    key = np.zeros(x.shape[1], np.uint64)
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << np.uint64(1)) | ((x[i] >> np.uint64(b)) & np.uint64(1))
    return key.astype(np.int64)


@cache
def _projection() -> np.ndarray:
    return np.random.default_rng(20).standard_normal((BUCKETS, DIMENSIONS))


def _coordinates(hashes: np.ndarray, pieces: np.ndarray) -> np.ndarray:
    """Projected, length-normalised bags of hashed pieces; a text without pieces lies at the origin."""
    n = len(pieces)
    owner = np.repeat(np.arange(n), pieces)
    out = np.zeros((n, DIMENSIONS))
    for lo in range(0, n, 256):
        part = (owner >= lo) & (owner < lo + 256)
        cell = (owner[part] - lo) * BUCKETS + (hashes[part] % np.uint64(BUCKETS)).astype(np.int64)
        bag = np.sqrt(np.bincount(cell, minlength=256 * BUCKETS).reshape(256, BUCKETS))[: n - lo]
        norm = np.sqrt((bag * bag).sum(1, keepdims=True))
        out[lo : lo + 256] = (bag / np.maximum(norm, 1)) @ _projection()
    return out


def tokenised(df: DataFrame, id_col: str, text_col: str, path: str, end_id: int) -> DataFrame:
    """Per row: id, ids (little-endian unsigned 16 or 32 bits), their number and the projected coordinates."""
    kind = df.schema[id_col].dataType.simpleString()
    names = [f"c{i}" for i in range(DIMENSIONS)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        engine = tokenizer(path)
        schema = None
        for batch in batches:
            texts = texts_of(batch.column(1))
            if schema is None:
                schema = pa.schema([("id", batch.schema.types[0]), ("ids", pa.binary()), ("n_tokens", pa.int64()), *((n, pa.float64()) for n in names)])
            for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
                ids, per, hashes, pieces = engine.encode(texts[lo:hi])
                ends = np.cumsum(per)
                ids = np.insert(ids, ends, end_id).astype("<u4")
                ends = np.concatenate([[0], ends + np.arange(1, len(per) + 1)])
                raw = ids.tobytes()
                xyz = _coordinates(hashes, pieces)
                yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), [_narrow(raw[4 * a : 4 * b]) for a, b in zip(ends[:-1], ends[1:], strict=True)], per + 1, *xyz.T])

    return df.select(id_col, text_col).mapInArrow(trimmed(run), f"id {kind}, ids binary, n_tokens long, {', '.join(f'{n} double' for n in names)}")


def _narrow(raw: bytes) -> bytes:
    """Ids as 16 bits behind a zero byte if all fit, else as 32 bits behind a one."""
    ids = np.frombuffer(raw, "<u4")
    return b"\1" + raw if len(ids) and ids.max() > 0xFFFF else b"\0" + ids.astype("<u2").tobytes()


def _wide(raw: bytes) -> np.ndarray:
    return np.frombuffer(raw, "<u4" if raw[0] else "<u2", offset=1).astype("<u4")


def with_curve_key(tokens: DataFrame) -> DataFrame:
    """Adds ``curve``: the Hilbert key of coordinates standardised by mean and deviation over all documents."""
    names = [f"c{i}" for i in range(DIMENSIONS)]
    moments = tokens.agg(*(f(n).alias(f"{k}{n}") for n in names for k, f in (("m", F.avg), ("s", F.stddev_pop)))).first()
    mean = np.array([moments[f"m{n}"] or 0.0 for n in names])
    spread = np.array([moments[f"s{n}"] or 1.0 for n in names])

    @F.pandas_udf("long")
    def key(a: pd.Series, b: pd.Series, c: pd.Series) -> pd.Series:
        z = (np.stack([a, b, c], 1) - mean) / spread
        cells = np.clip((z / 3 + 1) / 2 * (1 << BITS), 0, (1 << BITS) - 1)
        return pd.Series(hilbert_key(cells.astype(np.int64), BITS))

    return tokens.withColumn("curve", key(*names)).drop(*names)


def _pieces(limit: int, with_ids: bool):
    """Cuts a sorted partition's ids into sequences; only one open sequence is held at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        sequence, filled = part << 40, 0
        held: list[tuple] = []  # of the open sequence: id, start, ids, number of the document's ids
        rows: list[tuple] = []
        schema = None

        def place(sizes: list[int]) -> None:
            nonlocal sequence
            queue = held[::-1]
            for size in sizes:
                at = 0
                while at < size:
                    key, start, ids, n = queue.pop()
                    take = min(size - at, len(ids))
                    if take < len(ids):
                        queue.append((key, start + take, ids[take:], n))
                    body = ids[:take].tobytes()
                    rows.append((key, start, take, zlib.crc32(body), n, sequence, at, *([body] if with_ids else [])))
                    at += take
                sequence += 1
            held.clear()

        def out() -> pa.RecordBatch:
            made = batch_of(schema, list(zip(*rows, strict=True)) if rows else [[] for _ in schema])
            rows.clear()
            return made

        for batch in batches:
            if schema is None:
                schema = pa.schema([("doc_id", batch.schema.types[0]), *((n, pa.int64()) for n in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")), *([("ids", pa.binary())] if with_ids else [])])
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = _wide(raw)
                n, at = len(ids), 0
                while at < n:
                    take = min(limit - filled, n - at)
                    held.append((key, at, ids[at : at + take], n))
                    filled, at = filled + take, at + take
                    if filled == limit:
                        place([limit])
                        filled = 0
                if len(rows) >= 4096:
                    yield out()
        if filled:
            place([1 << b for b in range(filled.bit_length() - 1, -1, -1) if filled >> b & 1])
        if rows:
            yield out()

    return run


def pack(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, path: str | None = None, end_id: int = 1, limit: int = 2048, with_ids: bool = False) -> DataFrame:
    """Pieces of documents in sequences of at most ``limit`` ids, neighbours on the curve together.

    Every document is its text's ids and ``end_id``; a null or empty text is ``end_id`` alone. Rows with a null id and
    repeated rows are packed as documents of their own; an empty table gives no rows. Sequences hold exactly ``limit``
    ids, or a smaller power of two at the end of a sorted partition. With ``with_ids`` each piece carries its ids
    (little-endian unsigned 32 bits).
    """
    kind = df.schema[id_col].dataType.simpleString()
    tokens = written(tokenised(df, id_col, text_col, path or vocabularies.default_path("byte_bpe_50k.json"), end_id))
    keyed = with_curve_key(tokens).withColumn("tie", F.xxhash64("ids"))
    order = ["curve", "id", "tie"]
    laid = keyed.repartitionByRange(*order).sortWithinPartitions(*order).select("id", "ids")
    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return laid.mapInArrow(trimmed(_pieces(limit, with_ids)), schema + (", ids binary" if with_ids else ""))
