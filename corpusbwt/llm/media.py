"""Media columns: texts stored losslessly as WebP images, read back, hashed and described.

A payload is a text's UTF-8 bytes, filled up with bytes 255 to a positive multiple of 576; every 576 bytes are a row of 192
opaque pixels. A long payload is a series of images, so memory stays bounded whatever a text's length. Each image is stored
as literals or with back-references, whichever is shorter.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from corpusbwt.llm import webp
from corpusbwt.llm.common import batch_of, texts_of

UNIT, WIDTH = 576, 192
ROWS = 2048
#: From so many bytes on, an image has a prefix code of its own; below, the code of prose is shorter together with it.
OWN_CODE = 1 << 14


def payload_of(text: str) -> bytes:
    raw = text.encode("utf-8", "surrogatepass")
    return raw + b"\xff" * (UNIT - len(raw) % UNIT if len(raw) % UNIT or not raw else 0)


def stored(payload: bytes) -> bytes:
    """The payload's WebP files, one after the other."""
    step = UNIT * ROWS
    parts = [payload[i : i + step] for i in range(0, len(payload), step)]
    return b"".join(webp.encode_bytes(p, WIDTH, len(p) // UNIT, own_code=len(p) >= OWN_CODE) for p in parts)


def pixels_of(media: bytes) -> np.ndarray:
    """All pixels of a series of WebP files (rows, width, 4)."""
    out, at = [], 0
    while at < len(media):
        pixels, at = webp.decode(media, at)
        out.append(pixels)
    return np.concatenate(out) if len(out) > 1 else out[0]


def feature_of(pixels: np.ndarray) -> str:
    """Size, mean of each colour in thousandths, and a 16-bin histogram of all samples in 255ths."""
    rgb = pixels[..., 1:]
    sums = rgb.sum((0, 1), dtype=np.int64)
    n = rgb.shape[0] * rgb.shape[1]
    bins = np.bincount(rgb.ravel() >> 4, minlength=16)
    return f"{rgb.shape[1]}x{rgb.shape[0]};" + ",".join(str(int(s) * 1000 // n) for s in sums) + ";" + bytes((bins * 255 // (3 * n)).astype(np.uint8)).hex()


def encoded(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_bytes of the text (null: none) and its stored form ``media``."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("n_bytes", pa.int64()), ("media", pa.binary())])
            texts = texts_of(batch.column(1))
            for lo in range(0, len(texts), 256):
                part = texts[lo : lo + 256]
                yield batch_of(schema, [batch.column(0).slice(lo, len(part)), [len(t.encode("utf-8", "surrogatepass")) for t in part], [stored(payload_of(t)) for t in part]])

    return df.select(id_col, text_col).mapInArrow(run, f"doc_id {kind}, n_bytes long, media binary")


def decoded(df: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """Per row of WebP media: doc_id, width, height and ``pixels`` (samples in the order alpha, red, green, blue)."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("width", pa.int32()), ("height", pa.int32()), ("pixels", pa.binary())])
            for lo in range(0, batch.num_rows, 256):
                images = [pixels_of(m) if m else None for m in batch.column(1).slice(lo, 256).to_pylist()]
                yield batch_of(schema, [batch.column(0).slice(lo, 256), *([x.shape[i] if x is not None else None for x in images] for i in (1, 0)), [x.tobytes() if x is not None else None for x in images]])

    return df.select(id_col, media_col).mapInArrow(run, f"doc_id {kind}, width int, height int, pixels binary")


def described(media: DataFrame) -> DataFrame:
    """Digests and features of stored media, all but the text's size from the bytes read back."""
    kind = media.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])
            for lo in range(0, batch.num_rows, 256):
                rows = []
                for m in batch.column(2).slice(lo, 256).to_pylist():
                    pixels = pixels_of(m)
                    payload = np.ascontiguousarray(pixels[..., 1:]).tobytes()
                    rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(m), hashlib.sha256(m).hexdigest(), feature_of(pixels)))
                yield batch_of(schema, [batch.column(0).slice(lo, 256), batch.column(1).slice(lo, 256), *zip(*rows, strict=True)])

    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def media_columns(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Texts stored as media and described from what is read back.

    Null and empty texts are one row of pixels of 255. Equal texts have equal media. Rows are kept as they come, with null
    or repeated ids; an empty table gives no rows.
    """
    return described(encoded(df, id_col, text_col))

