"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

A text is a sparse vector: its distinct words, hashed, at equal weight and unit length together, and one cell for the bin
of each structure statistic and each metadata column. The score is a logistic function of a linear part and all pairwise
interactions of rank ``RANK``, summed in linear time: half of (square of sums - sum of squares) in each factor.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.llm import textscan
from corpusbwt.llm.common import batch_of, texts_of, trimmed

WORD_BITS, BINS, RANK = 15, 16, 8
WORDS = 1 << WORD_BITS
#: Labelled documents that training takes at most, those with the smallest hashes of their ids; the documented bound.
MOST_TRAINED = 12_000
THRESHOLD = 0.3
_MARKS = "#$%&*@~^|!"


@dataclass
class Machine:
    """Bias, linear weights and factors."""

    bias: float
    linear: np.ndarray
    factors: np.ndarray

    def margins(self, cells: np.ndarray, values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Scores before the logistic; every row has a cell at least."""
        scaled = self.factors[cells] * values[:, None]
        sums = np.add.reduceat(scaled, starts)
        squares = np.add.reduceat(scaled * scaled, starts)
        return self.bias + np.add.reduceat(self.linear[cells] * values, starts) + 0.5 * (sums * sums - squares).sum(1)

    def scores(self, cells: np.ndarray, values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margins(cells, values, starts), -30, 30)))


def _share(hits: np.ndarray, bounds: np.ndarray, out_of: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(hits, dtype=np.int64)])
    return np.diff(total[bounds]) / np.maximum(out_of, 1)


def features(texts: list[str], metadata: Sequence[np.ndarray] = ()) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells, values and each text's first cell, for whole texts; null metadata (NaN) has the last bin."""
    codes, bounds = textscan.codes_of(texts)
    kind = textscan.classes()[codes]
    n, sizes = len(texts), np.diff(bounds)
    starts, ends, owner = textscan.word_spans(codes, bounds, kind != textscan.SPACE)
    hashes = textscan.span_hashes(codes, starts, ends)
    first = np.searchsorted(owner, np.arange(n + 1))
    words = np.diff(first)
    cell = np.unique(owner * WORDS + (hashes >> np.uint64(64 - WORD_BITS)).astype(np.int64))
    row = cell // WORDS
    distinct = np.bincount(row, minlength=n)
    again = np.zeros(len(hashes), bool)
    again[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
    letters = kind == textscan.LETTER
    small = codes < 128
    upper = small & (codes >= 65) & (codes <= 90)
    tail = codes[ends - 1] if len(ends) else codes[:0]
    lines = np.diff(np.concatenate([[0], np.cumsum(codes == 10)])[bounds]) + 1
    root = lambda hits, out_of=sizes: np.sqrt(_share(hits, bounds, out_of))
    by_word = lambda hits: _share(hits, first, words)
    stats = [
        root(letters),
        root(upper),
        root(kind == textscan.NUMBER),
        root(kind == textscan.OTHER),
        root(kind == textscan.SPACE),
        *(root(codes == ord(c)) for c in _MARKS),
        distinct / np.maximum(words, 1),
        by_word(again),
        by_word(textscan.classes()[tail] == textscan.OTHER),
        np.minimum(_share(ends - starts, first, words) / 16, 1),
        np.log2(words + 1) / 20,
        np.log2(sizes / lines + 1) / 16,
        np.log2(lines) / 16,
        *(np.where(np.isnan(m), 1, np.log2(np.maximum(np.nan_to_num(m), 0) + 1) / 32) for m in metadata),
    ]
    bins = np.clip((np.stack(stats, 1) * (BINS - 1)).astype(np.int64), 0, BINS - 1)
    bins += WORDS + np.arange(len(stats)) * BINS
    width = len(stats)
    cells = np.concatenate([cell % WORDS, bins.ravel()])
    rows = np.concatenate([row, np.repeat(np.arange(n), width)])
    values = np.concatenate([1 / np.sqrt(np.maximum(distinct, 1))[row], np.ones(n * width)])
    order = np.argsort(rows, kind="stable")
    at = np.cumsum(distinct + width) - (distinct + width)
    return cells[order], values[order], at


def n_cells(n_metadata: int) -> int:
    return WORDS + (12 + len(_MARKS) + n_metadata) * BINS


def fit(cells: list[np.ndarray], values: list[np.ndarray], labels: np.ndarray, size: int, *, epochs: int = 6, batch: int = 128, rate: float = 0.05, decay: float = 1e-5) -> Machine:
    """A machine trained by adaptive gradient steps on the logistic loss; no labels give a score of one half."""
    rng = np.random.default_rng(11)
    model = Machine(0.0, np.zeros(size), rng.normal(0, 0.01, (size, RANK)))
    held_linear, held_factors, held_bias = np.full(size, 1e-2), np.full((size, RANK), 1e-2), 1e-2
    n = len(labels)
    for _ in range(epochs if n else 0):
        order = rng.permutation(n)
        for lo in range(0, n, batch):
            pick = order[lo : lo + batch]
            count = np.array([len(cells[i]) for i in pick])
            at = np.concatenate([cells[i] for i in pick])
            x = np.concatenate([values[i] for i in pick])
            starts = np.cumsum(count) - count
            slope = model.scores(at, x, starts) - labels[pick]
            each = np.repeat(slope, count) / len(pick)
            scaled = model.factors[at] * x[:, None]
            sums = np.repeat(np.add.reduceat(scaled, starts), count, axis=0)
            touched, back = np.unique(at, return_inverse=True)
            linear = np.bincount(back, each * x) + decay * model.linear[touched]
            step = (each * x)[:, None] * (sums - scaled)
            factors = np.stack([np.bincount(back, step[:, f]) for f in range(RANK)], 1) + decay * model.factors[touched]
            held_linear[touched] += linear**2
            held_factors[touched] += factors**2
            held_bias += slope.mean() ** 2
            model.linear[touched] -= rate * linear / np.sqrt(held_linear[touched])
            model.factors[touched] -= rate * factors / np.sqrt(held_factors[touched])
            model.bias -= rate * slope.mean() / np.sqrt(held_bias)
    return model


def _meta(batch: pa.RecordBatch, lo: int, hi: int) -> list[np.ndarray]:
    return [batch.column(i).slice(lo, hi - lo).to_numpy(zero_copy_only=False).astype(float) for i in range(2, batch.num_columns)]


def _spans(batch: pa.RecordBatch) -> Iterator[tuple[int, int, list[str]]]:
    texts = texts_of(batch.column(1))
    for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
        yield lo, hi, texts[lo:hi]


def _inputs(df: DataFrame, first: str, text_col: str, metadata: Sequence[str]) -> DataFrame:
    return df.select(first, text_col, *(F.col(m).cast("double") for m in metadata))


def train(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", metadata: Sequence[str] = ("n_chars",), most: int = MOST_TRAINED) -> Machine:
    """A machine fitted on labelled documents whose crc32 of the id, as text, isn't divisible by five.

    Labels that repeat an id are averaged and rounded; rows with a null id or label are left out. At most ``most`` labelled
    documents are taken (those with the smallest hashed ids), which bounds what reaches the driver.
    """
    known = labels.select(F.col(id_col), F.col(label_col).cast("double").alias("label_of_row")).dropna()
    known = known.where(F.crc32(F.col(id_col).cast("string")) % 5 != 0).groupBy(id_col).agg(F.round(F.avg("label_of_row")).alias("label_of_row"))
    chosen = known.orderBy(F.xxhash64(id_col), id_col).limit(most)
    rows = _inputs(docs.select(id_col, text_col, *metadata).join(F.broadcast(chosen), id_col), "label_of_row", text_col, metadata)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("label", pa.float64()), ("cells", pa.binary())])
        for batch in batches:
            for lo, hi, texts in _spans(batch):
                cells, _, at = features(texts, _meta(batch, lo, hi))
                parts = np.split(cells.astype("<u2"), at[1:])
                yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), [p.tobytes() for p in parts]])

    got = rows.mapInArrow(trimmed(run), "label double, cells binary").toArrow()
    pairs = sorted(zip(got.column(0).to_pylist(), got.column(1).to_pylist(), strict=True), key=lambda p: (p[1], p[0]))
    cells = [np.frombuffer(raw, "<u2").astype(np.int64) for _, raw in pairs]
    values = [np.where(c < WORDS, 1 / np.sqrt(max(1, int((c < WORDS).sum()))), 1.0) for c in cells]
    return fit(cells, values, np.array([label for label, _ in pairs]), n_cells(len(metadata)))


def _short(model: Machine) -> Machine:
    """The machine in single precision, as it is sent to tasks."""
    return Machine(model.bias, model.linear.astype(np.float32), model.factors.astype(np.float32))


def scored(docs: DataFrame, model: Machine, *, id_col: str = "doc_id", text_col: str = "text", metadata: Sequence[str] = ("n_chars",)) -> DataFrame:
    """Per row: doc_id, held_out, score, predicted. Null texts are scored as empty ones; a null id isn't held out."""
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(_short(model))
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("score", pa.float64())])
            for lo, hi, texts in _spans(batch):
                yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), sent.value.scores(*features(texts, _meta(batch, lo, hi)))])

    out = _inputs(docs, id_col, text_col, metadata).mapInArrow(trimmed(run), f"doc_id {kind}, score double")
    fold = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return out.select("doc_id", fold.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def accepted(docs: DataFrame, model: Machine, *, text_col: str = "text", metadata: Sequence[str] = ("n_chars",)) -> DataFrame:
    """The rows of ``docs``, whole and with all columns, whose score reaches the threshold.

    A null text is scored as an empty one, null metadata has a bin of its own; repeated rows are scored alike and an empty
    table gives no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(_short(model))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.Series]:
        for columns in frames:  # one struct a row: text, metadata
            texts = [t or "" for t in columns.iloc[:, 0]]
            meta = [columns.iloc[:, i].to_numpy(float) for i in range(1, columns.shape[1])]
            out = np.zeros(len(texts))
            for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
                out[lo:hi] = sent.value.scores(*features(texts[lo:hi], [m[lo:hi] for m in meta]))
            yield pd.Series(out)

    @F.pandas_udf("double")
    def score(frames: Iterator[pd.DataFrame]) -> Iterator[pd.Series]:
        yield from trimmed(run)(frames)

    held = F.struct(F.col(text_col).alias("text"), *(F.col(m).cast("double").alias(f"meta{i}") for i, m in enumerate(metadata)))
    return docs.where(score(held) >= THRESHOLD)
