"""Licence scans: sparse TF-IDF cosine of passages to templates, then inheritance from the nearest licensed directory.

A passage is a line of a file, or a window of as many words as a template has, wherever it starts and across line breaks; so
notices inside longer lines and wrapped ones are found. Templates are short notices and the bodies of licences, which are cut
into pieces of ``PIECE`` words. A passage's vector has a cell for each template word, weighted by how rare the word is among
all lines, and the length that its other words would add. A body in a file counts before any notice.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.llm import textscan
from corpusbwt.llm.common import batch_of, texts_of, trimmed
from corpusbwt.llm.licence_texts import BODIES
from corpusbwt.session import written

#: Short public notices by licence.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "BSD-3-Clause": "Use of this source code is governed by a BSD-style license.",
    "CC-BY-4.0": "This work is licensed under CC BY 4.0.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "CC0-1.0": "Dedicated to the public domain under CC0 1.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "MIT": "Released under the MIT License.",
    "MPL-2.0": "This file is subject to the Mozilla Public License, version 2.0.",
    "proprietary": "All rights reserved.",
}
LEAST_COSINE = 0.75
#: Words of a body's piece, and of how many words every first one starts a window for it.
PIECE, STEP = 100, 10
#: A window of so few words must end before a line break or another sign than a space, or it is a part of a sentence.
SHORT = 3
_LOWER = np.arange(0x110000, dtype=np.uint32)
_LOWER[65:91] += 32


def _words(texts: list[str]) -> tuple[np.ndarray, ...]:
    """Word hashes, each word's line and whether a plain space follows it, each line's text and their number, in reading order."""
    codes, bounds = textscan.codes_of([t + "\n" for t in texts])
    kind = textscan.classes()[codes]
    starts, ends, _ = textscan.word_spans(_LOWER[codes], bounds, (kind == textscan.LETTER) | (kind == textscan.NUMBER))
    breaks = np.flatnonzero(codes == 10)
    hashes = textscan.span_hashes(_LOWER[codes], starts, ends)
    return hashes, np.searchsorted(breaks, starts), codes[ends] == 32, np.searchsorted(bounds, breaks, "right") - 1, len(breaks)


def _pieces(body: str) -> list[str]:
    words = body.split()
    n = max(1, round(len(words) / PIECE))
    return [" ".join(words[len(words) * i // n : len(words) * (i + 1) // n]) for i in range(n)]


class Templates:
    """Template words and unit vectors under given line counts of the words."""

    def __init__(self, templates: Mapping[str, str] = TEMPLATES, bodies: Mapping[str, str] = BODIES):
        self.names = sorted({*templates, *bodies})
        given = [(n, templates[n]) for n in sorted(templates)] + [(n, p) for n in sorted(bodies) for p in _pieces(bodies[n])]
        self.notices = len(templates)
        self.of = np.array([self.names.index(n) for n, _ in given])
        hashes, line, _, _, _ = _words([" ".join(t.split()) for _, t in given])
        self.size = np.bincount(line, minlength=len(given))
        self.words, back = np.unique(hashes, return_inverse=True)
        self.index = textscan.HashIndex(12)
        self.index.add(self.words, np.arange(len(self.words)))
        self.raw = np.zeros((len(given), len(self.words)))
        np.add.at(self.raw, (line, back), 1)

    def weigh(self, lines: int, seen: np.ndarray) -> None:
        self.idf = np.log((1 + lines) / (1 + seen)) + 1
        self.other = np.log(1.0 + lines) + 1
        scaled = self.raw * self.idf
        self.unit = scaled / np.sqrt((scaled**2).sum(1, keepdims=True))
        self.share = np.hstack([self.unit * self.idf, np.zeros((len(scaled), 1))])  # what a word adds to a product; last: other words
        self.most = self.share[self.notices :].max(0, initial=0)

    def _lengths(self, row: np.ndarray, at: np.ndarray, rows: int) -> np.ndarray:
        """Length of each row's vector, of its words' cells (-1: other words)."""
        known = at >= 0
        cell, n = np.unique(row[known] * len(self.words) + at[known], return_counts=True)
        weight = n * self.idf[cell % len(self.words)]
        return np.sqrt(np.bincount(cell // len(self.words), weight**2, rows) + np.bincount(row[~known], minlength=rows) * self.other**2)

    def _found(self, at: np.ndarray, line: np.ndarray, spaced: np.ndarray, text: np.ndarray, n_lines: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """Of each template that is met: its number, first and last words (exclusive) of the passages, and their cosines."""
        total = len(at)
        edges = np.searchsorted(line, np.arange(n_lines + 1))
        ends = np.searchsorted(text, text, "right")
        place = np.arange(total) - np.searchsorted(text, text)
        sums = lambda x: np.concatenate([[0], np.cumsum(x)])
        squares, most = sums(np.where(at >= 0, self.idf[at] ** 2, self.other**2)), sums(self.most[at])
        # a word counted n times adds n * n to the true square, so these lengths are never too great and no passage is missed
        near = lambda dot, first, last: (dot > 0) & (dot >= (LEAST_COSINE - 1e-9) * np.sqrt(squares[last] - squares[first]))
        grid = np.flatnonzero(place % STEP == 0)
        windows: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for t, size in enumerate(self.size):
            if t < self.notices:
                first = np.flatnonzero(np.arange(total) + size <= ends)
                last = first + size
                if size <= SHORT:
                    free = ~spaced[last - 1]
                    first, last = first[free], last[free]
                first, last = np.concatenate([edges[:-1], first]), np.concatenate([edges[1:], last])
                dots = sums(self.share[t][at])
                dot = dots[last] - dots[first]
            else:
                if size not in windows:
                    first, last = grid, np.minimum(grid + size, ends[grid])
                    held = (2 * (last - first) >= size) & near(most[last] - most[first], first, last)
                    windows[size] = first[held], last[held]
                first, last = windows[size]
                if not len(first):
                    continue
                dot = np.add.reduceat(self.share[t][at[textscan.spread(first, last - first)]], np.cumsum(last - first) - (last - first))
            maybe = np.flatnonzero(near(dot, first, last))
            if not len(maybe):
                continue
            first, last, dot = first[maybe], last[maybe], dot[maybe]
            cosine = dot / self._lengths(np.repeat(np.arange(len(first)), last - first), at[textscan.spread(first, last - first)], len(first))
            good = cosine >= LEAST_COSINE
            if good.any():
                yield t, first[good], last[good], np.round(cosine[good], 9)

    def best(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of each text: the best licence (-1: none) over its passages, the cosine, the share of its words in such passages.

        The licence of whose body most words are found is the best one, without any body that of greatest cosine, the first of equals.
        """
        hashes, line, spaced, owner, n_lines = _words(texts)
        text = owner[line]
        top, high = np.full(len(texts), -1), np.zeros(len(texts))
        covered, place = np.zeros(len(hashes) + 1, np.int64), np.zeros(len(texts), np.int64)
        bodies: dict[tuple[int, int], list] = {}
        for t, first, last, cosine in self._found(self.index.find(hashes), line, spaced, text, n_lines) if len(hashes) else ():
            np.add.at(covered, first, 1)
            np.add.at(covered, last, -1)
            for a, b, c in zip(first, last, cosine, strict=True):
                if t >= self.notices:
                    bodies.setdefault((int(text[a]), int(self.of[t])), []).append((int(a), int(b), float(c)))
                elif (c, -a) > (high[text[a]], -place[text[a]]):
                    top[text[a]], high[text[a]], place[text[a]] = self.of[t], c, a
        most: dict[int, int] = {}
        for (i, name), spans in sorted(bodies.items()):
            n = len(set().union(*(range(a, b) for a, b, _ in spans)))
            if n > most.get(i, 0):
                most[i], top[i], high[i] = n, name, max(c for _, _, c in spans)
        words, inside = np.bincount(text, minlength=len(texts)), np.bincount(text[np.cumsum(covered[:-1]) > 0], minlength=len(texts))
        return top, high, inside / np.maximum(words, 1)


def _each(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    for batch in batches:
        texts = texts_of(batch.column(column))
        for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
            yield batch.slice(lo, hi - lo), texts[lo:hi]


def line_statistics(files: DataFrame, text_col: str, templates: Templates) -> tuple[int, np.ndarray]:
    """Number of lines, and of lines with each template word, over all files."""
    size = len(templates.words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size + 1, np.int64)
        for _, texts in _each(batches, 0):
            hashes, line, _, _, n_lines = _words(texts)
            at = templates.index.find(hashes)
            cells = np.unique(line[at >= 0] * size + at[at >= 0])
            total[:size] += np.bincount(cells % size, minlength=size)
            total[size] += n_lines
        yield batch_of(pa.schema([("word", pa.int32()), ("n", pa.int64())]), [np.arange(size + 1, dtype=np.int32), total])

    rows = files.select(text_col).mapInArrow(run, "word int, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    seen = np.zeros(size + 1, np.int64)
    for r in rows:
        seen[r.word] = r.n
    return int(seen[size]), seen[:size]


def scan(files: DataFrame, path_col: str = "path", text_col: str = "text", *, id_col: str = "doc_id", least_share: float = 0.5) -> DataFrame:
    """Per file: id, path, own licence and cosine (null: none found), directory it inherits from, licence in the end.

    A file in whose licensed passages at least ``least_share`` of its words stand is a licence file of its directory; of several, the
    best match and then the first path counts. A file without a licence of its own takes that of the nearest directory
    above it that has one. Null texts match nothing; a null path has no directory. An empty table gives no rows.
    """
    held = Templates()
    held.weigh(*line_statistics(files, text_col, held))
    kind = files.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in _each(batches, 2):
            schema = pa.schema([("id", batch.schema.types[0]), ("path", pa.string()), ("licence", pa.string()), ("cosine", pa.float64()), ("share", pa.float64())])
            top, high, share = held.best(texts)
            yield batch_of(schema, [batch.column(0), batch.column(1), [held.names[t] if t >= 0 else None for t in top], [round(float(h), 9) if t >= 0 else None for h, t in zip(high, top, strict=True)], share])

    found = written(files.select(id_col, path_col, text_col).mapInArrow(trimmed(run), f"id {kind}, path string, licence string, cosine double, share double"))
    found = found.withColumn("directory", F.regexp_extract("path", "^(.*/)[^/]*$", 1))
    given = found.where((F.col("share") >= least_share) & F.col("licence").isNotNull()).groupBy("directory").agg(F.min_by("licence", F.struct(-F.col("cosine"), "path")).alias("given"))
    parts = F.split(F.regexp_replace("directory", "/$", ""), "/")
    above = found.select("directory").where("directory <> ''").distinct().select("directory", F.explode(F.transform(F.sequence(F.lit(1), F.size(parts)), lambda n: F.concat(F.array_join(F.slice(parts, 1, n), "/"), F.lit("/")))).alias("ancestor"))
    nearest = above.join(given.withColumnRenamed("directory", "ancestor"), "ancestor").groupBy("directory").agg(F.max_by(F.struct("ancestor", "given"), F.length("ancestor")).alias("near"))
    out = found.join(nearest, "directory", "left")
    inherits = F.col("licence").isNull()
    return out.select(F.col("id").alias(id_col), "path", "licence", "cosine", F.when(inherits, F.col("near.ancestor")).alias("inherited_from"), F.coalesce("licence", F.col("near.given")).alias("effective"))
