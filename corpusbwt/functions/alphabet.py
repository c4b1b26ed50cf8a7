"""Ordered alphabets: dense codes for symbols, and symbols packed into few bits."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Alphabet:
    """Code points in order; a symbol's code is its place from 1 on, and 0 is the terminator."""

    points: tuple[int, ...]

    @classmethod
    def from_strings(cls, df: DataFrame, col: str) -> Alphabet:
        """The code points that occur; their number is bounded by the script, not by the data."""
        rows = df.select(F.explode(F.array_distinct(F.split(col, ""))).alias("symbol")).where("symbol <> ''").distinct().select(F.ascii("symbol").alias("cp")).orderBy("cp").collect()
        return cls(tuple(r.cp for r in rows))

    @classmethod
    def dna(cls) -> Alphabet:
        return cls(tuple(map(ord, "acgt")))

    @classmethod
    def utf8_bytes(cls) -> Alphabet:
        return cls(tuple(range(1, 256)))

    @classmethod
    def fixed(cls, symbols: str) -> Alphabet:
        return cls(tuple(sorted(set(map(ord, symbols)))))

    @property
    def sigma(self) -> int:
        return len(self.points)

    @property
    def bits(self) -> int:
        """Bits that a stored symbol takes, the terminator among them."""
        return max(1, self.sigma.bit_length())

    @property
    def dtype(self) -> type:
        return np.uint8 if self.sigma < 255 else np.uint16

    def codes(self, points: np.ndarray) -> np.ndarray:
        table = np.array(self.points, np.int64)
        at = np.searchsorted(table, points)
        if len(points) and (at.max(initial=0) >= len(table) or (table[at] != points).any()):
            raise ValueError("a symbol isn't in the alphabet")
        return (at + 1).astype(self.dtype)

    def text(self, codes: np.ndarray) -> str:
        return np.array((0, *self.points), "<u4")[codes].tobytes().decode("utf-32-le")

    def symbols_per_word(self, width: int) -> int:
        """Symbols that a sort word of so many bits holds."""
        return max(1, (width - 1 if width == 64 else width) // self.bits)

    def encode(self, df: DataFrame, col: str, name: str = "codes") -> DataFrame:
        """Adds a binary column with one code (8 or 16 bits) for each symbol."""

        @F.pandas_udf("binary")
        def run(texts: pd.Series) -> pd.Series:
            return texts.map(lambda t: None if t is None else self.codes(np.frombuffer(t.encode("utf-32-le"), "<u4")).tobytes())

        return df.withColumn(name, run(col))

    def decode(self, df: DataFrame, col: str = "codes", name: str = "s") -> DataFrame:
        @F.pandas_udf("string")
        def run(raw: pd.Series) -> pd.Series:
            return raw.map(lambda b: None if b is None else self.text(np.frombuffer(b, self.dtype)))

        return df.withColumn(name, run(col))

    def packed_words(self, col: str, start: F.Column, per: int) -> F.Column:
        """Words of ``per`` symbols from a place on as numbers, padded with terminators, in symbol order."""
        table = dict(zip(self.points, range(1, self.sigma + 1), strict=True))
        bits = self.bits

        @F.pandas_udf("long")
        def run(words: pd.Series) -> pd.Series:
            def one(word: str) -> int:
                out = 0
                for c in word:
                    out = (out << bits) | table[ord(c)]
                return out << bits * (per - len(word))

            return words.map(one)

        return run(F.substring(col, start, F.lit(per)))


def pack_bits(codes: np.ndarray, bits: int) -> bytes:
    """Codes of so many bits each, one behind the other."""
    grid = (codes[:, None].astype(np.uint32) >> np.arange(bits - 1, -1, -1, dtype=np.uint32)) & 1
    return np.packbits(grid.astype(np.uint8).ravel()).tobytes()


def unpack_bits(raw: bytes, bits: int, n: int) -> np.ndarray:
    grid = np.unpackbits(np.frombuffer(raw, np.uint8), count=n * bits).reshape(n, bits)
    return (grid.astype(np.uint32) << np.arange(bits - 1, -1, -1, dtype=np.uint32)).sum(1)
