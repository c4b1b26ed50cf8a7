"""Vectorised text scanning shared by the operators: code points, classes, word boundaries, hashes, hash tables.

Texts are handled as one array of code points per slice of rows, so whole documents of any length pass through a
bounded number of NumPy calls. Nothing here knows about Spark.
"""

from __future__ import annotations

import hashlib
import unicodedata
from collections.abc import Iterator
from functools import cache

import numpy as np

SPACE, LETTER, NUMBER, OTHER = 0, 1, 2, 3
#: The code points with Unicode's White_Space property.
WHITE_SPACE = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: Longer spans are hashed one by one.
LONG_SPAN = 192


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(factor)
    x ^= x >> np.uint64(31)
    return x


@cache
def classes() -> np.ndarray:
    """Class of every code point: white space, letter, number or other."""
    out = np.full(0x110000, OTHER, np.uint8)
    category = unicodedata.category
    for c in range(0x110000):
        kind = category(chr(c))[0]
        if kind == "L":
            out[c] = LETTER
        elif kind == "N":
            out[c] = NUMBER
    out[WHITE_SPACE] = SPACE
    return out


def slices(lengths: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` symbols; a longer row stands alone."""
    ends = np.cumsum(lengths)
    lo, n = 0, len(lengths)
    while lo < n:
        base = ends[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, base + most, "right")))
        yield lo, hi
        lo = hi


def codes_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts in a row, and each text's start with the total at the end."""
    bounds = np.zeros(len(texts) + 1, np.int64)
    np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)), out=bounds[1:])
    return np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4"), bounds


def span_hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span, equal for equal spans of arrays of one type anywhere.

    A span is taken in words of 64 bits (three code points, or eight bytes), each mixed into the state so far: nothing is
    a polynomial, and spans of up to three code points never share a hash. Spans of more than ``LONG_SPAN`` symbols are
    digested whole.
    """
    wide = codes.dtype.itemsize > 1
    per, bits = (3, 21) if wide else (8, 8)
    size = ends - starts
    if wide:
        held = np.zeros(len(codes) + 2, np.uint64)
        np.add(codes, 1, out=held[: len(codes)], casting="unsafe")
        words = held[:-2] | (held[1:-1] << np.uint64(bits)) | (held[2:] << np.uint64(2 * bits))
    else:
        held = np.zeros(len(codes) + per, np.uint8)
        held[: len(codes)] = codes
        words = np.ndarray(len(codes), "<u8", held.data, 0, (1,))
    masks = np.array([(1 << bits * i) - 1 for i in range(per + 1)], np.uint64)
    out = np.zeros(len(starts), np.uint64) if wide else size.astype(np.uint64) * _ODD
    long = np.flatnonzero(size > LONG_SPAN)
    on = np.flatnonzero((size > 0) & (size <= LONG_SPAN)) if len(long) else np.flatnonzero(size)
    at, left = starts[on], size[on]
    while len(on):
        out[on] = mix(out[on] * _ODD + (words[at] & masks[np.minimum(left, per)]))
        more = left > per
        on, at, left = on[more], at[more] + per, left[more] - per
    for i in long:
        out[i] = int.from_bytes(hashlib.blake2b(codes[starts[i] : ends[i]].tobytes(), digest_size=8).digest(), "little")
    return out


def byte_level_starts(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Starts of the pieces into which the byte-level tokenizers' pattern cuts each text.

    The pattern, in words: the seven English contractions; letters, digits or other signs, each run with one leading
    space; white space, which leaves its last character to a following piece.
    """
    n = len(codes)
    if not n:
        return np.zeros(0, np.int64)
    kind = classes()[codes]
    first = np.zeros(n + 1, bool)
    first[bounds] = True
    change = np.empty(n, bool)
    change[0] = True
    np.not_equal(kind[1:], kind[:-1], out=change[1:])
    change |= first[:n]
    run = np.flatnonzero(change)
    end = np.append(run[1:], n)
    of = kind[run]
    follows = ~first[end]  # another run of the same text comes next
    mark = change
    gap = (of == SPACE) & follows
    last = end[gap] - 1
    mark[last] = True
    mark[end[gap][codes[last] == 32]] = False
    short = np.flatnonzero((of == OTHER) & follows & (end - run == 1))
    short = short[(codes[run[short]] == 39) & mark[run[short]]]
    short = short[of[short + 1] == LETTER]
    if len(short):
        at, stop = run[short + 1], end[short + 1]
        one, two = codes[at], codes[np.minimum(at + 1, n - 1)]
        two = np.where(at + 1 < stop, two, 0)
        take = np.where(np.isin(one, [ord(c) for c in "stmd"]), 1, 0)
        for a, b in ("re", "ve", "ll"):
            take = np.where((one == ord(a)) & (two == ord(b)), 2, take)
        hit = take > 0
        at, stop, take = at[hit], stop[hit], take[hit]
        mark[at] = False
        rest = at + take
        mark[rest[rest < stop]] = True
    return np.flatnonzero(mark)


def word_spans(codes: np.ndarray, bounds: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of symbols for which ``inside`` holds, cut at text bounds: starts, ends, text of each."""
    n = len(codes)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, z
    edge = np.zeros(n + 1, bool)
    edge[bounds] = True
    begin = inside.copy()
    begin[1:] &= ~inside[:-1] | edge[1:n]
    stop = inside.copy()
    stop[:-1] &= ~inside[1:] | edge[1:n]
    starts = np.flatnonzero(begin)
    return starts, np.flatnonzero(stop) + 1, np.searchsorted(bounds, starts, "right") - 1


class HashIndex:
    """64-bit keys to dense integers, with vectorised lookups in an open-addressed table."""

    def __init__(self, bits: int = 16):
        self.clear(bits)

    def clear(self, bits: int = 16) -> None:
        self.bits, self.size = bits, 0
        self.keys = np.zeros(1 << bits, np.uint64)
        self.values = np.full(1 << bits, -1, np.int64)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * _ODD) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), -1, np.int64)
        slot = self._slot(keys)
        found = self.values[slot]
        same = self.keys[slot] == keys
        hit = same & (found >= 0)
        out[hit] = found[hit]
        left = np.flatnonzero(~same & (found >= 0))
        mask = len(self.keys) - 1
        slot = slot[left]
        while len(left):
            slot = (slot + 1) & mask
            found, same = self.values[slot], self.keys[slot] == keys[left]
            hit = same & (found >= 0)
            out[left[hit]] = found[hit]
            on = ~same & (found >= 0)
            left, slot = left[on], slot[on]
        return out

    def add(self, keys: np.ndarray, values: np.ndarray) -> None:
        """New, distinct keys."""
        if (self.size + len(keys)) * 2 > len(self.keys):
            held = self.values >= 0
            keys, values = np.concatenate([self.keys[held], keys]), np.concatenate([self.values[held], values])
            self.clear(max(self.bits + 1, int(len(keys) * 3).bit_length()))
        self.size += len(keys)
        mask = len(self.keys) - 1
        slot, left = self._slot(keys), np.arange(len(keys))
        while len(left):
            free = self.values[slot] < 0
            self.keys[slot[free]] = keys[left[free]]
            won = free & (self.keys[slot] == keys[left])
            self.values[slot[won]] = values[left[won]]
            left, slot = left[~won], (slot[~won] + 1) & mask


def text_piece(codes: np.ndarray, start: int, end: int) -> str:
    return codes[start:end].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")


def new_pieces(index: HashIndex, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Value of each hash (-1 where unknown) and the place of one occurrence of each unknown hash."""
    at = index.find(hashes)
    miss = np.flatnonzero(at < 0)
    if not len(miss):
        return at, miss
    _, one = np.unique(hashes[miss], return_index=True)
    return at, miss[one]


def spread(values_start: np.ndarray, values_len: np.ndarray) -> np.ndarray:
    """Indices of all elements of the given spans, span after span."""
    total = int(values_len.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(values_len)
    out = np.arange(total, dtype=np.int64)
    out += np.repeat(values_start - (ends - values_len), values_len)
    return out
