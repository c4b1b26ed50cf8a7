"""Array kernels on one block of strings: suffix order, symbols, ranks, insertion.

A block is an array of symbol codes (1..sigma, string after string) and its bounds. Suffixes are numbered in text order, a
string's terminator last; every string has its own terminator, terminators are ordered by string and below all symbols.
All of them are stored as code 0.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


def flat_codes(strings: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all strings in a row, and the bounds of the strings."""
    bounds = np.zeros(len(strings) + 1, np.int64)
    np.cumsum(np.fromiter(map(len, strings), np.int64, len(strings)), out=bounds[1:])
    return np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), "<u4"), bounds


def row_ranges(edges: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Ranges of rows with about ``most`` elements between their edges; a longer row stands alone."""
    out, lo = [], 0
    while lo < len(edges) - 1:
        hi = max(lo + 1, int(np.searchsorted(edges, edges[lo] + most, "right")) - 1)
        out.append((lo, hi))
        lo = hi
    return out


def with_terminators(codes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes with a 0 after each string, and each suffix's string."""
    text = np.insert(codes.astype(np.int64), bounds[1:], 0)
    return text, np.repeat(np.arange(len(bounds) - 1), np.diff(bounds) + 1)


def suffix_order(codes: np.ndarray, bounds: np.ndarray, sieve: bool = True) -> tuple[np.ndarray, list[int]]:
    """Suffix numbers in suffix order, and how many were unresolved after each round.

    The first round sorts words of as many symbols as fit 63 bits. Later rounds double the compared length by the ranks of
    the suffixes that far ahead; suffixes alone in their group leave (unless ``sieve`` is off, which sorts all again).
    """
    text, _ = with_terminators(codes, bounds)
    n = len(text)
    if not n:
        return np.zeros(0, np.int64), []
    bits = max(1, int(text.max()).bit_length())
    low = max(1, (n - 1).bit_length())
    width = (64 - low) // bits
    rest = np.repeat(bounds[1:] + np.arange(len(bounds) - 1), np.diff(bounds) + 1) - np.arange(n)
    ended = rest < width
    key = _words(text.astype(np.uint64), bits, width)
    at = np.flatnonzero(ended)
    drop = ((width - rest[at]) * bits).astype(np.uint64)
    key[at] = key[at] >> drop << drop  # what follows a terminator doesn't count
    del text, drop, rest, at
    order, lead = sorted_places(key, bits * width)
    lead |= ended[order]  # equal ones that have ended stay in text order
    del key, ended
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(lead, np.arange(n), 0))
    tied = ~lead
    tied[:-1] |= ~lead[1:]
    place = np.flatnonzero(tied)
    lead = lead[place]
    open_, h, left = len(place), width, []
    while True:
        left.append(open_)
        if not open_:
            return order, left
        if not sieve:
            place = np.arange(n)
            lead = rank[order] == place
        todo = order[place]
        # groups keep their places, so one sort of (group, rank that far ahead) sorts all of them
        key = np.cumsum(lead).astype(np.uint64)
        bits = int(key[-1]).bit_length() + low
        key <<= np.uint64(low)
        key |= rank[np.minimum(todo + h, n - 1)].astype(np.uint64)
        moved, lead = sorted_places(key, bits)
        todo = todo[moved]
        order[place] = todo
        rank[todo] = np.maximum.accumulate(np.where(lead, place, 0))
        tied = ~lead
        tied[:-1] |= ~lead[1:]
        place, lead, open_ = place[tied], lead[tied], int(tied.sum())
        h *= 2


def sorted_places(key: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The places of keys of so many bits in ascending order, and which of them begin a new key.

    Numbers are sorted several times faster than their places, so a place goes into the key's number where both fit; equal
    keys stay in order then.
    """
    n, lead = len(key), np.ones(len(key), bool)
    low = max(1, (n - 1).bit_length())
    if bits + low > 64:
        order = np.argsort(key)
        key = key[order]
    else:
        key = key << np.uint64(low) | np.arange(n, dtype=np.uint64)
        key.sort()
        order = (key & np.uint64((1 << low) - 1)).astype(np.int64)
        key >>= np.uint64(low)
    lead[1:] = key[1:] != key[:-1]
    return order, lead


def _words(text: np.ndarray, bits: int, width: int) -> np.ndarray:
    """From each place on, ``width`` codes in a number, joined from words of 1, 2, 4, ... codes."""
    ahead = lambda x, by: np.concatenate([x[by:], np.zeros(min(by, len(x)), x.dtype)])
    out, have, part, size = np.zeros(len(text), np.uint64), 0, text, 1
    while True:
        if width & size:
            out = out << np.uint64(size * bits) | ahead(part, have)
            have += size
        if have == width:
            return out
        part = part << np.uint64(size * bits) | ahead(part, size)
        size *= 2


def symbols_before(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """The symbol before each suffix, in text order; 0 before a whole string."""
    text, owner = with_terminators(codes, bounds)
    out = np.zeros(len(text), np.int64)
    out[1:] = np.where(owner[1:] == owner[:-1], text[:-1], 0)
    return out


def transform_of(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """The transform of a set, by sorting all its suffixes."""
    return symbols_before(codes, bounds)[suffix_order(codes, bounds)[0]]


def auto_spacing(sigma: int) -> int:
    """The least power of two at which counters of 32 bits take no more than log2(sigma) bits a symbol."""
    return 1 << max(6, math.ceil(math.log2(32 * sigma / max(1.0, math.log2(max(2, sigma))))))


@dataclass
class RankEngine:
    """Symbols of a transform with occurrence counters every ``spacing`` symbols; answers ranks of many (symbol, row) at once.

    With ``positions`` a sorted list of (symbol, row), 8 bytes a row, takes the counters' place: a row's place in it is the
    step itself, so a binary search answers what counters answer by a scan. It is faster and larger, for blocks in memory.
    """

    symbols: np.ndarray
    sigma: int
    spacing: int = 0
    positions: bool = False

    def __post_init__(self):
        if self.positions:
            n = len(self.symbols)
            order = np.argsort(self.symbols, kind="stable")
            self.listed = self.symbols[order].astype(np.int64) * (n + 1) + order
            totals = np.bincount(self.symbols, minlength=self.sigma + 1).astype(np.int64)
            self.smaller = np.cumsum(totals) - totals
            return
        self.spacing = self.spacing or auto_spacing(self.sigma)
        n, s, width = len(self.symbols), self.spacing, self.sigma + 1
        blocks = n // s + 1
        self.counters = np.zeros((blocks + 1, width), np.int64 if n >= 1 << 31 else np.int32)
        step = max(1, (1 << 22) // s)
        for lo in range(0, blocks, step):
            part = self.symbols[lo * s : (lo + step) * s].astype(np.int64)
            cell = (np.arange(len(part)) // s) * width + part
            size = -(-len(part) // s) if len(part) else 0
            self.counters[lo + 1 : lo + 1 + size] = np.bincount(cell, minlength=size * width).reshape(size, width)
        np.cumsum(self.counters, axis=0, out=self.counters)
        totals = self.counters[-1].astype(np.int64)
        self.smaller = np.cumsum(totals) - totals
        self.padded = np.concatenate([self.symbols, np.full(s, 255 if self.symbols.dtype == np.uint8 else 65535, self.symbols.dtype)])

    def rank(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol in the rows before."""
        if self.positions:
            return self.step(symbol, row) - self.smaller[symbol]
        out = np.empty(len(row), np.int64)
        offset = np.arange(self.spacing)
        step = max(1, (1 << 21) // self.spacing)
        for lo in range(0, len(row), step):
            c, i = symbol[lo : lo + step], row[lo : lo + step]
            block, rest = i // self.spacing, i % self.spacing
            seen = self.padded[(block * self.spacing)[:, None] + offset]
            hits = (seen == c[:, None].astype(seen.dtype)) & (offset < rest[:, None])
            out[lo : lo + step] = self.counters[block, c] + hits.sum(1)
        return out

    def step(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Rows smaller than the suffix that ``symbol`` begins, given the rows smaller than the suffix behind it."""
        if self.positions:
            return np.searchsorted(self.listed, symbol * np.int64(len(self.symbols) + 1) + row)
        return self.smaller[symbol] + self.rank(symbol, row)

    def pairs(self) -> RankEngine:
        """The same rows by their two symbols before, for chains of two symbols a step; pair codes of small alphabets.

        Made once. The j-th row with a symbol steps to the j-th row of the suffixes that it begins, so a pass over the rows
        with a cursor for each symbol reads the symbols before that.
        """
        if (held := self.__dict__.get("_pairs")) is not None:
            return held
        width = self.sigma + 1
        pair = pair_symbols(self.symbols, self.smaller, width, np.uint8 if width * width <= 255 else np.uint16)
        out = RankEngine(pair, width * width - 1, positions=self.positions)
        codes = np.arange(width * width)
        c0, c1 = codes // width, codes % width
        own = out.smaller
        out.rank = lambda symbol, row: RankEngine.step(out, symbol, row) - own[symbol] if out.positions else RankEngine.rank(out, symbol, row)
        out.smaller = self.step(c0, self.smaller[c1])
        self._pairs = out
        return out


def pair_symbols(symbols: np.ndarray, smaller: np.ndarray, width: int, dtype: type) -> np.ndarray:
    """For each row the two symbols before it, in a code; 0 where a string starts less than two symbols before."""
    pair, cursor = np.zeros(len(symbols), dtype), smaller.copy()
    for lo in range(0, len(pair), 1 << 20):
        part = symbols[lo : lo + (1 << 20)]
        for c in range(width):
            at = np.flatnonzero(part == c)
            earlier = symbols[cursor[c] : cursor[c] + len(at)].astype(pair.dtype)
            cursor[c] += len(at)
            if c:
                pair[lo + at] = np.where(earlier > 0, earlier * pair.dtype.type(width) + pair.dtype.type(c), 0)
    return pair


class PackedRanks:
    """Ranks from about two bytes a row: counters of 16 bits inside stretches of 2**16 rows, and bits counted between them.

    Answers what ``RankEngine`` answers, for symbols of a byte; for transforms too large to list positions.
    """

    STRETCH = 1 << 16
    #: Bytes of rows that are compared at once.
    CACHED = 1 << 18

    def __init__(self, symbols: np.ndarray, sigma: int):
        self.size, self.sigma, width = len(symbols), sigma, sigma + 1
        s = 64
        while 2 * width > 1.7 * s:
            s *= 2
        per = self.STRETCH // s
        self.shift, self.spacing, self.per = s.bit_length() - 1, s, per
        stretches = len(symbols) // self.STRETCH + 1
        blocks = len(symbols) // s + 1
        self.rows = np.full((blocks, s), 255, np.uint8)
        self.rows.reshape(-1)[: len(symbols)] = symbols
        self.near = np.zeros((blocks, width), np.uint16)
        self.far = np.zeros((stretches + 1, width), np.int64)
        offset = np.arange(self.STRETCH) // s * width
        for i in range(stretches):
            part = symbols[i * self.STRETCH : (i + 1) * self.STRETCH]
            each = np.bincount(offset[: len(part)] + part, minlength=per * width).reshape(per, width)
            total = np.cumsum(each, axis=0)
            own = self.near[i * per : (i + 1) * per]
            own[:] = (total - each)[: len(own)]
            self.far[i + 1] = self.far[i] + total[-1]
        totals = self.far[-1]
        self.smaller = np.cumsum(totals) - totals
        self.far = self.far[:-1]
        words = np.clip(np.arange(s)[:, None] - 64 * np.arange(s // 64), 0, 64)
        self.masks = np.where(words == 64, ~np.uint64(0), (np.uint64(1) << np.minimum(words, 63).astype(np.uint64)) - np.uint64(1))

    @property
    def symbols(self) -> np.ndarray:
        return self.rows.reshape(-1)[: self.size]

    def rank(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol in the rows before."""
        out, width, s, words = np.empty(len(row), np.int64), self.sigma + 1, self.spacing, self.spacing // 64
        most, near, far, asked = self.CACHED // s, self.near.reshape(-1), self.far.reshape(-1), symbol.astype(np.uint8)
        block = row >> self.shift
        cell, rest = block * width + symbol, row & (s - 1)
        above = (block >> self.per.bit_length() - 1) * width + symbol
        held, hits = np.empty((most, s), np.uint8), np.empty((most, s), bool)
        for lo in range(0, len(row), most):
            hi = min(lo + most, len(row))
            n = hi - lo
            np.take(self.rows, block[lo:hi], axis=0, out=held[:n], mode="clip")
            np.equal(held[:n], asked[lo:hi, None], out=hits[:n])
            bits = np.packbits(hits[:n].reshape(-1), bitorder="little").view("<u8").reshape(n, words)
            bits &= self.masks.take(rest[lo:hi], axis=0)
            seen = np.bitwise_count(bits)
            total = out[lo:hi]
            np.add(near.take(cell[lo:hi]), far.take(above[lo:hi]), out=total)
            for word in range(words):
                total += seen[:, word]
        return out

    def step(self, symbol: np.ndarray, row: np.ndarray) -> np.ndarray:
        return self.smaller[symbol] + self.rank(symbol, row)

    def pairs(self) -> PackedRanks:
        """The same rows by their two symbols before, for chains of two symbols a step; for alphabets of up to 14 symbols."""
        if (held := self.__dict__.get("_pairs")) is None:
            width, codes = self.sigma + 1, np.arange((self.sigma + 1) ** 2)
            held = self._pairs = PackedRanks(pair_symbols(self.symbols, self.smaller, width, np.uint8), len(codes) - 1)
            held.smaller = self.step(codes // width, self.smaller[codes % width])
        return held

    def walk(self, codes: np.ndarray, row: int) -> np.ndarray:
        """The rows of one string's chain, symbol after symbol from its end, without the arrays of ``step``."""
        out, flat, shift, far = np.empty(len(codes), np.int64), self.rows.reshape(-1), self.shift, self.far + self.smaller
        for i in range(len(codes) - 1, -1, -1):
            c, block = int(codes[i]), row >> shift
            row = int(far[block // self.per, c]) + int(self.near[block, c]) + flat[block << shift : row].tobytes().count(c)
            out[i] = row
        return out


#: Chains that are walked one by one, as steps of so few cost more as arrays.
MOST_WALKED = 12
#: Symbols of the largest alphabet whose pairs fit a byte.
MOST_PAIRED = 14
#: Rows up to which positions are listed where alphabets are too large for ``PackedRanks``.
MOST_LISTED = 1 << 26


def rank_engine(symbols: np.ndarray, sigma: int) -> PackedRanks | RankEngine:
    """The engine for many chains through one transform in bounded memory."""
    return PackedRanks(symbols, sigma) if sigma < 255 else RankEngine(symbols, sigma, positions=len(symbols) <= MOST_LISTED)


def chain_ranks(engine: RankEngine | PackedRanks, codes: np.ndarray, bounds: np.ndarray, start: int | np.ndarray, q: int = 1) -> np.ndarray:
    """For every suffix of new strings, in text order, how many old suffixes are smaller (q symbols a step, 1 or 2).

    ``start`` is the rank of a new terminator: the number of old strings, or 0 where the new strings come first; or one for
    each string.
    """
    sizes = np.diff(bounds)
    first = bounds[:-1] + np.arange(len(sizes))
    out = np.zeros(len(codes) + len(sizes), np.int64)
    order = np.argsort(-sizes, kind="stable")
    length = sizes[order]
    row = np.empty(len(sizes), np.int64)
    row[:] = start
    out[first + sizes] = start
    double = engine.pairs() if q == 2 else None
    longest = int(length[0]) if len(length) else 0
    width = engine.sigma + 1
    t = 1
    while t <= longest:
        on = order[: np.searchsorted(-length, -t, "right")]
        if len(on) <= MOST_WALKED and q == 1 and isinstance(engine, PackedRanks):
            for j in on.tolist():  # what is left of a few long strings goes string by string
                left = sizes[j] - t + 1
                out[first[j] : first[j] + left] = engine.walk(codes[bounds[j] : bounds[j] + left], int(row[j]))
            break
        at = bounds[on] + sizes[on] - t
        c = codes[at].astype(np.int64)
        stepped = engine.step(c, row[on])
        out[first[on] + sizes[on] - t] = stepped
        if double is not None:
            two = np.searchsorted(-length, -(t + 1), "right")
            on2 = on[:two]
            c2 = codes[bounds[on2] + sizes[on2] - t - 1].astype(np.int64)
            pair = c2 * width + c[:two]
            jumped = double.smaller[pair] + double.rank(pair, row[on2])
            out[first[on2] + sizes[on2] - t - 1] = jumped
            row[on] = stepped
            row[on2] = jumped
            t += 2
        else:
            row[on] = stepped
            t += 1
    return out


def insert_symbols(old: np.ndarray, ranks: np.ndarray, new: np.ndarray) -> np.ndarray:
    """Old symbols with new ones, in suffix order, before the old rows of their ranks."""
    at = ranks + np.arange(len(ranks))
    out, kept = np.empty(len(old) + len(new), old.dtype), np.ones(len(old) + len(new), bool)
    out[at], kept[at] = new, False
    out[kept] = old
    return out


def new_positions(ranks: np.ndarray) -> np.ndarray:
    """Where new symbols, in suffix order, end up."""
    return ranks + np.arange(len(ranks))


def read_back(engine: RankEngine, first: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """From each terminator row, the rows of its string's suffixes from the last to the whole string, and their symbols."""
    row, alive = first.astype(np.int64), np.arange(len(first))
    rows: list[np.ndarray] = [row.copy()]
    owners: list[np.ndarray] = [alive.copy()]
    while len(alive):
        c = engine.symbols[row[alive]].astype(np.int64)
        alive = alive[c > 0]
        if not len(alive):
            break
        row[alive] = engine.step(c[c > 0], row[alive])
        rows.append(row[alive].copy())
        owners.append(alive.copy())
    return rows, owners
