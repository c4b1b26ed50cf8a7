"""Suffixes sorted range by range, in bounded memory and disk: for strings of bounded length, however many.

Strings are packed once, as chunks of dense codes. Sampled suffixes cut the order into ranges that a task sorts; a few of the
ranges at a time leave their strings, as words of eight bytes, so the exchange on disk is a share of all suffix texts. Of
every range, packed symbols (and places) are kept, one row a range; positions follow from the ranges' sizes.
"""

from __future__ import annotations

import bisect
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.functions.kernels import flat_codes, row_ranges, sorted_places
from corpusbwt.session import release, ship, tidy, written

#: Suffixes of a chunk of strings, and of a range that one task sorts (about 150 bytes each for texts of 50 symbols).
CHUNK = 1 << 20
RANGE_BYTES = 32 << 20
#: Bytes of suffix text for each byte of strings that one pass may exchange.
PASS_SHARE = 2.0
SAMPLED = 40
#: Bytes of a suffix that are compared with splitters side by side.
LEADING = 32

_CHUNKS = "first long, sizes binary, text binary"
_MOVED = "bucket int, first long, words binary, counts binary, sym binary, owner binary, k binary"
_SORTED = "bucket int, n long, sym binary, sid binary, k binary"


@dataclass
class Sorted:
    """Sorted ranges, one stored row each, and the position at which each starts."""

    rows: DataFrame
    sizes: dict[int, int]
    points: np.ndarray
    wide: bool

    def __getstate__(self) -> dict:
        return self.__dict__ | {"rows": None}  # tasks read symbols by it, rows stay with the driver

    @property
    def n(self) -> int:
        return sum(self.sizes.values())

    @property
    def bases(self) -> dict[int, int]:
        at, out = 0, {}
        for bucket in sorted(self.sizes):
            out[bucket] = at
            at += self.sizes[bucket]
        return out

    def symbols(self, payload: bytes) -> np.ndarray:
        return self.points[np.frombuffer(payload, ">u2" if self.wide else np.uint8)]

    def expanded(self, columns: list[str], each: Callable, schema: str) -> DataFrame:
        """Rows that ``each(base, *columns)`` makes of a range, as arrays of the schema's columns."""
        bases, names = self.bases, [c.split()[0] for c in schema.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    bucket, *held = (batch.column(j)[i].as_py() for j in range(batch.num_columns))
                    made = each(bases[bucket], *held)
                    for lo in range(0, len(made[0]), 1 << 18):
                        yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + (1 << 18)]) for c in made], names)

        return self.rows.select("bucket", *columns).mapInArrow(run, schema)

    def transform(self) -> DataFrame:
        """``(pos, sym)``."""
        return self.expanded(["sym"], lambda base, sym: [base + np.arange(len(s := self.symbols(sym))), s], "pos long, sym int")

    def suffix_array(self) -> DataFrame:
        """``(pos, sid, k, sym)``, of ranges that kept their places."""
        read = lambda base, sid, k, sym: [base + np.arange(len(s := self.symbols(sym))), np.frombuffer(sid, np.int64), np.frombuffer(k, np.int32), s]
        return self.expanded(["sid", "k", "sym"], read, "pos long, sid long, k int, sym int")

    def runs(self) -> DataFrame:
        """``(run, sym, start, len)``: maximal runs of equal symbols. Ranges find their own; one summary a range tells
        the driver which first runs continue the one before, and where each last run ends."""

        def heads(payload: bytes) -> tuple[np.ndarray, np.ndarray]:
            sym = self.symbols(payload)
            return sym, np.flatnonzero(np.concatenate([[True], sym[1:] != sym[:-1]]))

        def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for bucket, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    sym, at = heads(payload)
                    second = int(at[1]) if len(at) > 1 else -1
                    yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), *(pa.array([int(x)], pa.int64()) for x in (len(at), sym[0], sym[-1], second))], ["bucket", "heads", "first", "last", "second"])

        found = sorted(self.rows.select("bucket", "sym").mapInArrow(told, "bucket int, heads long, first long, last long, second long").collect())
        bases, joined, number, ends = self.bases, {}, {}, {}
        prior, at = None, 0
        for r in found:
            joined[r["bucket"]] = prior == r["first"]
            number[r["bucket"]] = at
            at += r["heads"] - joined[r["bucket"]]
            prior = r["last"]
        end = self.n
        for r in reversed(found):
            ends[r["bucket"]] = end
            if not joined[r["bucket"]]:
                end = bases[r["bucket"]]
            elif r["second"] >= 0:
                end = bases[r["bucket"]] + r["second"]
        by_base = {bases[b]: (joined[b], number[b], ends[b]) for b in bases}

        def each(base, payload):
            sym, own = heads(payload)
            skip, first, end = by_base[base]
            own = own[1:] if skip else own
            start = base + own
            return [first + np.arange(len(own)), sym[own], start, np.diff(np.append(start, end))]

        return self.expanded(["sym"], each, "run long, sym int, start long, len long")


def _points(strings: DataFrame) -> np.ndarray:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(0x110000, bool)
        for batch in batches:
            seen[flat_codes(batch.column(0).to_pylist())[0]] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(seen).astype(np.int32))], ["cp"])

    return np.array(sorted(r[0] for r in strings.select("s").mapInArrow(run, "cp int").distinct().collect()), np.int64)


def alphabet_of(strings: DataFrame) -> np.ndarray:
    """0, for terminators, and the code points of strings, by dense code."""
    return np.concatenate([[0], _points(strings)]).astype(np.int32)


def _packed(strings: DataFrame, points: np.ndarray, dtype: str) -> DataFrame:
    """Chunks of consecutive strings: the first one's number, sizes, and codes with a 0 after each string."""
    table = np.zeros(int(points.max(initial=0)) + 1, dtype)
    table[points] = np.arange(1, len(points) + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sid, texts = batch.column(0).to_numpy(), batch.column(1).to_pylist()
            breaks = [0, *(np.flatnonzero(np.diff(sid) != 1) + 1).tolist(), len(sid)]
            for a, b in zip(breaks[:-1], breaks[1:], strict=True):
                ends = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts[a:b]], dtype=np.int64)])
                for lo, hi in row_ranges(ends, CHUNK):
                    codes, bounds = flat_codes(texts[a + lo : a + hi])
                    text = np.insert(table[codes], bounds[1:], 0)
                    yield pa.RecordBatch.from_arrays([pa.array([sid[a + lo]], pa.int64()), pa.array([np.diff(bounds).astype(np.int32).tobytes()], pa.binary()), pa.array([text.tobytes()], pa.binary())], ["first", "sizes", "text"])

    return strings.select("sid", "s").mapInArrow(run, _CHUNKS)


def _code_bits(points: np.ndarray) -> int:
    """Bits of a code in words: alphabets of up to 15 symbols share bytes."""
    return 4 if len(points) <= 15 else 8 if len(points) < 255 else 16


def _leading(suffix: bytes, bits: int) -> bytes:
    """The first ``LEADING`` bytes of a suffix's words, from its codes."""
    if bits == 4:
        codes = suffix[: 2 * LEADING].ljust(2 * LEADING, b"\0")
        return bytes(a << 4 | b for a, b in zip(codes[::2], codes[1::2], strict=True))
    return suffix[:LEADING].ljust(LEADING, b"\0")


class _Chunk:
    """A chunk's suffixes: codes, what is left of each string, and words at any place.

    With two codes a byte the words of even places stand before those of odd ones.
    """

    def __init__(self, first: int, sizes: bytes, text: bytes, dtype: str, bits: int):
        self.first, self.sizes, self.bits = first, np.frombuffer(sizes, np.int32), bits
        self.text, self.item = np.frombuffer(text, dtype), np.dtype(dtype).itemsize
        self.per, self.half = 64 // bits, len(text) // 2 + 16
        if bits == 4:
            held = np.frombuffer(text + bytes(2 * self.half + 1 - len(text)), np.uint8)
            self.raw = np.concatenate([held[at : at + 2 * self.half : 2] << 4 | held[at + 1 : at + 1 + 2 * self.half : 2] for at in (0, 1)])
        else:
            self.raw = np.frombuffer(text + bytes(16), np.uint8)
        self.edges = np.concatenate([[0], np.cumsum(self.sizes + np.int64(1))])
        self.words = np.ndarray((len(self.raw) - 8,), ">u8", self.raw, 0, (1,))

    def offset(self, at: np.ndarray) -> np.ndarray:
        """The byte at which a place's word starts."""
        return (at & 1) * self.half + (at >> 1) if self.bits == 4 else at * self.item

    def two(self) -> np.ndarray:
        """The first two bytes of every place's word."""
        if self.item == 2:
            return self.text.astype(np.uint16)
        pair = self.raw.astype(np.uint16) << 8
        pair[:-1] |= self.raw[1:]
        if self.bits == 8:
            return pair[: len(self.text)]
        out = np.empty(2 * self.half, np.uint16)
        out[::2], out[1::2] = pair[: self.half], pair[self.half :]
        return out[: len(self.text)]

    def owners(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        own = np.searchsorted(self.edges, at, "right") - 1
        return own, self.edges[own + 1] - 1 - at

    def word(self, at: np.ndarray, left: np.ndarray) -> np.ndarray:
        """Eight bytes of text from places on, with zeros behind the string's end."""
        drop = np.clip((self.per - left) * self.bits, 0, 64).astype(np.uint64)
        held = self.words[self.offset(at)].astype(np.uint64)
        return np.where(drop >= 64, np.uint64(0), held >> np.minimum(drop, 63) << np.minimum(drop, 63))

    def ragged(self, at: np.ndarray, left: np.ndarray) -> tuple[bytes, np.ndarray]:
        """All words of the suffixes, the last one with a zero in it, compressed, and their numbers."""
        counts = left // self.per + 1
        ends = np.cumsum(counts)
        index = np.arange(int(ends[-1])) - np.repeat(ends - counts, counts)
        index *= 8
        index += np.repeat(self.offset(at), counts)
        words = self.words[index]
        last = ends - 1
        words[last] = self.word(at + (counts - 1) * self.per, left % self.per)
        return pa.compress(words.tobytes(), "zstd", asbytes=True), counts

    def leading(self, at: np.ndarray, left: np.ndarray) -> np.ndarray:
        """The first ``LEADING`` bytes of suffixes, with zeros behind the string's end."""
        out = np.zeros((len(at), LEADING // 8), ">u8")
        for i in range(LEADING // 8):
            on = np.flatnonzero(left > i * self.per)
            out[on, i] = self.word(at[on] + i * self.per, left[on] - i * self.per)
        return out.view(f"S{LEADING}").reshape(-1)

    def suffix(self, at: int, left: int) -> bytes:
        return self.text[at : at + left].tobytes()


def _ordered(words: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The order of suffixes given by their words; equal ones stay in order."""
    off = np.cumsum(counts) - counts
    order, at, lead = np.arange(len(counts)), np.arange(len(counts)), np.arange(len(counts)) == 0
    depth, base = 0, words[off].min(initial=~np.uint64(0))  # the words of a range lie near each other
    rest = max(1, int(words[off].max(initial=base) - base).bit_length())
    while len(at):
        # as many bits of the word as fit a number with the group and the place
        group = np.cumsum(lead).astype(np.uint64) - np.uint64(1)
        most = 64 - max(1, (len(at) - 1).bit_length()) - int(group[-1]).bit_length()
        own = order[at]
        following = words[off[own] + depth] - base
        if rest < 64:
            following &= np.uint64((1 << rest) - 1)
        taken = min(rest, most)
        rest -= taken
        moved, lead = sorted_places(group << np.uint64(taken) | following >> np.uint64(rest), int(group[-1]).bit_length() + taken)
        own = own[moved]
        order[at] = own
        if not rest:
            lead |= counts[own] == depth + 1  # equal ones that have ended stay in order
            depth, rest, base = depth + 1, 64, np.uint64(0)
        tied = ~lead
        tied[:-1] |= ~lead[1:]
        at, lead = at[tied], lead[tied]
    return order


def sort_ranged(strings: DataFrame, *, places: bool = False, prefix: int = 0) -> Sorted:
    """Sorts all suffixes of strings ``(sid, s, len)``; with ``places`` ranges also keep (sid, k).

    With ``prefix`` ranges end where the first so many symbols change, besides at sampled suffixes.
    """
    spark = strings.sparkSession
    ship(spark)
    points = _points(strings)
    wide = len(points) >= 255
    dtype = ">u2" if wide else "u1"
    chunks = written(_packed(strings, points, dtype))
    tidy(spark)
    length, bits = F.col("len").cast("double"), _code_bits(points)
    total = strings.agg(F.sum(length + 1).alias("n"), F.sum(length * (length + 1) / 2 * (bits / 8) + 8 * max(1, bits // 8) * (length + 1)).alias("text")).first()
    n, text = int(total["n"] or 0), total["text"] or 0.0
    alphabet = np.concatenate([[0], points]).astype(np.int32)
    if not n:
        return Sorted(spark.createDataFrame([], _SORTED), {}, alphabet, wide)
    wanted = max(1, math.ceil(text / RANGE_BYTES))
    rate = min(1.0, SAMPLED * wanted / n)

    def sample(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                held = _Chunk(row["first"], row["sizes"], row["text"], dtype, bits)
                rng = np.random.default_rng(row["first"])
                at = np.flatnonzero(rng.random(len(held.text)) < rate)
                own, left = held.owners(at)
                yield pa.RecordBatch.from_arrays([pa.array([held.suffix(a, b) for a, b in zip(at.tolist(), left.tolist(), strict=True)], pa.binary()), pa.array(own + held.first, pa.int64())], ["suffix", "sid"])

    found = sorted((bytes(r[0]), r[1]) for r in chunks.mapInArrow(sample, "suffix binary, sid long").collect()) if wanted > 1 else []
    splits = sorted({found[len(found) * i // wanted] for i in range(1, wanted)}) if found else []
    item = np.dtype(dtype).itemsize
    if prefix:
        splits = sorted({*splits, *((s[: prefix * item], -1) for s, _ in splits)})
    del found
    leading = [_leading(s, bits) for s, _ in splits]
    first_words = np.array([int.from_bytes(s[:8], "big") for s in leading], np.uint64)
    leading = np.array(leading, f"S{LEADING}")
    passes = min(len(splits) + 1, max(1, math.ceil(text / max(n * item * PASS_SHARE, 20 * RANGE_BYTES))))

    def deal(lo: int, hi: int) -> Callable:
        """Suffixes of the ranges lo to hi - 1."""
        ends = [int(first_words[i]) >> 48 if 0 <= i < len(splits) else beyond for i, beyond in ((lo - 1, 0), (hi - 1, 1 << 16))]
        lead = np.arange(1 << 16)  # first two bytes; what follows a terminator doesn't count
        for shift in range(16 - bits, 0, -bits):
            lead = np.where(lead >> shift & (1 << bits) - 1, lead, lead >> shift << shift)
        wanted = (lead >= ends[0]) & (lead <= ends[1])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    held = _Chunk(*(batch.column(j)[i].as_py() for j in range(3)), dtype, bits)
                    if lo or hi <= len(splits):
                        at = np.flatnonzero(wanted[held.two()])
                    else:
                        at = np.arange(len(held.text))
                    own, left = held.owners(at)
                    word = held.word(at, left)
                    bucket = np.searchsorted(first_words, word, "right")
                    # where a splitter begins with the same word, more of them decide, then whole suffixes
                    alike = np.flatnonzero(np.searchsorted(first_words, word, "left") != bucket)
                    if len(alike):
                        more = held.leading(at[alike], left[alike])
                        bucket[alike] = np.searchsorted(leading, more, "right")
                        for x in alike[np.searchsorted(leading, more, "left") != bucket[alike]].tolist():
                            bucket[x] = bisect.bisect_right(splits, (held.suffix(at[x], left[x]), held.first + int(own[x])))
                    mine = np.flatnonzero((bucket >= lo) & (bucket < hi))
                    mine = mine[np.lexsort((word[mine], bucket[mine]))]  # like texts side by side, for the compression
                    at, own, left, bucket = at[mine], own[mine], left[mine], bucket[mine]
                    cuts = [0, *(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(bucket)]
                    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                        if a == b:
                            continue
                        words, counts = held.ragged(at[a:b], left[a:b])
                        k = held.sizes[own[a:b]] - left[a:b]
                        sym = np.where(k > 0, held.text[np.maximum(at[a:b] - 1, 0)], 0).astype(dtype)
                        extra = (own[a:b].astype(np.int32).tobytes(), k.astype(np.int32).tobytes()) if places else (b"", b"")
                        made = [[int(bucket[a])], [held.first], [words], [counts.astype(np.int32).tobytes()], [sym.tobytes()], [extra[0]], [extra[1]]]
                        yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(made, (pa.int32(), pa.int64(), *[pa.binary()] * 5), strict=True)], ["bucket", "first", "words", "counts", "sym", "owner", "k"])

        return run

    def order(table: pa.Table) -> pa.Table:
        table = table.sort_by("first")
        bucket = table.column("bucket")[0].as_py()
        joined = lambda c, t: np.frombuffer(b"".join(x.as_py() for x in table.column(c)), t)
        counts = joined("counts", np.int32).astype(np.int64)
        words, lo = np.empty(int(counts.sum()), np.uint64), 0
        for packed, own in zip(table.column("words"), table.column("counts"), strict=True):
            n = int(np.frombuffer(own.as_py(), np.int32).sum())
            words[lo : lo + n] = np.frombuffer(pa.decompress(packed.as_py(), n * 8, "zstd"), ">u8")
            lo += n
        at = _ordered(words, counts)
        del words
        sid = k = b""
        if places:
            names = np.repeat(np.array([x.as_py() for x in table.column("first")]), [len(x.as_py()) // 4 for x in table.column("owner")])
            sid, k = (names + joined("owner", np.int32))[at].tobytes(), joined("k", np.int32)[at].tobytes()
        return pa.table({"bucket": pa.array([bucket], pa.int32()), "n": pa.array([len(at)], pa.int64()), "sym": pa.array([joined("sym", dtype)[at].tobytes()], pa.binary()), "sid": pa.array([sid], pa.binary()), "k": pa.array([k], pa.binary())})

    edges = [(len(splits) + 1) * i // passes for i in range(passes + 1)]
    parts, sizes = [], {}
    for lo, hi in zip(edges[:-1], edges[1:], strict=True):
        part = written(chunks.mapInArrow(deal(lo, hi), _MOVED).groupBy("bucket").applyInArrow(order, _SORTED))
        sizes |= {r["bucket"]: r["n"] for r in part.select("bucket", "n").collect()}
        parts.append(part)
        if passes > 1:
            tidy(spark)
    release(chunks)
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return Sorted(out, sizes, alphabet, wide)
