"""The lossless WebP format in NumPy: a full decoder and an encoder for the streams that this subpackage stores.

The decoder reads prefix codes, meta codes, back-references and the colour cache, and inverts the predictor,
cross-colour, subtract-green and palette transforms. Streams of one group without a colour cache, which the media columns
use, are decoded by array operations: at every bit position of a block the length of the literal or back-reference that
would start there is looked up, and one pass follows these lengths from one to the next.
"""

from __future__ import annotations

import heapq
import struct
from collections.abc import Sequence
from dataclasses import dataclass
from functools import cache, lru_cache

import numpy as np

LITERALS, LENGTHS, DISTANCES = 256, 24, 40
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
#: Fixed values of the format: order of code-length codes; (dx, dy) of the first 120 distance codes.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2),
    (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3), (3, 2), (-3, 2), (0, 4), (4, 0),
    (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4),
    (-3, 4), (4, 3), (-4, 3), (5, 0), (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2),
    (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3),
    (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1), (4, 6), (-4, 6), (6, 4), (-6, 4),
    (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5),
    (8, 0), (4, 7), (-4, 7), (7, 4), (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7),
    (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
_HASH = 0x1E35A7BD
_BIT = np.arange(8, dtype=np.uint32)


class WebpError(ValueError):
    """The bytes are no valid lossless WebP image."""


# Prefix codes


def code_lengths(weights: np.ndarray, longest: int = 15) -> np.ndarray:
    """Lengths of an optimal prefix code for positive weights, flattened until none exceeds ``longest``."""
    weights = np.asarray(weights, np.int64)
    while True:
        used = np.flatnonzero(weights)
        out = np.zeros(len(weights), np.int64)
        if len(used) == 1:
            out[used] = 1
            return out
        heap = [(int(w), int(i), (int(i),)) for i, w in zip(used, weights[used], strict=True)]
        heapq.heapify(heap)
        while len(heap) > 1:
            a, b = heapq.heappop(heap), heapq.heappop(heap)
            both = a[2] + b[2]
            out[list(both)] += 1
            heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), both))
        if out.max(initial=0) <= longest:
            return out
        weights = np.where(weights > 0, (weights + 1) // 2, 0)


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Codes in the order in which their bits are stored, least bit first."""
    codes = np.zeros(len(lengths), np.int64)
    code = last = 0
    for i in sorted(np.flatnonzero(lengths), key=lambda i: (lengths[i], i)):
        n = int(lengths[i])
        code <<= n - last
        last = n
        codes[i] = int(format(code, f"0{n}b")[::-1], 2)
        code += 1
    return codes


class Code:
    """A prefix code as a table over its longest code's bits; a lone symbol takes no bits."""

    def __init__(self, lengths: np.ndarray):
        lengths = np.asarray(lengths, np.int64)
        used = np.flatnonzero(lengths)
        self.lengths = lengths
        if not len(used):
            used = np.array([0])
        if len(used) == 1:
            self.bits = 0
            self.symbol, self.length = np.array([used[0]], np.uint16), np.zeros(1, np.uint8)
        else:
            if (1 << 15 >> lengths[used]).sum() != 1 << 15:
                raise WebpError("a prefix code isn't complete")
            self.bits = int(lengths.max())
            self.symbol, self.length = np.zeros(1 << self.bits, np.uint16), np.zeros(1 << self.bits, np.uint8)
            for i, c in zip(used, canonical(lengths)[used], strict=True):
                self.symbol[c :: 1 << lengths[i]] = i
                self.length[c :: 1 << lengths[i]] = lengths[i]
        self.mask = (1 << self.bits) - 1


# Reading


class Reader:
    def __init__(self, data: bytes, at: int = 0):
        self.data, self.at, self.end = data, at, 8 * len(data)

    def peek(self, n: int) -> int:
        byte = self.at >> 3
        return int.from_bytes(self.data[byte : byte + 5], "little") >> (self.at & 7) & ((1 << n) - 1)

    def read(self, n: int) -> int:
        out = self.peek(n)
        self.at += n
        if self.at > self.end:
            raise WebpError("the data end early")
        return out

    def symbol(self, code: Code) -> int:
        slot = self.peek(15) & code.mask
        self.at += int(code.length[slot])
        if self.at > self.end:
            raise WebpError("the data end early")
        return int(code.symbol[slot])


@lru_cache(256)
def _code(lengths: bytes) -> Code:
    return Code(np.frombuffer(lengths, np.uint8))


def read_code(r: Reader, size: int) -> Code:
    lengths = np.zeros(size, np.int64)
    if r.read(1):
        two, wide = r.read(1), r.read(1)
        symbols = [r.read(8 if wide else 1), *([r.read(8)] if two else [])]
        if max(symbols) >= size:
            raise WebpError("a symbol is out of range")
        lengths[symbols] = 1
        return _code(lengths.astype(np.uint8).tobytes())
    small = np.zeros(19, np.int64)
    for i in LENGTH_ORDER[: 4 + r.read(4)]:
        small[i] = r.read(3)
    code, left = _code(small.astype(np.uint8).tobytes()), 2 + r.read(2 + 2 * r.read(3)) if r.read(1) else size
    at, last = 0, 8
    while at < size and left:
        left -= 1
        s = r.symbol(code)
        if s < 16:
            lengths[at] = s
            last, at = s or last, at + 1
        else:
            n = 3 + r.read(2) if s == 16 else 3 + r.read(3) if s == 17 else 11 + r.read(7)
            if at + n > size:
                raise WebpError("code lengths run over")
            lengths[at : at + n] = last if s == 16 else 0
            at += n
    return _code(lengths.astype(np.uint8).tobytes())


def _extra(r: Reader, prefix: int) -> int:
    if prefix < 4:
        return prefix + 1
    bits = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << bits) + r.read(bits) + 1


def _read_group(r: Reader, cache_size: int) -> list[Code]:
    return [read_code(r, n) for n in (LITERALS + LENGTHS + cache_size, LITERALS, LITERALS, LITERALS, DISTANCES)]


def read_image(r: Reader, width: int, height: int, main: bool) -> np.ndarray:
    """An entropy-coded image as ARGB values (height * width)."""
    bits = r.read(4) if r.read(1) else 0
    if bits > 11:
        raise WebpError("the colour cache is too large")
    meta, shift = None, 0
    if main and r.read(1):
        shift = r.read(3) + 2
        wide = -(-width >> shift)
        meta = (read_image(r, wide, -(-height >> shift), False) >> 8) & 0xFFFF
        meta = meta.reshape(-1, wide)
    n_groups = int(meta.max()) + 1 if meta is not None else 1
    groups = [_read_group(r, 1 << bits if bits else 0) for _ in range(n_groups)]
    if n_groups == 1 and not bits:
        return _plain(r, groups[0], width * height, width)
    return _general(r, groups, meta, shift, bits, width, height)


@cache
def _spare(symbols: int) -> np.ndarray:
    """Extra bits of each length or distance symbol."""
    return np.maximum(0, (np.arange(symbols) - 2) >> 1)


def _amounts(raw: np.ndarray, at: np.ndarray, symbols: np.ndarray) -> np.ndarray:
    """Lengths or distance codes of symbols whose extra bits stand at the bit positions ``at``."""
    bits = _spare(DISTANCES)[symbols]
    value = sum(raw[(at >> 3) + i].astype(np.int64) << (8 * i) for i in range(4)) >> (at & 7) & ((1 << bits) - 1)
    return np.where(symbols < 4, symbols + 1, ((2 + (symbols & 1)) << bits) + value + 1)


@cache
def _near(width: int) -> np.ndarray:
    """Distances in pixels of the first distance codes."""
    return np.array([0, *(max(1, dx + dy * width) for dx, dy in NEAR)])


def _plain(r: Reader, group: list[Code], n: int, width: int, block: int = 1 << 16) -> np.ndarray:
    """Pixels of one group without a colour cache: literals and back-references."""
    tables, far = group[:4], group[4]
    copies = bool(group[0].lengths[LITERALS:].any())
    out = np.zeros(n, np.uint32)
    got, at = 0, r.at
    raw = np.frombuffer(r.data, np.uint8)
    while got < n:
        base = at & ~7
        limit = min(block, r.end - base)
        more = raw[base >> 3 : ((base + limit) >> 3) + 16]
        held = np.zeros((limit >> 3) + 18, np.uint32)
        held[: len(more)] = more
        word = held[:-3] | held[1:-2] << 8 | held[2:-1] << 16
        window = ((word[:, None] >> _BIT) & 0x7FFF).ravel()  # 15 bits from each position on
        places = np.arange(len(window))

        def behind(code: Code) -> np.ndarray:
            reach = code.length.take(window & code.mask)  # noqa: B023
            reach[limit:] = 0  # noqa: B023  # behind the block, steps stand still
            return places + reach  # noqa: B023

        cursor, seen = None, []
        for code in tables:
            if code.bits:
                step = next((step for other, step in seen if np.array_equal(other.lengths[:LITERALS], code.lengths[:LITERALS]) and not other.lengths[LITERALS:].any()), None)
                if step is None:
                    step = behind(code)
                    seen.append((code, step))
                cursor = step if cursor is None else step.take(cursor)
        if copies and cursor is not None:
            told = group[0].symbol.take(window & group[0].mask)
            refer = np.flatnonzero(told[:limit] >= LITERALS)
            place = (behind(group[0]) if group[0].bits else places)[refer] + _spare(LENGTHS)[told[refer] - LITERALS]
            slot = window[place] & far.mask
            cursor[refer] = place + far.length[slot] + _spare(DISTANCES)[np.minimum(far.symbol[slot], DISTANCES - 1)]
        if cursor is None:  # every pixel is the same
            if copies:
                raise WebpError("a back-reference leaves the image")
            pixels = np.zeros(n - got, np.int64)
        else:
            follow, p, found = memoryview(cursor), at - base, []
            add = found.append
            safe = limit if base + limit == r.end else limit - 64  # the last pixels wait for the next block
            for _ in range(n - got):
                if p >= safe:
                    break
                add(p)
                p = follow[p]
            if not found:
                raise WebpError("the data end early")
            pixels = np.array(found, np.int64)
        size = np.ones(len(pixels), np.int64)
        refer = np.zeros(0, np.int64)
        if copies:
            told = group[0].symbol[window[pixels] & group[0].mask].astype(np.int64)
            refer = np.flatnonzero(told >= LITERALS)
            if len(refer):
                bytes_ = held.astype(np.uint8)
                symbol = told[refer] - LITERALS
                place = pixels[refer] + group[0].length[window[pixels[refer]] & group[0].mask]
                size[refer] = _amounts(bytes_, place, symbol)
                place = place + _spare(LENGTHS)[symbol]
                slot = window[place] & far.mask
                back = _amounts(bytes_, place + far.length[slot], far.symbol[slot].astype(np.int64))
                back = np.where(back <= len(NEAR), _near(width)[np.minimum(back, len(NEAR))], back - len(NEAR))
        ends = got + np.cumsum(size)
        kept = int(np.searchsorted(ends, n, "left")) + 1  # what follows the last pixel is no data
        if cursor is not None:
            at = base + (p if kept >= len(pixels) else int(pixels[kept]))
        pixels, ends, starts = pixels[:kept], ends[:kept], (ends - size)[:kept]
        if ends[-1] > n:
            raise WebpError("a back-reference leaves the image")
        plain = size[:kept] >= 0
        plain[refer[refer < kept]] = False
        channels, place = [], pixels[plain]
        for code in tables:
            slot = window[place] & code.mask
            channels.append(code.symbol[slot].astype(np.uint32))
            place = place + code.length[slot]
        green, red, blue, alpha = channels
        out[starts[plain]] = alpha << 24 | red << 16 | green << 8 | blue
        if len(refer):
            refer, back = refer[refer < kept], back[refer < kept]
            if (back > starts[refer]).any():
                raise WebpError("a back-reference leaves the image")
            for lo, hi, away in zip(starts[refer].tolist(), ends[refer].tolist(), back.tolist(), strict=True):
                out[lo:hi] = out[lo - away : hi - away] if away >= hi - lo else np.resize(out[lo - away : lo], hi - lo)
        got = int(ends[-1])
    if at > r.end:
        raise WebpError("the data end early")
    r.at = at
    return out


def _general(r: Reader, groups: list[list[Code]], meta: np.ndarray | None, shift: int, bits: int, width: int, height: int) -> np.ndarray:
    """Pixels one by one, with back-references and the colour cache."""
    n, out, cache_, i = width * height, [], [0] * (1 << bits), 0
    group = groups[0]
    while i < n:
        if meta is not None:
            group = groups[int(meta[(i // width) >> shift, (i % width) >> shift])]
        s = r.symbol(group[0])
        if s < LITERALS:
            red, blue, alpha = (r.symbol(c) for c in group[1:4])
            new = [alpha << 24 | red << 16 | s << 8 | blue]
        elif s < LITERALS + LENGTHS:
            length, code = _extra(r, s - LITERALS), _extra(r, r.symbol(group[4]))
            if code > len(NEAR):
                back = code - len(NEAR)
            else:
                dx, dy = NEAR[code - 1]
                back = max(1, dx + dy * width)
            if back > i or i + length > n:
                raise WebpError("a back-reference leaves the image")
            new = []
            for k in range(length):
                new.append(out[i - back + k] if k < back else new[k - back])
        else:
            new = [cache_[s - LITERALS - LENGTHS]]
        out += new
        i += len(new)
        if bits:
            for pixel in new:
                cache_[(_HASH * pixel & 0xFFFFFFFF) >> (32 - bits)] = pixel
    return np.array(out, np.uint32)


# Transforms; pixels are (height, width, 4) in the order alpha, red, green, blue


def channels_of(argb: np.ndarray, width: int) -> np.ndarray:
    return argb.astype(">u4").view(np.uint8).reshape(-1, width, 4)


def _average(a, b):
    return (a + b) >> 1


def _predicted(mode: int, left, top, right, corner) -> np.ndarray:
    """Prediction of one pixel from its neighbours (int arrays of four channels); ``right`` is above to the right."""
    if mode in (1, 2, 3, 4):
        return (left, top, right, corner)[mode - 1]
    if mode == 5:
        return _average(_average(left, right), top)
    if mode in (6, 7):
        return _average(left, corner if mode == 6 else top)
    if mode in (8, 9):
        return _average(top, corner if mode == 8 else right)
    if mode == 10:
        return _average(_average(left, corner), _average(top, right))
    if mode == 11:
        guess = left + top - corner
        return left if abs(guess - left).sum() < abs(guess - top).sum() else top
    if mode == 12:
        return np.clip(left + top - corner, 0, 255)
    if mode == 13:
        middle = _average(left, top)
        gap = middle - corner
        return np.clip(middle + np.sign(gap) * (abs(gap) >> 1), 0, 255)
    return np.array([255, 0, 0, 0])


def predict(pixels: np.ndarray, modes: np.ndarray, shift: int, forward: bool) -> np.ndarray:
    """Residuals of pixels (forward) or pixels of residuals, under a mode for each square of 2**shift pixels."""
    height, width, _ = pixels.shape
    given = pixels.astype(np.int64)
    done = given.copy()
    known = given if forward else done
    sign = -1 if forward else 1
    flat = known.reshape(-1, 4)
    for y in range(height):
        for x in range(width):
            at = y * width + x
            if not y or not x:
                guess = flat[at - 1] if x else flat[at - width] if y else np.array([255, 0, 0, 0])
            else:
                guess = _predicted(int(modes[y >> shift, x >> shift]), flat[at - 1], flat[at - width], flat[at - width + 1], flat[at - width - 1])
            done[y, x] = (given[y, x] + sign * guess) & 255
    return done.astype(np.uint8)


def cross_colour(pixels: np.ndarray, factors: np.ndarray, shift: int, forward: bool) -> np.ndarray:
    """Adds to red and blue (or takes away, forward) what green and red foretell; factors (rows, columns, 4) as pixels."""
    height, width, _ = pixels.shape
    each = np.repeat(np.repeat(factors, 1 << shift, 0), 1 << shift, 1)[:height, :width].astype(np.int8).astype(np.int64)
    red_to_blue, green_to_blue, green_to_red = each[..., 1], each[..., 2], each[..., 3]
    signed = lambda c: c.astype(np.uint8).astype(np.int8).astype(np.int64)
    out, sign = pixels.astype(np.int64), -1 if forward else 1
    green = signed(out[..., 2])
    red = out[..., 1] + sign * (green_to_red * green >> 5)
    whole = signed((pixels[..., 1] if forward else red) & 255)
    blue = out[..., 3] + sign * ((green_to_blue * green >> 5) + (red_to_blue * whole >> 5))
    out[..., 1], out[..., 3] = red, blue
    return (out & 255).astype(np.uint8)


def subtract_green(pixels: np.ndarray, forward: bool) -> np.ndarray:
    out = pixels.copy()
    out[..., 1::2] = pixels[..., 1::2] - pixels[..., 2:3] if forward else pixels[..., 1::2] + pixels[..., 2:3]
    return out


def _packing(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def unpack_palette(pixels: np.ndarray, table: np.ndarray, width: int) -> np.ndarray:
    """Colours of packed indices; an index beyond the table is transparent black."""
    shift = _packing(len(table))
    per, depth = 1 << shift, 8 >> shift
    index = (pixels[..., 2, None] >> (np.arange(per) * depth)) & ((1 << depth) - 1)
    index = index.reshape(len(pixels), -1)[:, :width]
    full = np.zeros((256, 4), np.uint8)
    full[: len(table)] = table
    return full[index]


#: Heads of plain images met so far: whole bytes, then size in bits and codes. Texts share a head, which is read once.
_HEADS: dict[bytes, tuple[int, list[Code]]] = {}


def _head_of(body: bytes) -> tuple[int, list[Code]] | None:
    """Bits and codes of a head met before, which starts at the sixth byte; a new plain head is remembered."""
    for raw, (bits, group) in _HEADS.items():
        rest = bits & 7
        if body[5 : 5 + (bits >> 3)] == raw[: bits >> 3] and (not rest or (body[5 + (bits >> 3)] ^ raw[-1]) & ((1 << rest) - 1) == 0):
            return bits, group
    r = Reader(body, 40)
    if r.read(3):
        return None
    group = _read_group(r, 0)
    bits = r.at - 40
    if len(_HEADS) < 8:
        _HEADS[body[5 : 5 + -(-bits // 8)]] = bits, group
    return bits, group


def decode(data: bytes, start: int = 0) -> tuple[np.ndarray, int]:
    """Pixels (height, width, 4: alpha, red, green, blue) of the image at ``start``, and where its file ends."""
    if data[start : start + 4] != b"RIFF" or data[start + 8 : start + 16] != b"WEBPVP8L":
        raise WebpError("no lossless WebP file")
    end = start + 8 + struct.unpack_from("<I", data, start + 4)[0]
    body = data[start + 20 : start + 20 + struct.unpack_from("<I", data, start + 16)[0]]
    r = Reader(body)
    if r.read(8) != 0x2F:
        raise WebpError("no lossless image data")
    width, height = r.read(14) + 1, r.read(14) + 1
    r.read(1)
    if r.read(3):
        raise WebpError("an unknown version")
    if (known := _head_of(body)) is not None:
        r.at += known[0]
        return channels_of(_plain(r, known[1], width * height, width), width), end
    undo, inner = [], width
    while r.read(1):
        kind = r.read(2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            shift = r.read(3) + 2
            wide = -(-inner >> shift)
            undo.append((kind, shift, channels_of(read_image(r, wide, -(-height >> shift), False), wide), inner))
        elif kind == PALETTE:
            n = r.read(8) + 1
            steps = channels_of(read_image(r, n, 1, False), n)[0]
            undo.append((kind, 0, np.cumsum(steps, axis=0, dtype=np.uint8), inner))
            inner = -(-inner >> _packing(n))
        else:
            undo.append((kind, 0, None, inner))
    pixels = channels_of(read_image(r, inner, height, True), inner)
    for kind, shift, held, wide in reversed(undo):
        if kind == PREDICTOR:
            pixels = predict(pixels, held[..., 2], shift, False)
        elif kind == CROSS_COLOUR:
            pixels = cross_colour(pixels, held, shift, False)
        elif kind == SUBTRACT_GREEN:
            pixels = subtract_green(pixels, False)
        else:
            pixels = unpack_palette(pixels, held, wide)
    return pixels, end


# Writing


class Writer:
    def __init__(self):
        self.value = self.size = 0

    def put(self, value: int, bits: int) -> None:
        self.value |= int(value) << self.size
        self.size += int(bits)


def put_code(w: Writer, lengths: np.ndarray) -> None:
    """A code's lengths: at most two small symbols simply, else with runs of zeros shortened."""
    used = np.flatnonzero(lengths)
    if len(used) <= 2 and (used < 256).all():
        used = used if len(used) else np.array([0])
        w.put(1, 1)
        w.put(len(used) - 1, 1)
        w.put(1, 1)
        for s in used:
            w.put(s, 8)
        return
    told: list[tuple[int, int, int]] = []
    i, n = 0, len(lengths)
    while i < n:
        run = 1
        while i + run < n and lengths[i + run] == lengths[i] == 0 and run < 138:
            run += 1
        told.append((18, run - 11, 7) if run >= 11 else (17, run - 3, 3) if run >= 3 else (int(lengths[i]), 0, 0))
        i += run if run >= 3 else 1
    small = code_lengths(np.bincount([t[0] for t in told], minlength=19), 7)
    if (small > 0).sum() == 1:
        small[1 if small[0] else 0] = small[small > 0][0] = 1
    w.put(0, 1)
    w.put(15, 4)
    for s in LENGTH_ORDER:
        w.put(small[s], 3)
    w.put(0, 1)
    codes = canonical(small)
    for s, extra, bits in told:
        w.put(codes[s], small[s])
        w.put(extra, bits)


def pack_symbols(codes: np.ndarray, lengths: np.ndarray, start: int) -> bytes:
    """Codes laid bit by bit from bit ``start`` of the first byte on."""
    ends = np.cumsum(lengths, dtype=np.int64) + start
    at = ends - lengths
    words = np.zeros((int(ends[-1]) >> 5) + 2 if len(ends) else 1, np.uint64)
    if len(ends):
        value = codes.astype(np.uint64) << (at & 31).astype(np.uint64)
        word = at >> 5
        first = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
        sums = np.add.reduceat(value, first)
        words[word[first]] += sums & np.uint64(0xFFFFFFFF)
        words[word[first] + 1] += sums >> np.uint64(32)
    size = -(-(int(ends[-1]) if len(ends) else start) // 8)
    return words.astype("<u4").tobytes()[:size]


def riff(stream: bytes) -> bytes:
    chunk = b"VP8L" + struct.pack("<I", len(stream)) + stream + b"\0" * (len(stream) & 1)
    return b"RIFF" + struct.pack("<I", 4 + len(chunk)) + b"WEBP" + chunk


@cache
def text_code() -> np.ndarray:
    """Code lengths that suit UTF-8 prose, from a rule: letters by English frequency, then other classes of bytes."""
    weight = np.ones(256, np.int64)
    weight[0x80:0xC0] = 24
    weight[0xC3] = 600
    weight[0x21:0x7F] = 8
    for i, c in enumerate(b"etaoinhrsdlucmfwygpbvkqxjz"):
        weight[c] = 2400 // (i + 2) + 20
        weight[c - 32] = weight[c] // 24 + 2
    weight[[0x20, 0x0A, 0x2C, 0x2E, 255]] = 2400, 60, 200, 200, 120
    return code_lengths(weight)


@cache
def reference_code() -> tuple[np.ndarray, np.ndarray]:
    """Code lengths of greens with lengths, and of distances, for short texts: short copies, and runs of the last row."""
    weight = 1 << (15 - text_code())
    lengths = (weight.sum() // 12) // (2 + np.arange(LENGTHS))
    distances = np.full(DISTANCES, 4)
    distances[1] = 120
    distances[14:32] = 16
    return code_lengths(np.concatenate([weight, lengths])), code_lengths(distances)


@cache
def _text_head(copies: bool) -> tuple[int, int, list[tuple[np.ndarray, np.ndarray]]]:
    green, far = reference_code() if copies else (np.concatenate([text_code(), np.zeros(LENGTHS, np.int64)]), np.zeros(DISTANCES, np.int64))
    return _plain_head(green, text_code(), far)


def _plain_head(green: np.ndarray, other: np.ndarray, far: np.ndarray) -> tuple[int, int, list[tuple[np.ndarray, np.ndarray]]]:
    """Bits after the dimensions of an opaque image, and codes and lengths of greens, of the other colours, of distances."""
    w = Writer()
    w.put(0, 3)  # no transform, no colour cache, no meta codes
    for lengths in (green, other, other, np.eye(1, 256, 255, dtype=np.int64)[0], far):
        put_code(w, lengths)
    return w.value, w.size, [(canonical(x), x if (x > 0).sum() > 1 else np.zeros(len(x), np.int64)) for x in (green, other, far)]


def repeats(pixels: np.ndarray, least: int = 4) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, length and distance of copies: from each start on, the pixels equal those a distance before.

    A pixel whose next ``least`` pixels last stood at one distance extends the copy before it; copies don't overlap.
    """
    n, none = len(pixels) - least + 1, np.zeros(0, np.int64)
    if n < 2:
        return none, none, none
    wide = pixels.astype(np.uint64)
    key = sum((wide[i : i + n] + np.uint64(1)) * np.uint64(_HASH * 2654435761 ** (2 * i) * 2 + 1 & (1 << 64) - 1) for i in range(least))
    order = np.argsort(key, kind="stable")
    away = np.zeros(n, np.int64)
    same = np.flatnonzero(key[order[1:]] == key[order[:-1]])
    late, early = order[same + 1], order[same]
    equal = np.logical_and.reduce([pixels[late + i] == pixels[early + i] for i in range(least)])
    away[late[equal]] = (late - early)[equal]
    edges = np.flatnonzero(np.concatenate([[True], away[1:] != away[:-1], [True]]))
    starts, sizes, back = edges[:-1], np.diff(edges) + least - 1, away[edges[:-1]]
    on = back > 0
    chosen, free = [], 0
    for lo, size, far in zip(starts[on].tolist(), sizes[on].tolist(), back[on].tolist(), strict=True):
        hi, lo = lo + size, max(lo, free)
        if hi - lo >= least:
            chosen += [(at, min(4096, hi - at), far) for at in range(lo, hi, 4096)]
            free = hi
    return tuple(np.array(chosen, np.int64).reshape(-1, 3).T)


def _prefixes(value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Prefix symbols, extra bits' values and numbers of lengths or distance codes."""
    if not len(value):
        return value, value, value
    less = value - 1
    top = (np.maximum(less, 1).astype(np.float64).view(np.int64) >> 52) - 1023  # the exponent
    spare = np.where(value <= 4, 0, top - 1)
    return np.where(value <= 4, less, 2 * top + (less >> np.maximum(top - 1, 0) & 1)), less & ((1 << spare) - 1), spare


@cache
def _codes_of_distances(width: int) -> dict[int, int]:
    return {d: code for code, d in reversed(list(enumerate(_near(width).tolist()))) if code}


def encode_bytes(payload: bytes, width: int, height: int, *, own_code: bool) -> bytes:
    """An opaque image whose red, green and blue samples are the payload, in the shorter of two forms.

    One has literals alone, the other back-references where pixels repeat; its size is known from the codes.
    """
    samples = np.frombuffer(payload, np.uint8)
    rgb = samples.reshape(-1, 3)
    starts, sizes, back = repeats(rgb[:, 0].astype(np.uint32) << 16 | rgb[:, 1].astype(np.uint32) << 8 | rgb[:, 2])
    form = _form(rgb, starts[:0], sizes[:0], back[:0], width, own_code)
    if len(starts):
        form = min(form, _form(rgb, starts, sizes, back, width, own_code), key=lambda f: f.bits)
    value, size = form.value, form.size
    codes, lengths = form.laid()
    head = 0x2F | (width - 1) << 8 | (height - 1) << 22 | value << 40
    size += 40
    body = pack_symbols(codes, lengths, size & 7)
    front = head.to_bytes(-(-size // 8), "little")
    if size & 7:
        body = bytes([front[-1] | (body[0] if body else 0)]) + body[1:]
        front = front[:-1]
    return riff(front + body)


@dataclass
class Form:
    """An image with given copies: its head and the head's bits, all bits, and the columns of literals and copies."""

    value: int
    size: int
    bits: int
    literals: list[tuple[np.ndarray, np.ndarray, np.ndarray]]
    copies: list[tuple[np.ndarray, np.ndarray]]
    kept: np.ndarray
    starts: np.ndarray

    def laid(self) -> tuple[np.ndarray, np.ndarray]:
        """Codes and lengths of all that follows the head, in order."""
        n, columns = len(self.kept), 4 if len(self.starts) else 3
        entries = np.zeros((2, n + len(self.starts), columns), np.int64)
        for i, (symbols, codes, bits) in enumerate(self.literals):
            entries[0, :n, i], entries[1, :n, i] = codes.take(symbols), bits.take(symbols)
        for i, (codes, bits) in enumerate(self.copies):
            entries[0, n:, i], entries[1, n:, i] = codes, bits
        if len(self.starts):
            entries = entries[:, np.argsort(np.concatenate([self.kept, self.starts]), kind="stable")]
        codes, lengths = entries.reshape(2, -1)
        codes[lengths == 0] = 0
        return codes, lengths


def _form(rgb: np.ndarray, starts: np.ndarray, sizes: np.ndarray, back: np.ndarray, width: int, own_code: bool) -> Form:
    """The form of an image with the given copies; nothing is laid out before one is chosen."""
    if len(starts):
        steps = np.zeros(len(rgb) + 1, np.int64)
        np.add.at(steps, starts, 1)
        np.add.at(steps, starts + sizes, -1)
        kept = np.flatnonzero(np.cumsum(steps)[:-1] == 0)
        red, green, blue = rgb[kept].T
    else:
        kept, (red, green, blue) = np.arange(len(rgb)), rgb.T
    known = _codes_of_distances(width)
    near = np.array([known.get(d, d + len(NEAR)) for d in back.tolist()], np.int64)
    length, length_rest, length_bits = _prefixes(sizes)
    far, far_rest, far_bits = _prefixes(near)
    counts = [np.bincount(x, minlength=256) for x in (red, green, blue)]
    greens = np.bincount(LITERALS + length, minlength=LITERALS + LENGTHS)
    if own_code:
        others = counts[0] + counts[1] + counts[2]
        whole = greens + np.append(counts[1] if len(starts) else others, np.zeros(LENGTHS, np.int64))
        made = [code_lengths(x) if x.any() else np.zeros(len(x), np.int64) for x in (whole, others, np.bincount(far, minlength=DISTANCES))]
        value, size, tables = _plain_head(*made)
    else:
        value, size, tables = _text_head(bool(len(starts)))
    (green_codes, green_lengths), (codes, lengths), (far_codes, far_lengths) = tables
    bits = size + int((counts[0] + counts[2]) @ lengths + counts[1] @ green_lengths[:LITERALS])
    copies = []
    if len(starts):
        copies = [(green_codes[LITERALS + length], green_lengths[LITERALS + length]), (length_rest, length_bits), (far_codes[far], far_lengths[far]), (far_rest, far_bits)]
        bits += sum(int(x.sum()) for _, x in copies)
    return Form(value, size, bits, [(green, green_codes, green_lengths), (red, codes, lengths), (blue, codes, lengths)], copies, kept, starts)


def put_image(w: Writer, argb: Sequence[int], width: int, *, main: bool, cache_bits: int = 0, references: bool = True, meta_shift: int = 0) -> None:
    """An image with back-references to the pixel before or the row above, a colour cache and two meta groups on request."""
    out, i, held = [], 0, {}
    remember = lambda p: held.__setitem__((_HASH * p & 0xFFFFFFFF) >> (32 - cache_bits), p) if cache_bits else None
    while i < len(argb):
        run = 0
        back = next((b for b in (1, width) if references and b <= i and argb[i] == argb[i - b]), 0)
        while back and i + run < len(argb) and argb[i + run] == argb[i + run - back] and run < 4096:
            run += 1
        if run >= 3:
            out.append(("copy", i, run, back))
        else:
            run = 1
            slot = (_HASH * argb[i] & 0xFFFFFFFF) >> (32 - cache_bits) if cache_bits else -1
            out.append(("cached", i, slot, 0) if held.get(slot) == argb[i] else ("literal", i, argb[i], 0))
        for p in argb[i : i + run]:
            remember(p)
        i += run
    w.put(bool(cache_bits), 1)
    if cache_bits:
        w.put(cache_bits, 4)
    group_of = lambda at: 0
    n_groups = 1
    if main:
        w.put(bool(meta_shift), 1)
        if meta_shift:
            wide, high = -(-width >> meta_shift), -(-(len(argb) // width) >> meta_shift)
            w.put(meta_shift - 2, 3)
            put_image(w, [((x + y) & 1) << 8 for y in range(high) for x in range(wide)], wide, main=False)
            group_of = lambda at: ((at % width >> meta_shift) + (at // width >> meta_shift)) & 1
            n_groups = 2 if wide * high > 1 else 1
    sizes = (LITERALS + LENGTHS + (1 << cache_bits if cache_bits else 0), LITERALS, LITERALS, LITERALS, DISTANCES)
    told = []
    for kind, at, a, b in out:
        if kind == "literal":
            part = [(0, a >> 8 & 255, 0, 0), (1, a >> 16 & 255, 0, 0), (2, a & 255, 0, 0), (3, a >> 24, 0, 0)]
        elif kind == "cached":
            part = [(0, LITERALS + LENGTHS + a, 0, 0)]
        else:
            near = next((k + 1 for k, (dx, dy) in enumerate(NEAR) if dx + dy * width == b), b + len(NEAR))
            (s, x, n), (t, y, m) = _prefix(a), _prefix(near)
            part = [(0, LITERALS + s, x, n), (4, t, y, m)]
        told.append((group_of(at), part))
    weights = [[np.zeros(n, np.int64) for n in sizes] for _ in range(n_groups)]
    for g, part in told:
        for channel, s, _, _ in part:
            weights[g][channel][s] += 1
    lengths = [[code_lengths(c) if c.any() else c for c in group] for group in weights]
    for group in lengths:
        for c in group:
            put_code(w, c)
    codes = [[canonical(c) for c in group] for group in lengths]
    for g, part in told:
        for channel, s, x, n in part:
            if (lengths[g][channel] > 0).sum() > 1:
                w.put(codes[g][channel][s], lengths[g][channel][s])
            w.put(x, n)


def _prefix(value: int) -> tuple[int, int, int]:
    """Prefix symbol, extra bits' value and number of a length or distance."""
    if value <= 4:
        return value - 1, 0, 0
    v = value - 1
    top = v.bit_length() - 1
    half = v >> (top - 1) & 1
    return 2 * top + half, v & ((1 << (top - 1)) - 1), top - 1


def encode(pixels: np.ndarray, *, transforms: Sequence[str] = (), cache_bits: int = 0, meta_shift: int = 0, shift: int = 2, modes: np.ndarray | None = None) -> bytes:
    """Any image (height, width, 4: alpha, red, green, blue) under the named transforms, in the order given."""
    height, width, _ = pixels.shape
    w = Writer()
    w.put(0x2F, 8)
    w.put(width - 1, 14)
    w.put(height - 1, 14)
    w.put(int((pixels[..., 0] != 255).any()), 1)
    w.put(0, 3)
    as_argb = lambda p: [int(v) for v in np.ascontiguousarray(p).view(">u4").ravel()]
    for name in transforms:
        w.put(1, 1)
        wide, high = -(-pixels.shape[1] >> shift), -(-height >> shift)
        if name == "predictor":
            if modes is None:
                modes = (np.arange(wide * high) % 14).reshape(high, wide)
            w.put(PREDICTOR, 2)
            w.put(shift - 2, 3)
            put_image(w, [int(m) << 8 for m in modes.ravel()], wide, main=False)
            pixels = predict(pixels, modes, shift, True)
        elif name == "cross_colour":
            factors = (np.arange(wide * high * 4) * 37 % 256).astype(np.uint8).reshape(high, wide, 4)
            w.put(CROSS_COLOUR, 2)
            w.put(shift - 2, 3)
            put_image(w, as_argb(factors), wide, main=False)
            pixels = cross_colour(pixels, factors, shift, True)
        elif name == "subtract_green":
            w.put(SUBTRACT_GREEN, 2)
            pixels = subtract_green(pixels, True)
        else:
            table, index = np.unique(np.ascontiguousarray(pixels).view(">u4").ravel(), return_inverse=True)
            if len(table) > 256:
                raise ValueError("more than 256 colours")
            colours = table.astype(">u4").view(np.uint8).reshape(-1, 4)
            w.put(PALETTE, 2)
            w.put(len(table) - 1, 8)
            put_image(w, as_argb(np.diff(colours, axis=0, prepend=np.zeros((1, 4), np.uint8))), len(table), main=False)
            per, depth = 1 << _packing(len(table)), 8 >> _packing(len(table))
            grid = np.zeros((height, -(-width // per) * per), np.int64)
            grid[:, :width] = index.reshape(height, width)
            packed = (grid.reshape(height, -1, per) << (np.arange(per) * depth)).sum(2)
            pixels = np.zeros((*packed.shape, 4), np.uint8)
            pixels[..., 0], pixels[..., 2] = 255, packed
    w.put(0, 1)
    put_image(w, as_argb(pixels), pixels.shape[1], main=True, cache_bits=cache_bits, meta_shift=meta_shift)
    return riff(w.value.to_bytes(-(-w.size // 8), "little"))
