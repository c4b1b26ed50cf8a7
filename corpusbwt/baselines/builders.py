"""Array forms of the builders that the block-append builder is compared with; each gives the whole set's transform.

All take dense codes (from 1) and bounds of a set and keep it in one task, as the originals keep it in one machine; a larger set
is cut into groups, whose transforms are merged (``operators.merged``).
"""

from __future__ import annotations

import tempfile
from pathlib import Path

import numpy as np

from corpusbwt.functions.kernels import MOST_PAIRED, RankEngine, chain_ranks, insert_symbols, rank_engine, suffix_order, symbols_before, transform_of


def brute(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """All suffixes sorted at once."""
    return transform_of(codes, bounds)


def cut(bounds: np.ndarray, blocks: int) -> list[tuple[int, int]]:
    """Ranges of strings whose suffixes fill about equal shares."""
    ends = np.cumsum(np.diff(bounds) + 1)
    total = int(ends[-1]) if len(ends) else 0
    of = (ends - np.diff(bounds) - 1) * blocks // max(1, total)
    edges = np.searchsorted(of, np.arange(blocks + 1))
    return [(int(a), int(b)) for a, b in zip(edges[:-1], edges[1:], strict=True) if a < b]


def part_of(codes: np.ndarray, bounds: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    return codes[bounds[lo] : bounds[hi]], bounds[lo : hi + 1] - bounds[lo]


def block_append(codes: np.ndarray, bounds: np.ndarray, blocks: int = 4, *, reverse: bool = False, q: int = 1, log: list | None = None) -> np.ndarray:
    """Blocks of strings appended in turn: sort the block, rank its suffixes in the old transform, insert its symbols.

    Forward, a new terminator is larger than all old ones; in reverse order of blocks it is smaller than all.
    """
    import time

    sigma = int(codes.max(initial=1))
    held, m = np.zeros(0, np.uint8 if sigma < 255 else np.uint16), 0
    parts = cut(bounds, blocks)
    for lo, hi in reversed(parts) if reverse else parts:
        own, edges = part_of(codes, bounds, lo, hi)
        t0 = time.perf_counter()
        order, _ = suffix_order(own, edges)
        new = symbols_before(own, edges)[order]
        t1 = time.perf_counter()
        if len(held):
            engine = rank_engine(held, sigma) if q == 1 or sigma <= MOST_PAIRED else RankEngine(held, sigma, positions=True)
            ranks = chain_ranks(engine, own, edges, 0 if reverse else m, q)[order]
        else:
            ranks = np.zeros(len(new), np.int64)
        t2 = time.perf_counter()
        held = insert_symbols(held, ranks, new)
        m += hi - lo
        if log is not None:
            log.append((len(new), len(held), t1 - t0, t2 - t1, time.perf_counter() - t2))
    return held


def appended(codes: np.ndarray, bounds: np.ndarray, most: int = 1 << 22, q: int = 1) -> np.ndarray:
    """``block_append`` in as many blocks as keep each of them to about ``most`` suffixes, and in four at least."""
    return block_append(codes, bounds, max(4, -(-(len(codes) + len(bounds)) // most)), q=q)


def backward_single(codes: np.ndarray, bounds: np.ndarray, blocks: int = 4) -> np.ndarray:
    """The predecessor's roles: blocks from the end; **old** suffixes are ranked in the new block, whose symbols stay put.

    Old strings come after the new ones, so an old terminator is larger than all new ones. Every old suffix takes a
    step at every block, and the merge rewrites the whole transform.
    """
    sigma = int(codes.max(initial=1))
    held, last = np.zeros(0, np.uint8 if sigma < 255 else np.uint16), len(bounds) - 1
    for lo, hi in reversed(cut(bounds, blocks)):
        own, edges = part_of(codes, bounds, lo, hi)
        new = transform_of(own, edges).astype(held.dtype)
        if len(held):
            old, old_edges = part_of(codes, bounds, hi, last)
            before = chain_ranks(rank_engine(new, sigma), old, old_edges, hi - lo)
            gaps = np.bincount(before, minlength=len(new) + 1)  # old rows before each new row
            held = insert_symbols(held, np.cumsum(gaps)[:-1], new)
        else:
            held = new
    return held


def column_wise(codes: np.ndarray, bounds: np.ndarray, storage: str = "memory") -> np.ndarray:
    """From all terminators on, every pass inserts the next symbol, from the end, of every string.

    ``storage='disk'`` writes the transform after every pass and reads it before the next one.
    """
    sizes, m, sigma = np.diff(bounds), len(bounds) - 1, int(codes.max(initial=1))
    dtype = np.uint8 if sigma < 255 else np.uint16
    place = tempfile.TemporaryDirectory() if storage == "disk" else None
    last = np.where(sizes > 0, codes[np.maximum(bounds[1:] - 1, 0)] if len(codes) else 0, 0)
    held = last.astype(dtype)
    row, live = np.arange(m), np.flatnonzero(sizes > 0)
    t = 1
    while len(live):
        if place:
            path = Path(place.name) / "transform.npy"
            np.save(path, held)
            held = np.load(path)
        engine = rank_engine(held, sigma)
        c = codes[bounds[live + 1] - t].astype(np.int64)
        # the suffixes of this column lie behind all shorter ones that start with a smaller symbol
        inserted_smaller = engine.smaller[c] - engine.smaller[1] if sigma else 0
        at = m + inserted_smaller + engine.rank(c, row[live])
        order = np.argsort(at, kind="stable")
        live, at = live[order], at[order]
        more = sizes[live] > t
        new = np.where(more, codes[np.maximum(bounds[live + 1] - t - 1, 0)], 0)
        spot = at - np.arange(len(at))
        held = insert_symbols(held, spot, new)
        row[live] = at
        live = live[more]
        t += 1
    if place:
        place.cleanup()
    return held


class SymbolTree:
    """A balanced tree of symbol leaves with counts: rank and insertion one symbol at a time.

    A node holds its children's sizes, for each symbol their counts, the children, and whether they are leaves; a full one
    is cut in two, up to the root, so an insertion touches one node a level.
    """

    def __init__(self, sigma: int, leaf: int = 512, fan: int = 64):
        self.sigma, self.leaf, self.fan = sigma, leaf, fan
        self.totals = [0] * (sigma + 1)
        self.root = ([0], [[0] for _ in range(sigma + 1)], [bytearray() if sigma < 256 else []], True)

    def smaller(self, symbol: int) -> int:
        return sum(self.totals[:symbol])

    def insert(self, at: int, symbol: int, asked: int) -> int:
        """Puts a symbol before row ``at``; gives the rows before it that hold ``asked``."""
        seen, node, path = 0, self.root, []
        self.totals[symbol] += 1
        while True:
            sizes, counts, children, last = node
            i = 0
            for size in sizes:
                if at <= size:
                    break
                at -= size
                i += 1
            if i:
                seen += sum(counts[asked][:i])
            sizes[i] += 1
            counts[symbol][i] += 1
            path.append((node, i))
            if last:
                break
            node = children[i]
        held = children[i]
        seen += held.count(asked, 0, at) if type(held) is bytearray else held[:at].count(asked)
        held.insert(at, symbol)
        if len(held) > self.leaf:
            self._cut(path)
        return seen

    def _cut(self, path: list) -> None:
        node, i = path.pop()
        held = node[2][i]
        right = held[len(held) // 2 :]
        del held[len(held) // 2 :]
        self._put(node, i, len(held), [held.count(s) for s in range(self.sigma + 1)], right)
        while len(node[0]) > self.fan:
            sizes, counts, children, last = node
            half = len(sizes) // 2
            right = (sizes[half:], [c[half:] for c in counts], children[half:], last)
            del sizes[half:], children[half:]
            for c in counts:
                del c[half:]
            if not path:
                both = node, right
                self.root = ([sum(x[0]) for x in both], [[sum(x[1][s]) for x in both] for s in range(self.sigma + 1)], list(both), False)
                return
            node, i = path.pop()
            self._put(node, i, sum(sizes), [sum(c) for c in counts], right)

    @staticmethod
    def _put(node: tuple, i: int, size: int, kept: list[int], right) -> None:
        """What has been cut off child i becomes the next child; the child keeps ``size`` symbols, ``kept`` of each."""
        sizes, counts, children, _ = node
        sizes.insert(i + 1, sizes[i] - size)
        sizes[i] = size
        for c, n in zip(counts, kept, strict=True):
            c.insert(i + 1, c[i] - n)
            c[i] = n
        children.insert(i + 1, right)

    def symbols(self) -> np.ndarray:
        level, last = [self.root], self.root[3]
        while not last:
            level = [x for node in level for x in node[2]]
            last = level[0][3]
        leaves = [x for node in level for x in node[2]]
        return np.concatenate([np.frombuffer(x, np.uint8) if type(x) is bytearray else np.array(x, np.int64) for x in leaves])


def tree_insert(codes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """String after string, symbol after symbol from its end, into a balanced tree: no block is ever sorted."""
    sigma = int(codes.max(initial=1))
    tree = SymbolTree(sigma)
    for j in range(len(bounds) - 1):
        at = j  # behind the terminators of all earlier strings
        text = codes[bounds[j] : bounds[j + 1]].tolist()
        for c in reversed(text):
            # the string's own terminator isn't in the tree yet, which the added one stands for
            at = tree.smaller(c) + tree.insert(at, c, c) + 1
        tree.insert(at, 0, 0)
    return tree.symbols()


BUILDERS = {"brute": brute, "block_append": block_append, "backward_single": backward_single, "column_wise": column_wise, "tree_insert": tree_insert}
