"""Transforms of whole sets from groups of strings: each group by array code in one task, then one inserted in another.

Suffixes of one set, ranked in the transform of another, have ranks that never contradict their order. So the sorted ranks
and the set's own transform are all that an insertion needs: nothing is joined by suffix, and no suffix text is moved. Ranks
come from chains through transforms of at most ``MOST_SENT`` rows, sent to tasks one at a time; a larger transform is ranked
in through the transforms of its parts, whose ranks add up. What a task holds is bounded by ``GROUP`` and ``MOST_SENT``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.functions.kernels import chain_ranks, flat_codes, insert_symbols, rank_engine, row_ranges
from corpusbwt.operators.ranged import Sorted, alphabet_of
from corpusbwt.plans.store import locate, split_page
from corpusbwt.session import release, ship, tidy, written

#: Suffixes of a group that one task takes, and rows of a stored piece of a transform.
GROUP = 1 << 24
PIECE = 1 << 20
#: Suffixes whose chains run side by side in a task; the longest string sets the number of steps.
CHAINED = 1 << 23
#: Suffixes that a task ranks in several parts; every task makes each part's counters anew.
RANKED = 1 << 25
#: Rows of a transform that is sent to tasks as a whole.
MOST_SENT = 3 << 26
#: Merges that run side by side, of parts of up to so many rows; larger ones run one by one.
BESIDE, MOST_BESIDE = 3, 1 << 26
#: Groups of strings of which the driver keeps the sizes.
CELLS = 1 << 16

_PIECES = "group_id int, bucket int, n long, sym binary"
_PARTS = "bucket int, kind int, at long, n long, body binary"


@dataclass
class Part:
    """A stored transform of the strings ``first`` to ``last - 1``, and those it was made from where it is too large to be sent."""

    held: Sorted
    first: int
    last: int
    parts: list[Part] | None = None

    @property
    def sent(self) -> list[Part]:
        return self.parts or [self]

    def joined(self, other: Part, held: Sorted, q: int) -> Part:
        both = sorted([*self.sent, *other.sent], key=lambda p: p.first)
        return Part(held, min(self.first, other.first), max(self.last, other.last), both if held.n > MOST_SENT // q else None)


def cells(strings: DataFrame, most: int) -> list[tuple[int, int, int]]:
    """Consecutive strings of about ``most`` suffixes: first number, the next one's first, suffixes. A longer string stands alone."""
    count = strings.count()
    width = count // CELLS + 1
    found = sorted(strings.groupBy(F.floor(F.col("sid") / width).alias("cell")).agg(F.sum(F.col("len").cast("long") + 1).alias("n"), F.min("sid").alias("lo"), F.max("sid").alias("hi")).collect(), key=lambda r: r["cell"])
    out: list[tuple[int, int, int]] = []
    for r in found:
        if out and out[-1][2] + r["n"] <= most:
            out[-1] = (out[-1][0], r["hi"] + 1, out[-1][2] + r["n"])
        else:
            out.append((r["lo"], r["hi"] + 1, r["n"]))
    return out


def string_at(strings: DataFrame, upto: int) -> int:
    """The first string before which there are ``upto`` suffixes or more; behind the last one, if there is none."""
    width, before = strings.count() // CELLS + 1, 0
    sized = strings.select("sid", (F.col("len").cast("long") + 1).alias("n"), F.floor(F.col("sid") / width).alias("cell"))
    last = 0
    for r in sorted(sized.groupBy("cell").agg(F.sum("n").alias("n"), F.max("sid").alias("hi")).collect(), key=lambda r: r["cell"]):
        if before + r["n"] >= upto:
            for row in sorted(sized.where(F.col("cell") == r["cell"]).select("sid", "n").collect()):
                if before >= upto:
                    return row["sid"]
                before += row["n"]
            return r["hi"] + 1
        before, last = before + r["n"], r["hi"] + 1
    return last


def _of(strings: DataFrame, first: int, last: int) -> DataFrame:
    return strings.where((F.col("sid") >= first) & (F.col("sid") < last))


def _dtype(points: np.ndarray) -> type:
    return np.uint8 if len(points) <= 255 else np.uint16


def _coded(texts: list[str], points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Dense codes of texts, and their bounds; ``points`` has 0 and all code points in order."""
    table = np.zeros(int(points.max(initial=0)) + 1, _dtype(points))
    table[points[1:]] = np.arange(1, len(points))
    bounds = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))])
    codes = np.empty(int(bounds[-1]), table.dtype)
    for lo, hi in row_ranges(bounds, 1 << 20):  # code points take four bytes each
        codes[bounds[lo] : bounds[hi]] = table[flat_codes(texts[lo:hi])[0]]
    return codes, bounds


def groups(strings: DataFrame, build: Callable, most: int | None = None, points: np.ndarray | None = None) -> list[Part]:
    """The transforms of consecutive groups of strings ``(sid, s, len)``, side by side: ``build(codes, bounds)`` in one task each."""
    spark = strings.sparkSession
    ship(spark)
    points = alphabet_of(strings) if points is None else points
    cut = cells(strings, most or GROUP)
    starts, piece, wide = np.array([c[0] for c in cut], np.int64), PIECE, len(points) > 255

    def made(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held)
        group = table.column("group_id")[0].as_py()
        codes, bounds = _coded(table.column("s").to_pylist(), points)
        del table
        held.clear()
        symbols = build(codes, bounds).astype(">u2" if wide else np.uint8)
        parts = split_page(symbols, piece)
        yield pa.RecordBatch.from_arrays([pa.array([group] * len(parts), pa.int32()), pa.array(range(len(parts)), pa.int32()), pa.array([len(p) for p in parts], pa.int64()), pa.array([p.tobytes() for p in parts], pa.binary())], ["group_id", "bucket", "n", "sym"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            group = batch.column(2).to_numpy()
            edges = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(group)]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if held and a < b and held[0].column(2)[0].as_py() != group[a]:
                    yield from made(held)
                    held = []
                if a < b:
                    held.append(batch.slice(a, b - a))
        if held:
            yield from made(held)

    if not cut:
        return []
    dealt = locate(strings.select("sid", "s"), "sid", starts, list(range(len(cut))), "group_id")
    stored = written(dealt.repartitionByRange(len(cut), "group_id").sortWithinPartitions("sid").mapInArrow(run, _PIECES))
    sizes: dict[int, dict[int, int]] = {}
    for r in stored.select("group_id", "bucket", "n").collect():
        sizes.setdefault(r["group_id"], {})[r["bucket"]] = r["n"]
    tidy(spark)
    return [Part(Sorted(stored.where(F.col("group_id") == i).select("bucket", "n", "sym"), sizes[i], points, wide), lo, hi) for i, (lo, hi, _) in enumerate(cut)]


def sent(part: Part):
    """A part's pieces in order, compressed and broadcast: copies on the driver and in executors stay small."""

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bodies = [pa.compress(x.as_py(), "zstd", asbytes=True) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(x) for x in batch.column(1).to_pylist()], pa.int64()), pa.array(bodies, pa.binary())], ["bucket", "size", "body"])

    rows = part.held.rows.select("bucket", "sym").mapInArrow(packed, "bucket int, size long, body binary").toArrow().sort_by("bucket")
    return part.held.rows.sparkSession.sparkContext.broadcast(list(zip(rows.column("size").to_pylist(), rows.column("body").to_pylist(), strict=True)))


def _symbols(pieces: list[tuple[int, bytes]], wide: bool, dtype: type) -> np.ndarray:
    out, lo = np.empty(sum(n for n, _ in pieces) // (2 if wide else 1), dtype), 0
    for n, body in pieces:
        part = np.frombuffer(pa.decompress(body, n, "zstd"), ">u2" if wide else np.uint8)
        out[lo : lo + len(part)] = part
        lo += len(part)
    return out


def chained(strings: DataFrame, parts: list[Part], answer: Callable, schema: str, kept: list | None = None, q: int = 1) -> DataFrame:
    """Rows that ``answer(sid, sizes, ranks)`` makes of chunks of strings, with ranks of all their suffixes, in text order, summed
    over the parts, ``q`` symbols a step. Strings may be those of a part: the rank is then the number of smaller suffixes in it. What
    is broadcast is added to ``kept``, for a caller that stores the rows and can drop it."""
    points, wide = parts[0].held.points, parts[0].held.wide
    sigma, asked = len(points) - 1, [(sent(p), p.first, p.last) for p in parts]
    names = [c.split()[0] for c in schema.split(", ")]
    kind = np.uint32 if sum(p.held.n for p in parts) < 1 << 32 else np.int64
    if kept is not None:
        kept += [x[0] for x in asked]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        sid, texts = table.column(0).to_numpy(), table.column(1).to_pylist()
        cuts = row_ranges(np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])]), CHAINED)
        ranks: list[np.ndarray] = []
        for symbols, first, last in asked:
            engine = rank_engine(_symbols(symbols.value, wide, _dtype(points)), sigma)
            symbols.__dict__.pop("_value", None)  # one transform at a time
            for i, (lo, hi) in enumerate(cuts):
                got = chain_ranks(engine, *_coded(texts[lo:hi], points), np.clip(sid[lo:hi] - first, 0, last - first), q)
                if i < len(ranks):
                    ranks[i] += got.astype(kind)
                else:
                    ranks.append(got.astype(kind))
            del engine, got
        for i, (lo, hi) in enumerate(cuts):
            sizes = np.fromiter(map(len, texts[lo:hi]), np.int64, hi - lo)
            made = answer(sid[lo:hi], sizes, ranks[i])
            ranks[i] = np.zeros(0, kind)
            for a in range(0, len(made[0]), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array(c[a : a + (1 << 18)]) for c in made], names)

    spark = strings.sparkSession
    size = strings.agg(F.sum(F.col("len").cast("long") + 1)).first()[0] or 0
    tasks = max(spark.sparkContext.defaultParallelism, -(-size // RANKED) if len(parts) > 1 else 0)
    return strings.select("sid", "s").repartition(tasks, "sid").mapInArrow(run, schema)


def inserted(old: Part, new: Part, strings: DataFrame, q: int = 1) -> Part:
    """The transform of both: rows of ``new`` before the rows of ``old`` that their suffixes' ranks give. ``strings`` has those of
    ``new``, which come behind the old ones."""
    x, y = old.held, new.held
    spark, item, dtype = x.rows.sparkSession, 2 if x.wide else 1, ">u2" if x.wide else np.uint8
    names = sorted(x.sizes)
    starts = np.array([x.bases[b] for b in names], np.int64)

    def ranked(sid: np.ndarray, sizes: np.ndarray, total: np.ndarray) -> list:
        total.sort()
        cuts = np.append(np.searchsorted(total, starts.astype(total.dtype)), len(total))
        cuts[0] = 0
        own = np.flatnonzero(np.diff(cuts))
        bodies = [pa.compress(np.diff(total[cuts[i] : cuts[i + 1]], prepend=total.dtype.type(starts[i])).astype(np.uint32).tobytes(), "zstd", asbytes=True) for i in own]
        return [np.array([names[i] for i in own], np.int32), np.zeros(len(own), np.int32), np.zeros(len(own), np.int64), np.diff(cuts)[own], bodies]

    kept: list = []
    ranks = written(chained(_of(strings, new.first, new.last), old.sent, ranked, _PARTS, kept, q))
    for one in kept:
        one.destroy()
    counts = {r["bucket"]: r["n"] for r in ranks.groupBy("bucket").agg(F.sum("n").alias("n")).collect()}
    tidy(spark)
    added = np.array([counts.get(b, 0) for b in names], np.int64)
    edges, bases, piece = np.concatenate([[0], np.cumsum(added)]), y.bases, PIECE
    after, free = {}, 0
    for b, n in zip(names, added.tolist(), strict=True):
        after[b] = free
        free += max(1, -(-(x.sizes[b] + n) // piece))

    def routed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Slices of the new transform, each for the old piece that takes it."""
        for batch in batches:
            for bucket, n, sym in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                lo, i = bases[bucket], max(0, int(np.searchsorted(edges, bases[bucket], "right")) - 1)
                while i < len(names) and edges[i] < lo + n:
                    a, b = max(int(edges[i]), lo), min(int(edges[i + 1]), lo + n)
                    if a < b:
                        yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in ((names[i], pa.int32()), (1, pa.int32()), (a, pa.int64()), (b - a, pa.int64()), (sym[(a - lo) * item : (b - lo) * item], pa.binary()))], ["bucket", "kind", "at", "n", "body"])
                    i += 1

    def merge(table: pa.Table) -> pa.Table:
        bucket, rows = table.column("bucket")[0].as_py(), sorted(table.to_pylist(), key=lambda r: r["at"])
        kept = np.frombuffer(b"".join(r["body"] for r in rows if r["kind"] == 2), dtype)
        fresh = np.frombuffer(b"".join(r["body"] for r in rows if r["kind"] == 1), dtype)
        places = [np.cumsum(np.frombuffer(pa.decompress(r["body"], r["n"] * 4, "zstd"), np.uint32), dtype=np.uint32) for r in rows if r["kind"] == 0]
        made = insert_symbols(kept, np.sort(np.concatenate(places)), fresh) if places else kept
        parts = split_page(made, piece)
        return pa.table({"bucket": pa.array(range(after[bucket], after[bucket] + len(parts)), pa.int32()), "n": pa.array([len(p) for p in parts], pa.int64()), "sym": pa.array([p.tobytes() for p in parts], pa.binary())})

    fresh = y.rows.select("bucket", "n", "sym").mapInArrow(routed, _PARTS)
    stays = x.rows.select("bucket", F.lit(2).alias("kind"), F.lit(0).cast("long").alias("at"), "n", F.col("sym").alias("body"))
    out = written(ranks.union(fresh).union(stays).groupBy("bucket").applyInArrow(merge, "bucket int, n long, sym binary"))
    sizes = {r["bucket"]: r["n"] for r in out.select("bucket", "n").collect()}
    release(ranks)
    tidy(spark)
    return old.joined(new, Sorted(out, sizes, x.points, x.wide), q)


def transform(strings: DataFrame, build: Callable, *, blocks: int = 1, q: int = 1, points: np.ndarray | None = None) -> Sorted:
    """The transform of strings ``(sid, s, len)``: groups by ``build``, so many at least, each appended to its neighbour by chains of
    ``q`` symbols a step. Two at a step are for alphabets of up to ``MOST_PAIRED`` symbols."""
    total = strings.agg(F.sum(F.col("len").cast("long") + 1)).first()[0] or 0
    made = groups(strings, build, min(GROUP, -(-total // blocks)), points)
    if not made:
        return Sorted(strings.sparkSession.createDataFrame([], "bucket int, n long, sym binary"), {}, np.zeros(1, np.int32), False)
    return _appended(large(made, strings, q), strings, q).held


def large(made: list[Part], strings: DataFrame, q: int = 1) -> list[Part]:
    """Neighbours of several transforms merged, as far as they can be sent to tasks together; pairs of symbols take as much again."""
    most = MOST_SENT // q
    runs: list[list[Part]] = []
    for part in made:
        if runs and sum(p.held.n for p in runs[-1]) + part.held.n <= most:
            runs[-1].append(part)
        else:
            runs.append([part])
    return [_appended(run, strings, q) for run in runs]


def _appended(parts: list[Part], strings: DataFrame, q: int = 1) -> Part:
    """Neighbours merged in pairs, then the pairs: the later strings are ranked among the earlier ones, whichever of them are
    called new, and a suffix takes a step in each of about log2 of the parts."""
    while len(parts) > 1:
        pairs = [parts[i : i + 2] for i in range(0, len(parts), 2)]
        with ThreadPoolExecutor(BESIDE if max(p.held.n for p in parts) <= MOST_BESIDE else 1) as pool:
            parts = list(pool.map(lambda pair: _pair(pair, strings, q), pairs))
    return parts[0]


def _pair(parts: list[Part], strings: DataFrame, q: int = 1) -> Part:
    if len(parts) == 1:
        return parts[0]
    made = inserted(*parts, strings, q)
    for part in parts:
        # groups share a stored table, and what is still sent stays
        if all(p is not part for p in made.sent) and "group_id" not in part.held.rows._jdf.queryExecution().analyzed().toString():
            release(part.held.rows)
    return made
