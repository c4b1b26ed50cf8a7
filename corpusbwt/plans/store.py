"""The stored index: pages of symbols in shards, counters inside, and versioned manifests.

Pages hold p/2 to p symbols (a lone page of a shard may hold fewer). Everything a page says about positions and counts is
relative to its shard; only the manifest knows the order of shards and their totals, so an insertion rewrites the shards
it touches and no other. A shard belongs to one task, which makes it the unit of parallel work.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusbwt.functions.alphabet import Alphabet, pack_bits, unpack_bits
from corpusbwt.functions.kernels import RankEngine, auto_spacing, insert_symbols
from corpusbwt.session import release, ship, written

PAGE_SCHEMA = "shard_id int, page_no int, start_in_shard long, n_sym int, payload binary, occ_in_shard array<long>, occ_rel binary"
#: Bytes of symbols that may be sent to every task as one copy of the index; beyond it ranks are found shard by shard.
MOST_REPLICATED = 2 << 30


@dataclass
class Shard:
    shard_id: int
    n_sym: int
    occ: list[int]
    version: int


@dataclass
class Manifest:
    points: list[int]
    page: int = 1 << 16
    spacing: int = 0
    packing: str = "bytes"
    shard_symbols: int = 1 << 24
    version: int = 0
    m: int = 0
    shards: list[Shard] = field(default_factory=list)
    blocks: list[int] = field(default_factory=list)
    batches: list[str] = field(default_factory=list)

    @property
    def n(self) -> int:
        return sum(s.n_sym for s in self.shards)

    def dumps(self) -> str:
        return json.dumps(asdict(self))

    @classmethod
    def loads(cls, text: str) -> Manifest:
        told = json.loads(text)
        told["shards"] = [Shard(**s) for s in told["shards"]]
        return cls(**told)


def split_sizes(n: int, p: int, fill: float = 1.0) -> list[int]:
    """Near-equal parts of at most p, filled to about ``fill``: each is half full at least wherever there are several."""
    wanted = -(-n // max(1, int(p * min(1.0, max(0.5, fill)))))
    q = max(1, -(-n // p), min(wanted, n // -(-p // 2)))
    return [n // q + (i < n % q) for i in range(q)]


def split_page(symbols: np.ndarray, p: int, fill: float = 1.0) -> list[np.ndarray]:
    return np.split(symbols, np.cumsum(split_sizes(len(symbols), p, fill))[:-1])


def deal_pages(pages: list[np.ndarray], shards: list[int]) -> list[tuple[int, list[np.ndarray]]]:
    """A shard's pages dealt to shards of near-equal size, in order; pages stay whole."""
    ends = np.cumsum([len(x) for x in pages])
    cuts = np.searchsorted(ends, [ends[-1] * (i + 1) // len(shards) for i in range(len(shards) - 1)], "left") + 1 if len(pages) else []
    edges = [0, *np.minimum(cuts, len(pages)), len(pages)]
    return [(shard, pages[a:b]) for shard, a, b in zip(shards, edges[:-1], edges[1:], strict=True)]


class PageCodec:
    """Symbols to page rows and back, under an alphabet, a counter spacing and a packing (``bytes`` or ``bits``)."""

    def __init__(self, sigma: int, bits: int, spacing: int, packing: str):
        self.sigma, self.bits, self.packing = sigma, bits, packing
        self.spacing = spacing or auto_spacing(sigma)
        self.dtype = np.uint8 if sigma < 255 else np.uint16

    def payload(self, symbols: np.ndarray) -> bytes:
        return pack_bits(symbols, self.bits) if self.packing == "bits" else symbols.astype(self.dtype).tobytes()

    def symbols(self, payload: bytes, n: int) -> np.ndarray:
        return unpack_bits(payload, self.bits, n).astype(self.dtype) if self.packing == "bits" else np.frombuffer(payload, self.dtype)

    def counts(self, symbols: np.ndarray) -> np.ndarray:
        return np.bincount(symbols, minlength=self.sigma + 1).astype(np.int64)

    def sampled(self, symbols: np.ndarray) -> np.ndarray:
        """Counts before every ``spacing``-th symbol of the page."""
        blocks = -(-len(symbols) // self.spacing) if len(symbols) else 0
        cell = (np.arange(len(symbols)) // self.spacing) * (self.sigma + 1) + symbols
        each = np.bincount(cell, minlength=blocks * (self.sigma + 1)).reshape(blocks, self.sigma + 1)
        return (np.cumsum(each, axis=0) - each).astype(np.int32)

    def table(self, shard: int, pages: list[np.ndarray]) -> pa.Table:
        """A shard's page rows with starts and counters relative to the shard."""
        sizes = np.array([len(p) for p in pages], np.int64)
        counts = np.stack([self.counts(p) for p in pages]) if pages else np.zeros((0, self.sigma + 1), np.int64)
        before = np.cumsum(counts, axis=0) - counts
        return pa.table(
            {
                "shard_id": pa.array(np.full(len(pages), shard, np.int32)),
                "page_no": pa.array(np.arange(len(pages), dtype=np.int32)),
                "start_in_shard": pa.array(np.cumsum(sizes) - sizes),
                "n_sym": pa.array(sizes.astype(np.int32)),
                "payload": pa.array([self.payload(p) for p in pages], pa.binary()),
                "occ_in_shard": pa.array([b.tolist() for b in before], pa.list_(pa.int64())),
                "occ_rel": pa.array([self.sampled(p).tobytes() for p in pages], pa.binary()),
            }
        )


CHUNK_SCHEMA = "shard_id int, n long, at binary, ord binary, sym binary"


def chunked(rows: DataFrame, starts: np.ndarray, names: list[int]) -> DataFrame:
    """Rows ``(at, ord, sym)``, or arrays of them, routed to shards by a binary search of ``at`` in the sorted ``starts``.

    One row for each shard and batch, with its values as bytes, so an exchange moves few rows whatever a block's size.
    """
    held, ids = np.asarray(starts, np.int64), np.array(names, np.int32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(i) for i in range(3)]
            if pa.types.is_list(columns[0].type):
                columns = [c.flatten() for c in columns]
            for lo in range(0, len(columns[0]), 1 << 20):
                at, order, sym = (c.slice(lo, 1 << 20).to_numpy().astype(t) for c, t in zip(columns, (np.int64, np.int64, np.int32), strict=True))
                shard = np.maximum(np.searchsorted(held, at, "right") - 1, 0)
                moved = np.argsort(shard, kind="stable")
                for part in np.split(moved, np.flatnonzero(np.diff(shard[moved])) + 1):
                    if len(part):
                        yield pa.RecordBatch.from_pylist([{"shard_id": int(ids[shard[part[0]]]), "n": len(part), "at": at[part].tobytes(), "ord": order[part].tobytes(), "sym": sym[part].tobytes()}], _CHUNK)

    return rows.mapInArrow(run, CHUNK_SCHEMA)


_CHUNK = pa.schema([("shard_id", pa.int32()), ("n", pa.int64()), ("at", pa.binary()), ("ord", pa.binary()), ("sym", pa.binary())])


def _values(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Positions and symbols of a shard's chunks, in the order ``ord``."""
    at, order, sym = (np.frombuffer(b"".join(rows.column(c).to_pylist()), t) for c, t in (("at", np.int64), ("ord", np.int64), ("sym", np.int32)))
    moved = np.argsort(order)
    return at[moved], sym[moved]


class StoredIndex:
    """An index in a folder; every change writes a new version and then its manifest."""

    def __init__(self, spark: SparkSession, path: str, manifest: Manifest):
        self.spark, self.path, self.manifest = spark, path.rstrip("/"), manifest
        ship(spark)

    # Files

    @staticmethod
    def _fs(spark: SparkSession, path: str):
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where

    @classmethod
    def create(cls, spark: SparkSession, path: str, alphabet: Alphabet, **options) -> StoredIndex:
        """An empty index; options: page, spacing (0: by alphabet), packing, shard_symbols."""
        index = cls(spark, path, Manifest(list(alphabet.points), **options))
        index.commit()
        return index

    @classmethod
    def open(cls, spark: SparkSession, path: str, version: int | None = None) -> StoredIndex:
        fs, folder = cls._fs(spark, f"{path.rstrip('/')}/manifest")
        names = [s.getPath().getName() for s in fs.listStatus(folder)]
        found = sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))
        at = version if version is not None else found[-1]
        text = spark.read.text(f"{path.rstrip('/')}/manifest/v{at}.json", wholetext=True).first()[0]
        return cls(spark, path, Manifest.loads(text))

    def commit(self) -> None:
        """Write the manifest under a temporary name and rename it into place."""
        final = f"{self.path}/manifest/v{self.manifest.version}.json"
        fs, target = self._fs(self.spark, final)
        _, draft = self._fs(self.spark, f"{self.path}/manifest/.draft-v{self.manifest.version}")
        out = fs.create(draft, True)
        out.write(bytearray(self.manifest.dumps().encode()))
        out.close()
        if not fs.rename(draft, target):
            raise RuntimeError(f"version {self.manifest.version} exists already")
        self.__dict__.pop("symbols", None)

    # Views

    @property
    def alphabet(self) -> Alphabet:
        return Alphabet(tuple(self.manifest.points))

    @property
    def codec(self) -> PageCodec:
        a = self.alphabet
        return PageCodec(a.sigma, a.bits, self.manifest.spacing, self.manifest.packing)

    @property
    def starts(self) -> np.ndarray:
        """Row at which each shard starts (the offset vector's upper level)."""
        sizes = np.array([s.n_sym for s in self.manifest.shards], np.int64)
        return np.cumsum(sizes) - sizes

    def pages(self, shards: list[int] | None = None) -> DataFrame:
        """Page rows of the current version, pruned to some shards' files on request."""
        out = None
        wanted = [s for s in self.manifest.shards if shards is None or s.shard_id in set(shards)]
        for version in sorted({s.version for s in wanted}):
            ids = [s.shard_id for s in wanted if s.version == version]
            part = self.spark.read.schema(PAGE_SCHEMA).parquet(f"{self.path}/pages/v{version}").where(F.col("shard_id").isin(ids))
            out = part if out is None else out.unionByName(part)
        return out if out is not None else self.spark.createDataFrame([], PAGE_SCHEMA)

    def located_pages(self) -> DataFrame:
        """``(shard_id, page_no, start, n_sym)``: the page index and offset vector with global starts."""
        base = {s.shard_id: int(b) for s, b in zip(self.manifest.shards, self.starts, strict=True)}
        at = F.element_at(F.create_map(*[F.lit(x) for kv in base.items() for x in kv]), F.col("shard_id")) if base else F.lit(0)
        return self.pages().select("shard_id", "page_no", (at + F.col("start_in_shard")).cast("long").alias("start"), "n_sym")

    def rows(self) -> DataFrame:
        """The transform in row form ``(pos, sym)``, symbols as code points."""
        codec, points = self.codec, np.array((0, *self.manifest.points), np.int32)
        base = {s.shard_id: int(b) for s, b in zip(self.manifest.shards, self.starts, strict=True)}

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for shard, start, n, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    symbols = codec.symbols(payload, n)
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(n) + base[shard] + start), pa.array(points[symbols])], ["pos", "sym"])

        return self.pages().select("shard_id", "start_in_shard", "n_sym", "payload").mapInArrow(run, "pos long, sym int")

    @cached_property
    def symbols(self) -> np.ndarray:
        """All symbols in one array, for the replicated strategies; refused beyond MOST_REPLICATED bytes."""
        if self.manifest.n * self.codec.dtype().itemsize > MOST_REPLICATED:
            raise MemoryError("the index is too large to be replicated; use the strategies 'rounds' or 'merge'")
        order = {s.shard_id: i for i, s in enumerate(self.manifest.shards)}
        rows = self.pages().select("shard_id", "page_no", "n_sym", "payload").toArrow().to_pylist()
        rows.sort(key=lambda r: (order[r["shard_id"]], r["page_no"]))
        return np.concatenate([self.codec.symbols(r["payload"], r["n_sym"]) for r in rows]) if rows else np.zeros(0, self.codec.dtype)

    def engine(self) -> RankEngine:
        return RankEngine(self.symbols, self.alphabet.sigma, self.codec.spacing)

    # Changes

    def _write(self, pages: DataFrame) -> dict[int, Shard]:
        """Store a version's pages; totals of its shards come back, one row a shard."""
        version = self.manifest.version + 1
        where = f"{self.path}/pages/v{version}"
        pages.write.mode("overwrite").parquet(where)
        codec = self.codec

        def totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for shard, n, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([n], pa.int64()), pa.array([codec.counts(codec.symbols(payload, n)).tolist()], pa.list_(pa.int64()))], ["shard_id", "n", "occ"])

        stored = self.spark.read.schema(PAGE_SCHEMA).parquet(where).select("shard_id", "n_sym", "payload").mapInArrow(totals, "shard_id int, n long, occ array<long>")
        parts = stored.select("shard_id", "n", F.posexplode("occ").alias("code", "count")).groupBy("shard_id", "code").agg(F.sum("count").alias("count")).collect()
        out: dict[int, Shard] = {}
        for r in parts:
            shard = out.setdefault(r["shard_id"], Shard(r["shard_id"], 0, [0] * (self.alphabet.sigma + 1), version))
            shard.occ[r["code"]] = r["count"]
        for shard in out.values():
            shard.n_sym = sum(shard.occ)
        return out

    @staticmethod
    def _rows_of(bwt: DataFrame) -> int:
        kind = dict(bwt.dtypes)["pos"]
        return bwt.agg(F.sum(F.size("pos")) if kind.startswith("array") else F.count("*")).first()[0] or 0

    def bulk_load(self, bwt: DataFrame, m: int, *, fill: float = 0.75) -> StoredIndex:
        """Fill an empty index from a transform ``(pos, sym)``, rows or arrays of them: one task a shard, pages filled to
        ``fill`` (1/2 to 1)."""
        codec, alphabet = self.codec, self.alphabet
        per_shard, page = self.manifest.shard_symbols, self.manifest.page

        def run(table: pa.Table) -> pa.Table:
            _, points = _values(table)
            symbols = np.zeros(len(points), codec.dtype)
            symbols[points > 0] = alphabet.codes(points[points > 0])
            return codec.table(table.column("shard_id")[0].as_py(), split_page(symbols, page, fill))

        count = -(-rows_of // per_shard) if (rows_of := self._rows_of(bwt)) else 0
        dealt = chunked(bwt.select("pos", F.col("pos").alias("ord"), "sym"), np.arange(count) * per_shard, list(range(count)))
        made = self._write(dealt.groupBy("shard_id").applyInArrow(run, PAGE_SCHEMA))
        self.manifest.shards = [made[i] for i in sorted(made)]
        self.manifest.version += 1
        self.manifest.m = m
        return self

    def insert(self, new: DataFrame, strings_added: int) -> StoredIndex:
        """Insert ``(g, ord, sym)``, rows or arrays of them: symbols, in the order ``ord``, before the old rows ``g``; only
        touched shards are rewritten.

        Rows are routed by a binary search in the shards' starts and meet their shard's pages in one task, which edits
        page by page and splits what overflows. A shard that grows beyond the set size is dealt to several, whose numbers
        are set ahead from counted rows.
        """
        codec, alphabet, p, most = self.codec, self.alphabet, self.manifest.page, self.manifest.shard_symbols
        starts = {s.shard_id: int(b) for s, b in zip(self.manifest.shards, self.starts, strict=True)}
        routed = written(chunked(new.select("g", "ord", "sym"), self.starts, [s.shard_id for s in self.manifest.shards]))
        added = {r["shard_id"]: r["n"] for r in routed.groupBy("shard_id").agg(F.sum("n").alias("n")).collect()}
        free = max(starts, default=-1) + 1
        parts: dict[int, list[int]] = {}
        for s in self.manifest.shards:
            more = max(0, -(-(s.n_sym + added.get(s.shard_id, 0)) // max(most, p)) - 1) if s.shard_id in added else 0
            parts[s.shard_id] = [s.shard_id, *range(free, free + more)]
            free += more

        def run(key: tuple, rows: pa.Table, pages: pa.Table) -> pa.Table:
            pages = pages.sort_by("page_no")
            shard = pages.column("shard_id")[0].as_py()
            at, points = _values(rows)
            at = at - starts[shard]
            symbols = np.zeros(len(points), codec.dtype)
            symbols[points > 0] = alphabet.codes(points[points > 0])
            begin = pages.column("start_in_shard").to_numpy()
            page = np.maximum(np.searchsorted(begin, at, "right") - 1, 0)
            cuts = np.searchsorted(page, np.arange(len(begin) + 1))
            out: list[np.ndarray] = []
            for i, (n, payload) in enumerate(zip(pages.column("n_sym").to_pylist(), pages.column("payload").to_pylist(), strict=True)):
                old = codec.symbols(payload, n)
                lo, hi = cuts[i], cuts[i + 1]
                out += split_page(insert_symbols(old, at[lo:hi] - begin[i], symbols[lo:hi]), p) if hi > lo else [old]
            return pa.concat_tables([codec.table(name, own) for name, own in deal_pages(out, parts[shard])])

        old = self.pages(sorted(added))
        merged = routed.groupBy("shard_id").cogroup(old.groupBy("shard_id")).applyInArrow(run, PAGE_SCHEMA)
        made = self._write(merged)
        release(routed)
        after = [made.get(i) or (s if i == s.shard_id and i not in added else None) for s in self.manifest.shards for i in parts[s.shard_id]]
        self.manifest.shards = [s for s in after if s is not None]
        self.manifest.version += 1
        self.manifest.m += strings_added
        return self

    def widen(self, points: set[int]) -> StoredIndex:
        """Admit further symbols: codes are dense and in order, so all pages are coded anew, each by itself."""
        old, wider = self.alphabet, Alphabet(tuple(sorted({*self.manifest.points, *points})))
        if wider == old:
            return self
        kept = np.concatenate([[0], wider.codes(np.array(old.points, np.int64))]).astype(np.int64)
        before, after = self.codec, PageCodec(wider.sigma, wider.bits, self.manifest.spacing, self.manifest.packing)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    symbols = kept[before.symbols(row["payload"], row["n_sym"])].astype(after.dtype)
                    occ = np.zeros(wider.sigma + 1, np.int64)
                    occ[kept] = row["occ_in_shard"]
                    row |= {"payload": after.payload(symbols), "occ_in_shard": occ.tolist(), "occ_rel": after.sampled(symbols).tobytes()}
                    yield pa.RecordBatch.from_pylist([row], batch.schema)

        pages = self.pages().mapInArrow(run, PAGE_SCHEMA)
        self.manifest.points = list(wider.points)
        if self.manifest.shards:
            made = self._write(pages)
            self.manifest.shards = [made[s.shard_id] for s in self.manifest.shards]
            self.manifest.version += 1
        self.__dict__.pop("symbols", None)
        return self

    def rebalance(self) -> StoredIndex:
        """Deal all rows to shards of the set size again, once insertions have made some of them much larger."""
        return self.bulk_load(self.rows(), self.manifest.m)


def locate(points: DataFrame, col: str, starts: np.ndarray, names: list[int], name: str) -> DataFrame:
    """Adds the last of the sorted ``starts`` at or before a position, by its name: a vectorised binary search."""
    held, ids = np.asarray(starts, np.int64), np.array(names, np.int32)

    @F.pandas_udf("int")
    def find(at: pd.Series) -> pd.Series:
        return pd.Series(ids[np.maximum(np.searchsorted(held, at.to_numpy(), "right") - 1, 0)])

    return points.withColumn(name, find(col))
