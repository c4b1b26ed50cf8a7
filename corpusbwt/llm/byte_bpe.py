"""Byte-level BPE encoding and decoding by recursive DuckDB queries inside each partition.

A worker finds the pieces of its texts by array scans, keeps a table of the pieces met so far, and hands the new ones to
DuckDB: rows of (piece, position, token) join the merge table, every piece contracts its leftmost pair of least rank, and
the query recurs until no piece has a pair left. Decoding joins tokens with their bytes and aggregates them in order.

Pieces are first cut where two bytes stand side by side in no token, which no contraction can cross. What is still long
contracts all places of its least rank in one step, from the left, as far as the next contraction would surely be the next
of those places: a place whose new token could join a neighbour at a lower rank is the last of its step.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache

import duckdb
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from corpusbwt.llm import textscan, vocabularies
from corpusbwt.llm.common import batch_of, texts_of, trimmed

#: Parts of more bytes contract all places of a rank in a step; one a step costs the square of the length.
LONG_PART = 64
#: Sum of squared part lengths that one stepwise query takes (it keeps a list of tokens for each merge), and sum of lengths
#: of the other: memory is bounded by them, and by the length of a single part beyond them.
MOST_STEPS, MOST_LONG = 1 << 24, 1 << 18
#: Memory of a worker's DuckDB, and what it needs for each byte of a part beyond ``MOST_LONG``.
MEMORY_MB, BYTES_EACH = 400, 1000
#: Symbols of text taken at once: new pieces of a slice share one recursive query.
SLICE = 1 << 21

_CONTRACT = """
WITH RECURSIVE state AS (
    SELECT piece, list(token ORDER BY pos) AS tokens, 0 AS step FROM start GROUP BY piece
    UNION ALL
    (WITH positions AS (
        SELECT piece, unnest(range(1, len(tokens))) AS pos, unnest(tokens[:-2]) AS token, unnest(tokens[2:]) AS right_token FROM state),
     chosen AS (
        SELECT piece, min({'made': made, 'at': pos}) AS best
        FROM positions JOIN merges ON positions.token = merges.left_token AND positions.right_token = merges.right_token
        GROUP BY piece)
     SELECT state.piece, list_concat(list_append(tokens[: best.at - 1], best.made), tokens[best.at + 2 :]), step + 1
     FROM state JOIN chosen ON state.piece = chosen.piece))
SELECT piece, unnest(range(len(tokens))) AS pos, unnest(tokens) AS token
FROM (SELECT piece, arg_max(tokens, step) AS tokens FROM state GROUP BY piece)
"""

_CONTRACT_ALL = """
WITH RECURSIVE state(piece, tokens) USING KEY (piece) AS (
    SELECT piece, list(token ORDER BY pos) FROM start GROUP BY piece
    UNION
    (WITH positions AS MATERIALIZED (
        SELECT piece, unnest(range(1, len(tokens) + 1)) AS pos, unnest(tokens) AS token, unnest(list_append(tokens[2:], NULL)) AS right_token FROM state),
     pairs AS MATERIALIZED (
        SELECT piece, pos, made FROM positions JOIN merges ON positions.token = merges.left_token AND positions.right_token = merges.right_token),
     least AS (SELECT piece, min(made) AS made FROM pairs GROUP BY piece),
     runs AS (SELECT piece, made, pos, pos - row_number() OVER (PARTITION BY piece ORDER BY pos) AS run FROM pairs JOIN least USING (piece, made)),
     apart AS MATERIALIZED (SELECT piece, made, pos FROM runs QUALIFY row_number() OVER (PARTITION BY piece, run ORDER BY pos) % 2 = 1),
     around AS (
        SELECT apart.piece, apart.made, apart.pos, nextto.token AS after, CASE WHEN lag(apart.pos) OVER w = apart.pos - 2 THEN apart.made ELSE ahead.token END AS before
        FROM apart LEFT JOIN positions AS ahead ON apart.piece = ahead.piece AND apart.pos - 1 = ahead.pos
        LEFT JOIN positions AS nextto ON apart.piece = nextto.piece AND apart.pos + 2 = nextto.pos
        WINDOW w AS (PARTITION BY apart.piece ORDER BY apart.pos)),
     stops AS (
        SELECT piece, min(pos) AS last
        FROM (SELECT piece, pos, made AS own, before AS left_token, made AS right_token FROM around UNION ALL SELECT piece, pos, made, made, after FROM around) AS sides
        JOIN sooner USING (left_token, right_token) WHERE sooner.made < own GROUP BY piece),
     chosen AS MATERIALIZED (SELECT apart.* FROM apart LEFT JOIN stops USING (piece) WHERE last IS NULL OR pos <= last)
     SELECT piece, list(coalesce(made, token) ORDER BY pos)
     FROM positions LEFT JOIN chosen USING (piece, pos)
     WHERE piece IN (SELECT piece FROM chosen) AND (piece, pos) NOT IN (SELECT piece, pos + 1 FROM chosen)
     GROUP BY piece))
SELECT piece, unnest(range(len(tokens))) AS pos, unnest(tokens) AS token FROM state
"""


class DuckBpe:
    """One worker's DuckDB session with the vocabulary and its merge table."""

    def __init__(self, path: str):
        self.ranks = vocabularies.ranks(path)
        self.tokens = {i: t for t, i in self.ranks.items()}
        self.single = np.array([self.ranks[bytes([b])] for b in range(256)], np.int32)
        rows = [(self.ranks[t[:i]], self.ranks[t[i:]], r) for t, r in self.ranks.items() for i in range(1, len(t)) if t[:i] in self.ranks and t[i:] in self.ranks]
        left, right, made = (np.array(c, np.int32) for c in zip(*rows, strict=True))
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": f"{MEMORY_MB}MB", "temp_directory": ""})
        self._table("merges", {"left_token": left, "right_token": right, "made": made})
        early = (made < left) | (made < right)
        self._table("sooner", {"left_token": left[early], "right_token": right[early], "made": made[early]})
        self._table("vocabulary", {"token": np.fromiter(self.tokens, np.int32, len(self.tokens)), "bytes": pa.array(list(self.tokens.values()), pa.binary())})
        self.joined = np.zeros((256, 256), bool)
        for t in map(np.frombuffer, self.ranks, [np.uint8] * len(self.ranks)):
            self.joined[t[:-1], t[1:]] = True

    def _table(self, name: str, columns: dict) -> None:
        held = pa.table({k: pa.array(v) if isinstance(v, np.ndarray) else v for k, v in columns.items()})
        self.db.register("incoming", held)
        self.db.execute(f"CREATE OR REPLACE TABLE {name} AS SELECT * FROM incoming")
        self.db.unregister("incoming")

    def encode(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all pieces in a row, and each piece's number of ids; parts go to DuckDB in queries of bounded work."""
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        raw = np.frombuffer(b"".join(pieces), np.uint8)
        piece = np.repeat(np.arange(len(pieces)), sizes)
        cut = np.ones(len(raw), bool)
        cut[1:] = (piece[1:] != piece[:-1]) | ~self.joined[raw[:-1], raw[1:]]
        starts = np.flatnonzero(cut)
        lengths = np.diff(np.append(starts, len(raw)))
        found = [(np.zeros(0, np.int64),) * 3]
        for query, parts, work, most in (
            (_CONTRACT, np.flatnonzero(lengths <= LONG_PART), lengths**2, MOST_STEPS),
            (_CONTRACT_ALL, np.flatnonzero(lengths > LONG_PART), lengths, MOST_LONG),
        ):
            for lo, hi in textscan.slices(work[parts], most):
                found.append(self._contract(query, raw, parts[lo:hi], starts, lengths))
        part, at, token = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.lexsort((at, part))
        return token[order].astype(np.int64), np.bincount(piece[starts[part]], minlength=len(pieces))

    def _contract(self, query: str, raw: np.ndarray, parts: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, ...]:
        """(part, place, token) rows of some parts of ``raw`` after all contractions."""
        sizes = lengths[parts]
        pos = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        self._table("start", {"piece": np.repeat(parts, sizes), "pos": pos, "token": self.single[raw[np.repeat(starts[parts], sizes) + pos]]})
        needs = MEMORY_MB + max(0, int(sizes.sum()) - MOST_LONG) * BYTES_EACH // 10**6
        if needs > MEMORY_MB and query is _CONTRACT_ALL:
            self.db.execute(f"SET memory_limit = '{needs}MB'")
        rows = self.db.execute(query).fetchnumpy()
        self.db.execute(f"SET memory_limit = '{MEMORY_MB}MB'")
        return tuple(np.asarray(rows[c], np.int64) for c in ("piece", "pos", "token"))

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> list[bytes]:
        """Bytes of each sequence of ids, joined in order of position."""
        owner = np.repeat(np.arange(len(counts)), counts)
        self._table("sequence", {"piece": owner.astype(np.int64), "pos": np.arange(len(ids)), "token": np.asarray(ids, np.int32)})
        rows = self.db.execute("SELECT piece, list(bytes ORDER BY pos) FROM sequence JOIN vocabulary USING (token) GROUP BY piece").fetchall()
        out = [b""] * len(counts)
        for piece, parts in rows:
            out[piece] = b"".join(parts)
        return out


class PieceBook:
    """Pieces met so far by this worker: number of ids, ids as text, bytes decoded from the ids."""

    def __init__(self, path: str, most: int = 1 << 20):
        self.engine, self.most = DuckBpe(path), most
        self._reset()

    def _reset(self) -> None:
        self.index = textscan.HashIndex()
        self.count = np.zeros(0, np.int64)
        self.ids: list[str] = []
        self.raw: list[bytes] = []

    def look_up(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Places of all pieces in this book, and each text's first piece with the total."""
        codes, bounds = textscan.codes_of(texts)
        starts = textscan.byte_level_starts(codes, bounds)
        ends = np.append(starts[1:], len(codes)) if len(starts) else starts
        hashes = textscan.span_hashes(codes, starts, ends)
        if len(self.ids) > self.most:
            self._reset()
        at, new = textscan.new_pieces(self.index, hashes)
        if len(new):
            pieces = [textscan.text_piece(codes, s, e).encode() for s, e in zip(starts[new], ends[new], strict=True)]
            ids, counts = self.engine.encode(pieces)
            words, cuts = list(map(str, ids.tolist())), np.concatenate([[0], np.cumsum(counts)]).tolist()
            self.index.add(hashes[new], np.arange(len(self.ids), len(self.ids) + len(new)))
            self.raw += self.engine.decode(ids, counts)
            self.ids += [" ".join(words[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
            self.count = np.concatenate([self.count, counts])
            at = self.index.find(hashes)
        return at, np.searchsorted(starts, bounds)


@cache
def book(path: str) -> PieceBook:
    return PieceBook(path)


def _slices(batch: pa.RecordBatch) -> Iterator[tuple[pa.Array, list[str]]]:
    texts = texts_of(batch.column(1))
    for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts)), SLICE):
        yield batch.column(0).slice(lo, hi - lo), texts[lo:hi]


def round_trip(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, path: str | None = None) -> DataFrame:
    """Per row: doc_id, n_tokens, SHA-256 of the decimal ids joined by spaces, SHA-256 of the bytes decoded from them.

    Special strings are ordinary text. A null text is an empty one: no ids, and both digests are of nothing. Rows are
    kept as they come, with null or repeated ids; an empty table gives no rows.
    """
    where = path or vocabularies.default_path("byte_bpe_50k.tiktoken")
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = book(where)
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])
            for keys, texts in _slices(batch):
                at, first = held.look_up(texts)
                totals = np.concatenate([[0], np.cumsum(held.count[at])])
                places, cuts = at.tolist(), first.tolist()
                ids, raw = held.ids.__getitem__, held.raw.__getitem__
                spans = [places[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
                yield batch_of(schema, [keys, np.diff(totals[first]), [hashlib.sha256(" ".join(map(ids, s)).encode()).hexdigest() for s in spans], [hashlib.sha256(b"".join(map(raw, s))).hexdigest() for s in spans]])

    return df.select(id_col, text_col).mapInArrow(trimmed(run), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, path: str | None = None) -> DataFrame:
    """Per row: the id column and ``ids``, an array of the text's ids (empty for a null text)."""
    where = path or vocabularies.default_path("byte_bpe_50k.tiktoken")
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = book(where)
        for batch in batches:
            schema = pa.schema([(id_col, batch.schema.types[0]), ("ids", pa.list_(pa.int32()))])
            for keys, texts in _slices(batch):
                at, first = held.look_up(texts)
                cuts = np.concatenate([[0], np.cumsum(held.count[at])])[first]
                flat = np.array(" ".join(map(held.ids.__getitem__, at.tolist())).split(), np.int32)
                yield batch_of(schema, [keys, pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array(flat))])

    return df.select(id_col, text_col).mapInArrow(trimmed(run), f"{id_col} {kind}, ids array<int>")


def decode(df: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", *, path: str | None = None) -> DataFrame:
    """Per row: the id column and ``decoded``, the bytes of its ids in order (null or empty ids: no bytes)."""
    where = path or vocabularies.default_path("byte_bpe_50k.tiktoken")
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        engine = book(where).engine
        for batch in batches:
            schema = pa.schema([(id_col, batch.schema.types[0]), ("decoded", pa.binary())])
            rows = [x or [] for x in batch.column(1).to_pylist()]
            sizes = np.fromiter(map(len, rows), np.int64, len(rows))
            for lo, hi in textscan.slices(sizes):
                flat = np.array([i for r in rows[lo:hi] for i in r], np.int64)
                yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), engine.decode(flat, sizes[lo:hi])])

    return df.select(id_col, ids_col).mapInArrow(trimmed(run), f"{id_col} {kind}, decoded binary")
