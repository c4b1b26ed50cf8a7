"""Approximate nearest neighbours by inner product over robust-pruned directed graphs, one for each shard.

Inner products become distances by one more coordinate that gives all vectors of a shard the same length. A graph grows by
batches of doubling size: a beam search from the entry proposes neighbours, pruning keeps a neighbour only while no kept one
is nearer to it by the factor ``RELAX``, and reverse edges are pruned likewise. Every query searches every shard with a
beam; what the beam holds is scored exactly, in double precision, on the original vectors.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusbwt.llm.common import batch_of
from corpusbwt.session import written

SHARD, DEGREE, BUILD_BEAM, SEARCH_BEAM, RELAX = 8192, 32, 64, 160, 1.2
WIDE, BATCH, TOP = 4, 256, 20
#: Queries that one copy of a shard's index answers; beyond it the index is sent to more tasks.
QUERIES_A_COPY = 100_000


def lengthened(vectors: np.ndarray) -> np.ndarray:
    """Vectors with one more coordinate, all of the longest one's length."""
    square = (vectors.astype(np.float64) ** 2).sum(1)
    return np.concatenate([vectors, np.sqrt(np.maximum(square.max(initial=0) - square, 0))[:, None]], 1).astype(np.float32)


def beam_search(points: np.ndarray, edges: np.ndarray, entry: int, queries: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Nodes (queries, beam) by falling inner product, and these products; -1 where fewer were reached.

    All queries step together: each opens its ``WIDE`` best unopened nodes and merges their unseen neighbours.
    """
    m, n = len(queries), len(points)
    rows = np.arange(m)[:, None]
    seen = np.zeros((m, n + 1), bool)
    seen[:, [entry, n]] = True
    ids = np.full((m, beam), n, np.int64)
    near = np.full((m, beam), -np.inf, np.float32)
    opened = np.ones((m, beam), bool)
    ids[:, 0], near[:, 0], opened[:, 0] = entry, queries @ points[entry], False
    live = np.arange(m)
    while len(live):
        rank = np.where(opened[live], -np.inf, near[live])
        wide = min(WIDE, beam)
        pick = np.argpartition(-rank, wide - 1, axis=1)[:, :wide]
        good = np.take_along_axis(rank, pick, 1) > -np.inf
        at = live[:, None]
        source = np.where(good, ids[at, pick], n)
        opened[at, pick] = True
        reach = edges[source].reshape(len(live), -1)
        reach = np.sort(reach, axis=1)
        fresh = ~seen[at, reach]
        fresh[:, 1:] &= reach[:, 1:] != reach[:, :-1]
        r, c = np.nonzero(fresh)
        node = reach[r, c]
        seen[live[r], node] = True
        found = np.full(reach.shape, -np.inf, np.float32)
        found[r, c] = np.einsum("ij,ij->i", points[node], queries[live[r]])
        all_near = np.concatenate([near[live], found], 1)
        all_ids = np.concatenate([ids[live], reach], 1)
        all_open = np.concatenate([opened[live], found == -np.inf], 1)
        keep = np.argpartition(-all_near, beam - 1, axis=1)[:, :beam]
        near[live] = np.take_along_axis(all_near, keep, 1)
        ids[live] = np.take_along_axis(all_ids, keep, 1)
        opened[live] = np.take_along_axis(all_open, keep, 1)
        live = live[~opened[live].all(1)]
    order = np.argsort(-near, axis=1, kind="stable")
    ids, near = ids[rows, order], near[rows, order]
    return np.where(near > -np.inf, ids, -1), near


def pruned(points: np.ndarray, nodes: np.ndarray, options: np.ndarray) -> np.ndarray:
    """Robustly pruned neighbours (nodes, DEGREE) out of options (nodes, any; -1 for none), -1 behind them."""
    m = len(nodes)
    options = np.sort(options, axis=1)
    bad = (options < 0) | (options == nodes[:, None])
    bad[:, 1:] |= options[:, 1:] == options[:, :-1]
    held = points[np.where(bad, 0, options)]
    far = ((held - points[nodes][:, None]) ** 2).sum(2)
    far[bad] = np.inf
    order = np.argsort(far, axis=1)
    options, far = np.take_along_axis(options, order, 1), np.take_along_axis(far, order, 1)
    held = np.take_along_axis(held, order[:, :, None], 1)
    square = (held**2).sum(2)
    between = square[:, :, None] + square[:, None, :] - 2 * np.matmul(held, held.transpose(0, 2, 1))
    alive = far < np.inf
    out = np.full((m, DEGREE), -1, np.int64)
    rows = np.arange(m)
    for slot in range(DEGREE):
        first = alive.argmax(1)
        on = alive[rows, first]
        if not on.any():
            break
        out[on, slot] = options[on, first[on]]
        alive &= ~((RELAX * RELAX * between[rows, first] <= far) & on[:, None])
        alive[rows, first] = False
    return out


def build(points: np.ndarray) -> tuple[np.ndarray, int]:
    """Edges (points + 1, DEGREE), padded by the number of points, and the entry, the point nearest to the mean."""
    n = len(points)
    edges = np.full((n + 1, DEGREE), n, np.int64)
    entry = int(np.argmax(points @ points.mean(0)))
    order = np.random.default_rng(3).permutation(n)
    order = np.concatenate([[entry], order[order != entry]])
    done, size = 1, 1
    while done < n:
        part = order[done : done + size]
        found = np.concatenate([beam_search(points, edges, entry, points[p], BUILD_BEAM)[0] for p in np.array_split(part, -(-len(part) // BATCH))])
        if done < 4 * DEGREE:  # a few early points: all are options
            found = np.concatenate([found, np.tile(order[:done], (len(part), 1))], 1)
        for lo in range(0, len(part), BATCH):
            own = part[lo : lo + BATCH]
            kept = pruned(points, own, found[lo : lo + BATCH])
            edges[own] = np.where(kept < 0, n, kept)
        source, target = np.repeat(part, DEGREE), edges[part].ravel()
        source, target = source[target < n], target[target < n]
        order_ = np.argsort(target, kind="stable")
        source, target = source[order_], target[order_]
        hit, first, count = np.unique(target, return_index=True, return_counts=True)
        for lo in range(0, len(hit), BATCH):
            own, at, many = hit[lo : lo + BATCH], first[lo : lo + BATCH], count[lo : lo + BATCH]
            wide = int(many.max())
            grid = at[:, None] + np.arange(wide)
            new = np.where(np.arange(wide) < many[:, None], source[np.minimum(grid, len(source) - 1)], -1)
            old = edges[own]
            room = (old < n).sum(1) + many
            for fits in (True, False):
                pick = np.flatnonzero((room <= DEGREE) == fits)
                if not len(pick):
                    continue
                both = np.concatenate([np.where(old[pick] < n, old[pick], -1), new[pick]], 1)
                if fits:
                    both = -np.sort(-both, axis=1)[:, :DEGREE]
                    edges[own[pick]] = np.where(both < 0, n, both)
                else:
                    kept = pruned(points, own[pick], both)
                    edges[own[pick]] = np.where(kept < 0, n, kept)
        done += len(part)
        size = min(done, BATCH * 4)
    return edges, entry


class ShardIndex:
    """A shard's distinct vectors, the least ids of the rows that hold each, its graph and entry."""

    def __init__(self, vectors: np.ndarray, ids: np.ndarray, edges: np.ndarray | None = None, entry: int = 0):
        self.vectors, self.ids = vectors, ids
        self.points = lengthened(vectors)
        self.edges, self.entry = (edges, entry) if edges is not None else build(self.points)

    def dump(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, vectors=self.vectors, ids=self.ids, edges=self.edges.astype(np.int32), entry=self.entry)
        return out.getvalue()

    @classmethod
    def load(cls, raw: bytes) -> ShardIndex:
        with np.load(io.BytesIO(raw)) as held:
            return cls(held["vectors"], held["ids"], held["edges"].astype(np.int64), int(held["entry"]))

    def search(self, query_ids: np.ndarray, queries: np.ndarray, top: int) -> Iterator[tuple[int, int, float]]:
        """(query, id, score) of each query's ``top`` best rows here, its own row left out."""
        distinct, back = np.unique(queries, axis=0, return_inverse=True)
        wide = np.concatenate([distinct, np.zeros((len(distinct), 1))], 1).astype(np.float32)
        found, scores = [], []
        for part, own in zip(*(np.array_split(x, -(-len(distinct) // BATCH)) for x in (wide, distinct)), strict=True):
            nodes, _ = beam_search(self.points, self.edges, self.entry, part, min(SEARCH_BEAM, len(self.points)))
            exact = np.einsum("ijk,ik->ij", self.vectors[nodes], own)
            exact[nodes < 0] = -np.inf
            first = np.argsort(-exact, axis=1, kind="stable")[:, : top + 1]
            found.append(np.take_along_axis(nodes, first, 1))
            scores.append(np.take_along_axis(exact, first, 1))
        found, scores = np.concatenate(found), np.concatenate(scores)
        for i, j in enumerate(back.ravel()):
            rows = self.ids[found[j]]
            score = np.broadcast_to(scores[j][:, None], rows.shape)
            good = (rows >= 0) & (rows != query_ids[i]) & (score > -np.inf)
            rows, score = rows[good], score[good]
            for k in np.lexsort((rows, -score))[:top]:
                yield int(query_ids[i]), int(rows[k]), float(score[k])


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Distinct vectors of a partition with the least ids of each: enough for any result, however many rows are equal."""
    held: dict[bytes, list[int]] = {}
    schema = pa.schema([("vector", pa.binary()), ("ids", pa.list_(pa.int64()))])

    def out() -> pa.RecordBatch:
        made = batch_of(schema, [list(held), [sorted(set(x))[: TOP + 1] for x in held.values()]])
        held.clear()
        return made

    for batch in batches:
        for key, vector in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            ids = held.setdefault(np.array(vector, np.float64).tobytes(), [])
            ids.append(key)
            if len(ids) > 1024:
                ids[:] = sorted(set(ids))[: TOP + 1]
        if len(held) > 1 << 15:
            yield out()
    if held:
        yield out()


def _built(table: pa.Table) -> pa.Table:
    merged: dict[bytes, list[int]] = {}
    for vector, ids in zip(table.column("vector").to_pylist(), table.column("ids").to_pylist(), strict=True):
        merged.setdefault(vector, []).extend(ids)
    order = sorted(merged)
    ids = np.full((len(order), TOP + 1), -1, np.int64)
    for i, key in enumerate(order):
        own = sorted(set(merged[key]))[: TOP + 1]
        ids[i, : len(own)] = own
    vectors = np.frombuffer(b"".join(order), np.float64).reshape(len(order), -1)
    index = ShardIndex(vectors, ids)
    return pa.table({"shard": pa.array([table.column("shard")[0].as_py()], pa.int32()), "body": pa.array([index.dump()], pa.binary())})


def _searched(top: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])
        at, index, waiting = None, None, []

        def flush() -> pa.RecordBatch:
            ids, vectors = zip(*waiting, strict=True)
            waiting.clear()
            rows = list(index.search(np.array(ids, np.int64), np.stack([np.frombuffer(v, np.float64) for v in vectors]), top))
            return batch_of(schema, list(zip(*rows, strict=True)) if rows else [[], [], []])

        for batch in batches:
            for shard, copy, query, body in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if query is None:
                    if waiting:
                        yield flush()
                    at, index = (shard, copy), ShardIndex.load(body)
                elif at == (shard, copy):
                    waiting.append((query, body))
                    if len(waiting) == 4 * BATCH:
                        yield flush()
        if waiting:
            yield flush()

    return run


def usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """Rows (vec_id, vector) that take part: an id, and a vector of the commonest size, finite and not zero."""
    rows = df.select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector_col, lambda x: x.cast("double")).alias("vector"))
    finite = F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = rows.where(F.col("vec_id").isNotNull() & F.col("vector").isNotNull()).where(finite & F.exists("vector", lambda x: x != 0))
    size = rows.groupBy(F.size("vector").alias("size")).count().orderBy(F.desc("count"), "size").limit(1).collect()
    return rows.where(F.size("vector") == (size[0]["size"] if size else 0))


def nearest(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", *, every: int = 20, top: int = TOP) -> DataFrame:
    """Of each row whose id is divisible by ``every``: rank, vec_id and score of its ``top`` (at most TOP) nearest other rows.

    Nearness is the inner product; ties go to the smaller id. Vectors that are null, zero, of an unusual size, or hold
    null or non-finite components take no part. Rows that repeat an id are one row. An empty table gives no rows.
    """
    rows = usable(df, id_col, vector_col)
    single = written(rows.mapInArrow(_grouped, "vector binary, ids array<long>"))
    shards = max(1, -(-single.count() // SHARD))
    index = written(single.withColumn("shard", F.pmod(F.xxhash64("vector"), F.lit(shards)).cast("int")).groupBy("shard").applyInArrow(_built, "shard int, body binary"))
    asked = rows.where(F.col("vec_id") % every == 0).select("vec_id", "vector").dropDuplicates(["vec_id"])

    def raw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("query", pa.int64()), ("body", pa.binary())])
        for batch in batches:
            yield batch_of(schema, [batch.column(0), [np.array(v, np.float64).tobytes() for v in batch.column(1).to_pylist()]])

    asked = written(asked.mapInArrow(raw, "query long, body binary"))
    copies = max(1, -(-asked.count() // QUERIES_A_COPY))
    asked = asked.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.pmod(F.xxhash64("query"), F.lit(copies)).cast("int").alias("copy"), "query", "body")
    held = index.select("shard", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy"), F.lit(None).cast("long").alias("query"), "body")
    lots = held.union(asked).repartition(max(1, shards * copies), "shard", "copy").sortWithinPartitions("shard", "copy", F.col("query").asc_nulls_first())
    found = lots.mapInArrow(_searched(top), "query_id long, vec_id long, score double")
    best = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", best).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
