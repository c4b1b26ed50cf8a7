"""The block-append build over stored pages: rank a block in the index so far, sort it, insert its symbols, commit."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusbwt.functions.alphabet import Alphabet
from corpusbwt.operators import ranking, suffixsort
from corpusbwt.operators.numbering import with_row_index
from corpusbwt.operators.stringset import assign_blocks
from corpusbwt.plans import planner
from corpusbwt.plans.store import StoredIndex
from corpusbwt.session import release, written


@dataclass
class StageLog:
    """Seconds and work of each stage of each block."""

    rows: list[tuple[int, str, int, float]] = field(default_factory=list)

    def timed(self, block: int, stage: str, symbols: int, run: Callable):
        begun = time.perf_counter()
        out = run()
        self.rows.append((block, stage, symbols, time.perf_counter() - begun))
        return out

    def frame(self, spark: SparkSession) -> DataFrame:
        """``(block, stage, symbols, seconds, rate)``; rates in symbols a second."""
        rows = [(b, s, n, t, n / max(t, 1e-9)) for b, s, n, t in self.rows]
        return spark.createDataFrame(rows, "block int, stage string, symbols long, seconds double, rate double")


def _sorted(block: DataFrame, sorter: str) -> DataFrame:
    """A block's suffixes, stored: in order ``(pos, sid, k, sym)``, or by strings ``(sid, pos, sym)`` where one task sorts."""
    return written(suffixsort.places_local(block) if sorter == "local" else suffixsort.suffix_array(block, sorter))


def append_block(index: StoredIndex, block: DataFrame, *, sorter: str = "auto", ranker: str = "auto", reverse: bool = False, old: DataFrame | None = None, block_id: int = 0, log: StageLog | None = None, presorted: DataFrame | None = None, q: int = 1) -> StoredIndex:
    """Append a block of strings ``(sid, s, len)`` to an index; committed as one version.

    Ranks never wait for the block's order: they lead its sort, whose rows carry symbol and rank, or (with a block that
    was sorted ahead) are joined to it.
    """
    log = log or StageLog()
    n, longest, average = planner.measure(block)
    count = block.count()
    if sorter == "auto":
        sorter = planner.choose_sorter(n, longest, average)
    by_string = sorter == "local"
    if not index.manifest.shards:
        sa = presorted if presorted is not None else log.timed(block_id, "sort", n, lambda: _sorted(block, sorter))
        log.timed(block_id, "insert", n, lambda: index.bulk_load(sa, count))
    else:
        start = 0 if reverse else index.manifest.m
        strategy = planner.choose_ranker(index, block, old is not None) if ranker == "auto" else ranker
        whole = by_string and strategy == "replicated"
        rank = ranking.chained if whole else lambda *a, **o: ranking.compute_ranks(*a, strategy, old=old, **o)
        ranks = log.timed(block_id, "rank", n, lambda: written(rank(block, index, start=start, q=q)))
        if presorted is None and sorter == "direct":
            new = log.timed(block_id, "sort", n, lambda: ranking.ordered_new(block, ranks))
        else:
            sa = presorted if presorted is not None else log.timed(block_id, "sort", n, lambda: _sorted(block, sorter))
            if whole:
                new = sa.select("sid", F.col("pos").alias("ord"), "sym").join(ranks, "sid")
            else:
                if by_string:
                    sa = sa.select("sid", F.posexplode(F.arrays_zip("pos", "sym")).alias("k", "x")).select("x.pos", "sid", "k", "x.sym")
                new = ranking.reorder(ranks, sa).select(F.col("pos").alias("ord"), "g", "sym")
        log.timed(block_id, "insert", n, lambda: index.insert(new.select("g", "ord", "sym"), count))
        release(ranks)
    if block_id not in index.manifest.blocks:
        index.manifest.blocks.append(block_id)
    index.commit()
    return index


def build(strings: DataFrame, path: str, *, m_suffixes: int | None = None, blocks: int | None = None, alphabet: Alphabet | None = None, sorter: str = "auto", ranker: str = "auto", order: str = "forward", overlap: bool | None = None, ahead: int = 8, log: StageLog | None = None, q: int = 1, **options) -> StoredIndex:
    """An index of a string set ``(sid, s, len)``, block after block.

    ``order='reverse'`` appends the last block first, with terminators below the old ones; the transform is the same.
    ``overlap`` sorts blocks ahead, up to ``ahead`` of them at once, while those before are ranked and inserted; it is on
    of itself where blocks are sorted by one task each. Options: page, spacing, packing, shard_symbols.
    """
    spark = strings.sparkSession
    if m_suffixes is None and blocks is None:
        m_suffixes = planner.choose(strings).m_suffixes
    held = written(assign_blocks(strings, m_suffixes, blocks=blocks))
    index = StoredIndex.create(spark, path, alphabet or Alphabet.from_strings(held, "s"), **options)
    ids = sorted((r[0] for r in held.select("block_id").distinct().collect()), reverse=order == "reverse")
    part = lambda b: held.where(F.col("block_id") == b)
    log = log or StageLog()

    how = planner.choose_sorter(*planner.measure(held, per_block=True)) if sorter == "auto" else sorter
    if overlap is None:
        overlap = how == "local" and len(ids) > 1

    def presort(b: int) -> DataFrame:
        block = part(b)
        return log.timed(b, "sort", planner.measure(block)[0], lambda: _sorted(block, how))

    with ThreadPoolExecutor(max(1, ahead)) as pool:
        waiting = {b: pool.submit(presort, b) for b in ids[:ahead]} if overlap else {}
        for i, b in enumerate(ids):
            presorted = waiting.pop(b).result() if overlap else None
            if overlap and i + ahead < len(ids):
                waiting[ids[i + ahead]] = pool.submit(presort, ids[i + ahead])
            older = held.where(F.col("block_id") > b if order == "reverse" else F.col("block_id") < b)
            append_block(index, part(b), sorter=how, ranker=ranker, reverse=order == "reverse", old=older, block_id=int(b), log=log, presorted=presorted, q=q)
            if presorted is not None:
                release(presorted)
    release(held)
    return index


def append(index: StoredIndex, df: DataFrame, text_col: str, order_cols: list[str], *, batch_id: int | None = None, source: str = "", **options) -> StoredIndex:
    """Append new strings, numbered behind the indexed ones; a batch of a source that has been applied changes nothing.

    Sources number their batches by themselves: a stream's is its checkpoint. Symbols that the index lacks are admitted.
    """
    mark = f"{source}#{batch_id}"
    if batch_id is not None and mark in index.manifest.batches:
        return index
    base = index.manifest.m
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = with_row_index(df.select(*order_cols, text.alias("s"), F.length(text).alias("len")), order_cols, "_n")
    block = written(rows.withColumn("sid", F.col("_n") + base).drop("_n"))
    if batch_id is not None:
        index.manifest.batches.append(mark)
    if not block.limit(1).count():
        return index
    index.widen(set(Alphabet.from_strings(block, "s").points))
    options.setdefault("block_id", max(index.manifest.blocks, default=-1) + 1)
    append_block(index, block, **options)
    release(block)
    return index
