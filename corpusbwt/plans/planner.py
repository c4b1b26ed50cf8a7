"""Choices of sorter, ranking strategy and build from sizes, and the parameters that follow from memory."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.plans import store

#: Suffix text (bytes) that the direct sorter may carry for each suffix on average; longer strings go word by word.
DIRECT_BYTES = 512
#: Suffixes that one task sorts in memory (about 60 bytes each).
LOCAL_SUFFIXES = 8_000_000
#: Longest string whose chain may take one exchange a symbol.
MOST_ROUNDS = 1000


@dataclass(frozen=True)
class IndexPlan:
    m_suffixes: int
    sorter: str
    ranker: str
    build: str


def measure(strings: DataFrame, *, per_block: bool = False) -> tuple[int, int, float]:
    """Suffixes, longest string, average bytes of suffix text; with ``per_block`` the largest block's suffixes."""
    sums = F.sum(F.col("len").cast("long") + 1).alias("n"), F.max("len").alias("longest"), F.sum(F.col("len").cast("double") * (F.col("len") + 1) / 2).alias("text")
    if per_block:
        r = strings.groupBy("block_id").agg(*sums).agg(F.max("n").alias("n"), F.max("longest").alias("longest"), F.sum("text").alias("text"), F.sum("n").alias("all")).first()
        return r.n or 0, r.longest or 0, (r.text or 0.0) / max(1, r.all or 0)
    r = strings.agg(*sums).first()
    n = r.n or 0
    return n, r.longest or 0, (r.text or 0.0) / max(1, n)


def choose_sorter(n: int, longest: int, average: float) -> str:
    """direct while rows stay small, local while a task holds the block, else doubling or the sieve."""
    if average <= DIRECT_BYTES:
        return "direct"
    if n <= LOCAL_SUFFIXES:
        return "local"
    return "doubling" if longest > 1 << 14 else "sieve"


def choose_ranker(index: store.StoredIndex, strings: DataFrame, have_old: bool) -> str:
    """replicated while the index fits every task, else rounds for short strings, else merge if the old strings are kept."""
    if index.manifest.n * index.codec.dtype().itemsize <= store.MOST_REPLICATED:
        return "replicated"
    longest = strings.agg(F.max("len")).first()[0] or 0
    return "rounds" if longest <= MOST_ROUNDS or not have_old else "merge"


def regime(n: int, m_suffixes: int, page: int) -> dict:
    """Blocks, and whether p > n/M: then bulk insertions touch every page and cost n*n/M, less than p*n*log(n)."""
    k = max(1, -(-n // max(1, m_suffixes)))
    return {"blocks": k, "pages_all_touched": page > k}


def choose(strings: DataFrame, *, memory_bytes: int = 8 << 30, appended: bool = False) -> IndexPlan:
    """A plan for a set: the block takes a fifth of memory at 60 bytes a suffix; a first bulk build is gathered by range,
    as it replicates nothing, while later strings are appended in blocks."""
    n, longest, average = measure(strings)
    m = max(1, memory_bytes // 5 // 60)
    if average > DIRECT_BYTES:  # long strings: blocks that one task sorts, one after the other ranked and inserted
        m = min(m, LOCAL_SUFFIXES // 2)
    sorter = choose_sorter(min(n, m), longest, average)
    return IndexPlan(m, sorter, "auto", "append" if appended or n > m else "bulk")
