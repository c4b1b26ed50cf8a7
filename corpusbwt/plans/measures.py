"""Cost measures: time, throughput, memory, occupancy, work, common prefixes, bounds and models."""

from __future__ import annotations

import math
import resource
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.operators import bwt as rows
from corpusbwt.plans.store import StoredIndex


def timed(run: Callable) -> tuple[object, float]:
    begun = time.perf_counter()
    return run(), time.perf_counter() - begun


def throughput(symbols: int, seconds: float) -> float:
    """Millions of input symbols a second."""
    return symbols / max(seconds, 1e-9) / 1e6


def speedup(seconds: float, baseline: float) -> float:
    return baseline / max(seconds, 1e-9)


def peak_rss() -> int:
    """Peak bytes of this process and of its largest ended child."""
    return 1024 * max(resource.getrusage(w).ru_maxrss for w in (resource.RUSAGE_SELF, resource.RUSAGE_CHILDREN))


def resident_peak(reset: bool = False) -> int:
    """Peak resident bytes of this process since the last reset (0 where the system doesn't tell)."""
    try:
        if reset:
            with open("/proc/self/clear_refs", "w") as file:
                file.write("5")
        with open("/proc/self/status") as file:
            return next(int(line.split()[1]) * 1024 for line in file if line.startswith("VmHWM"))
    except (OSError, StopIteration):
        return 0


def memory_bits(index: StoredIndex) -> DataFrame:
    """``(part, bits, bits_per_symbol, bound, within)`` of payload, counters and both, against 2, 1 and 3 n log2(sigma)."""
    width, n = index.alphabet.sigma + 1, index.manifest.n
    sums = index.pages().agg(F.sum(F.octet_length("payload") * 8).alias("payload"), F.sum(F.octet_length("occ_rel") * 8 + F.lit(64 * width)).alias("counters"))
    unit = n * math.log2(max(2, index.alphabet.sigma))
    parts = sums.select(F.explode(F.array(*(F.struct(F.lit(p).alias("part"), e.cast("long").alias("bits"), F.lit(b * unit).alias("bound")) for p, e, b in (("payload", F.col("payload"), 2), ("counters", F.col("counters"), 1), ("total", F.col("payload") + F.col("counters"), 3))))).alias("x")).select("x.*")
    return parts.select("part", "bits", (F.col("bits") / max(1, n)).alias("bits_per_symbol"), "bound", (F.col("bits") <= F.col("bound")).alias("within"))


def occupancy(index: StoredIndex) -> DataFrame:
    """``(shard_id, pages, least, most, bad)``: page sizes of each shard; bad ones lie outside p/2..p and aren't alone."""
    p = index.manifest.page
    sizes = index.pages().groupBy("shard_id").agg(F.count("*").alias("pages"), F.min("n_sym").alias("least"), F.max("n_sym").alias("most"), F.sum(F.when((F.col("n_sym") > p) | (F.col("n_sym") < p // 2), 1).otherwise(0)).alias("outside"))
    return sizes.select("shard_id", "pages", "least", "most", F.when((F.col("pages") == 1) & (F.col("most") <= p), 0).otherwise(F.col("outside")).cast("long").alias("bad"))


def counter_bits(sigma: int, spacing: int, page: int) -> float:
    """Counter bits for each symbol of full pages: sampled 32-bit ones and 64-bit ones for each page."""
    return 32 * sigma / spacing + 64 * sigma / page


def work(strings: DataFrame) -> DataFrame:
    """``(block_id, strings, steps, before)``: chain steps of each block (its symbols) and symbols indexed before it."""
    from corpusbwt.operators.numbering import running_sum

    per = strings.groupBy("block_id").agg(F.count("*").alias("strings"), F.sum("len").cast("long").alias("steps"), F.sum(F.col("len") + 1).cast("long").alias("_n"))
    return running_sum(per, ["block_id"], "_n", "before").select("block_id", "strings", "steps", "before")


def insertion_work(before: StoredIndex, after: StoredIndex) -> dict:
    """Symbols added, and shards, pages and symbols rewritten, between two versions."""
    old = {(s.shard_id, s.version) for s in before.manifest.shards}
    touched = [s for s in after.manifest.shards if (s.shard_id, s.version) not in old]
    pages = after.pages([s.shard_id for s in touched]).count() if touched else 0
    return {"added": after.manifest.n - before.manifest.n, "shards_touched": len(touched), "pages_rewritten": pages, "symbols_moved": sum(s.n_sym for s in touched)}


def lcp_stats(sa: DataFrame, strings: DataFrame) -> DataFrame:
    """``(suffixes, mean_lcp, max_lcp)`` of neighbours in one suffix order; the source leaves open which of the two it means."""
    return rows.lcp(sa, strings).agg(F.count("*").alias("suffixes"), F.avg("lcp").alias("mean_lcp"), F.max("lcp").alias("max_lcp"))


def regime_table(spark, n: int, page: int, sizes: list[int]) -> DataFrame:
    """``(m_suffixes, blocks, pages_all_touched)`` for block sizes."""
    from corpusbwt.plans.planner import regime

    return spark.createDataFrame([(m, *regime(n, m, page).values()) for m in sizes], "m_suffixes long, blocks long, pages_all_touched boolean")


def cost_model(n: float, m: float, block_lcp: float, lcp: float, block: float) -> dict:
    """Asymptotic work: appending, m l + n log2 n; gathering, m L + n n / M."""
    append, gather = m * block_lcp + n * math.log2(max(2.0, n)), m * lcp + n * n / max(1.0, block)
    return {"append": append, "gather": gather, "ratio": gather / max(1.0, append)}


def pipeline_model(rates: dict[str, float], serial: tuple[str, ...] = ("rank", "insert")) -> dict:
    """Rate of overlapped stages: those that share a processor run one after the other, the slowest share decides."""
    shared = 1 / sum(1 / rates[s] for s in serial)
    alone = {s: r for s, r in rates.items() if s not in serial}
    slowest = min([("+".join(serial), shared), *alone.items()], key=lambda x: x[1])
    return {"rate": slowest[1], "bottleneck": slowest[0], "serial_rate": 1 / sum(1 / r for r in rates.values())}


def shuffle_cost(df: DataFrame) -> dict:
    """Exchanges, sorts and Python stages of a frame's plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {k: plan.count(k) for k in ("Exchange", "Sort", "MapInArrow", "BroadcastExchange")}


def sieve_rounds(unresolved: list[int]) -> np.ndarray:
    """Share of suffixes that a round leaves, from one round to the next."""
    u = np.array(unresolved, float)
    return u[1:] / np.maximum(u[:-1], 1)
