"""The experiment workloads w01 to w20: outputs as frames, and measures of each with its parameters.

Workloads that compare whole methods run queries of the catalogue; those that sweep a parameter run the array builder on the
same reads, so nothing but the parameter changes.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusbwt.baselines import builders
from corpusbwt.functions import kernels
from corpusbwt.operators import suffixsort
from corpusbwt.plans import builder, catalog, measures
from corpusbwt.session import ship, written

MEASURES = "workload string, builder string, dataset string, param string, symbols long, seconds double, rate double, bytes long"


@dataclass
class WorkloadResult:
    outputs: dict[str, DataFrame]
    measures: DataFrame


#: Workloads by the queries whose results and times they compare.
COMPARED = {
    "w01": ("bwt_short_reads",),
    "w02": ("bwt_long_reads",),
    "w03": ("bwt_whole_documents", "pages_html_bwt", "conversations_append"),
    "w04": ("bwt_dna", "bwt_dna_two_symbol_steps"),
    "w06": ("stage_breakdown", "array_stage_breakdown"),
    "w07": ("bwt_incremental_append", "conversations_append", "part_names_ties"),
    "w11": ("sieve_survival",),
    "w14": ("memory_bits",),
    "w15": ("bwt_incremental_append", "bwt_scan_insert", "bwt_tree_insert"),
    "w16": ("bwt_block_append", "bwt_gather"),
    "w17": ("fm_count_benchmark", "fm_locate_benchmark", "fm_documents_with", "fm_absent_patterns", "fm_shared_passages"),
    "w18": ("bwt_runs", "runs_by_lang_source"),
    "w19": ("part_names_ties", "customer_names_high_lcp", "duplicates_by_order"),
    "w20": ("order_flag_strings", "event_type_strings"),
}


#: Array builders of one task: the block-append builder and what it is compared with.
ARRAY_BUILDERS = {
    "block_append": builders.block_append,
    "column_wise_memory": builders.column_wise,
    "column_wise_disk": lambda c, b: builders.column_wise(c, b, "disk"),
    "old_in_new": builders.backward_single,
    "brute": builders.brute,
}
#: Builders that insert string by string: their time grows too fast for anything but the shorter texts.
SERIAL_BUILDERS = {"tree": builders.tree_insert}


def measured_builder(strings: DataFrame, name: str) -> DataFrame:
    """``(builder, symbols, seconds, bytes)``: an array builder's time and peak resident memory, taken in its own task."""
    ship(strings.sparkSession)
    function = (ARRAY_BUILDERS | SERIAL_BUILDERS)[name]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            points, bounds = kernels.flat_codes(pa.Table.from_batches(held).sort_by("sid").column("s").to_pylist())
            codes = np.unique(points, return_inverse=True)[1] + 1
            measures.resident_peak(reset=True)
            _, seconds = _timed(lambda: function(codes, bounds))
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (name, len(codes), seconds, measures.resident_peak())], ["builder", "symbols", "seconds", "bytes"])

    return strings.select("sid", "s").coalesce(1).mapInArrow(run, "builder string, symbols long, seconds double, bytes long")


def builder_table(spark: SparkSession, sf_dir: str) -> list[tuple]:
    """Time, rate and memory of all builders on short and on long reads; sorters and the stored builder run in Spark."""
    rows = []
    for width in (catalog.SHORT, catalog.LONG):
        reads = written(catalog.reads(spark, sf_dir, width))
        n = reads.agg(F.sum("len")).first()[0] or 0
        spread = {
            "block_append_stored": lambda r=reads: builder.build(r, catalog.folder(spark), blocks=4, sorter="local", shard_symbols=catalog.SHARD).rows(),
            "gather": lambda r=reads: suffixsort.sort_gather(r),
            "one_sort": lambda r=reads: suffixsort.sort_direct(r),
        }
        for name, make in spread.items():
            _, s = _timed(lambda make=make: make().write.format("noop").mode("overwrite").save())
            rows.append((f"width={width}", name, n, s, 0))
        for name in ARRAY_BUILDERS:
            rows += [(f"width={width}", r.builder, r.symbols, r.seconds, r.bytes) for r in measured_builder(reads, name).collect()]
    short = written(catalog.names(spark, sf_dir))
    for name in (*SERIAL_BUILDERS, "block_append"):
        rows += [("part names", r.builder, r.symbols, r.seconds, r.bytes) for r in measured_builder(short, name).collect()]
    return rows


def overlap_table(spark: SparkSession, sf_dir: str) -> list[tuple]:
    """The same build with blocks sorted ahead and without, nothing else changed."""
    reads = written(catalog.reads(spark, sf_dir))
    n = reads.agg(F.sum("len")).first()[0] or 0
    rows = []
    for overlap in (False, True):
        _, s = _timed(lambda o=overlap: builder.build(reads, catalog.folder(spark), blocks=4, sorter="local", overlap=o, shard_symbols=catalog.SHARD))
        rows.append((f"overlap={overlap}", "block_append_stored", n, s, 0))
    return rows


def _texts(spark: SparkSession, sf_dir: str, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Dense codes and bounds of the reads of one width, for the one-task array builder."""
    table = catalog.reads(spark, sf_dir, width).select("sid", "s").toArrow().sort_by("sid")
    points, bounds = kernels.flat_codes(table.column("s").to_pylist())
    return np.unique(points, return_inverse=True)[1] + 1, bounds


def _timed(run: Callable) -> tuple[object, float]:
    begun = time.perf_counter()
    return run(), time.perf_counter() - begun


def _sweep(name: str, spark: SparkSession, sf_dir: str) -> list[tuple]:
    """Rows of measures of one parameter's sweep."""
    rows = []
    if name == "w12":
        for width in (32, 101, 250, 875, 1 << 30):  # all symbols of the documents at every length, whole texts last
            codes, bounds = _texts(spark, sf_dir, width)
            made, s = _timed(lambda c=codes, b=bounds: builders.block_append(c, b, 4))
            rows.append((f"len={width}" if width < 1 << 30 else "whole", len(codes), s, made.nbytes))
        return rows
    codes, bounds = _texts(spark, sf_dir, catalog.SHORT)
    sigma = int(codes.max(initial=1))
    made = builders.brute(codes, bounds).astype(np.uint8)
    if name == "w08":
        for k in (1, 2, 4, 8, 16):
            log: list = []
            _, s = _timed(lambda k=k, log=log: builders.block_append(codes, bounds, k, log=log))
            rows.append((f"M=n/{k}", len(made), s, made.nbytes))
            rows += [(f"M=n/{k} block={i} stage={stage}", x[0], x[2 + j], x[1]) for i, x in enumerate(log) for j, stage in enumerate(("sort", "rank", "insert"))]
    elif name == "w09":
        from corpusbwt.plans.store import split_page

        rng = np.random.default_rng(0)
        at = np.sort(rng.integers(0, len(made), len(made) // 16))
        new = rng.integers(1, sigma + 1, len(at))
        for p in (1 << 12, 1 << 14, 1 << 16, 1 << 18, 1 << 20):
            pages = split_page(made, p)
            starts = np.cumsum([0, *map(len, pages)])

            def edit(pages=pages, starts=starts, p=p):
                cuts = np.searchsorted(at, starts)
                return [x for i, page in enumerate(pages) for x in split_page(kernels.insert_symbols(page, at[cuts[i] : cuts[i + 1]] - starts[i], new[cuts[i] : cuts[i + 1]]), p)]

            out, s = _timed(edit)
            rows.append((f"p={p} pages={len(out)}", len(at), s, sum(x.nbytes for x in out)))
    else:  # w10
        rng = np.random.default_rng(0)
        asked = rng.integers(1, sigma + 1, 200_000), rng.integers(0, len(made), 200_000)
        for spacing in (64, 128, 256, 512, 1024):
            engine = kernels.RankEngine(made, sigma, spacing)
            _, s = _timed(lambda e=engine: e.rank(*asked))
            rows.append((f"spacing={spacing} bits={measures.counter_bits(sigma, spacing, 1 << 16):.2f}", len(asked[0]), s, engine.counters.nbytes))
    return rows


def run(name: str, spark: SparkSession, sf_dir: str) -> WorkloadResult:
    """A workload by name, ``w01`` to ``w20``. ``symbols`` are a sweep's input symbols, or a compared query's rows."""
    rows, outputs = [], {}
    if name in COMPARED:
        for query in COMPARED[name]:
            frame, s = _timed(lambda q=query: catalog.QUERIES[q](spark, sf_dir).cache())
            n, counted = _timed(frame.count)
            outputs[query] = frame
            rows.append((name, query, sf_dir, "", n, s + counted, n / max(s + counted, 1e-9), None))
    elif name in TABLES:
        rows = [(name, what, sf_dir, p, n, s, n / max(s, 1e-9), size or None) for p, what, n, s, size in TABLES[name](spark, sf_dir)]
    else:
        rows = [(name, "block_append", sf_dir, p, n, s, n / max(s, 1e-9), size) for p, n, s, size in _sweep(name, spark, sf_dir)]
    return WorkloadResult(outputs, spark.createDataFrame(rows, MEASURES))


TABLES = {"w05": builder_table, "w13": overlap_table}
NAMES = tuple(sorted({*COMPARED, *TABLES, "w08", "w09", "w10", "w12"}))


def _measured(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return run(name, spark, sf_dir).measures

    query.__name__, query.__doc__ = name, f"Measures of workload {name}."
    return query


#: The workloads as queries that return their measures.
QUERIES = {name: _measured(name) for name in NAMES}
