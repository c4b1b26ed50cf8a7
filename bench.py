"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: The block-append builder, the baselines it is compared with, one-sort builds, and searches.
BUILDERS = ("bwt_block_append", "bwt_block_append_long", "bwt_block_append_array", "bwt_brute_array", "bwt_column_wise", "bwt_backward_old_in_new", "bwt_short_reads", "bwt_gather")
#: ``documents_index`` builds one index of whole documents; the searches after it share blocks that the first of them indexes.
HEADLINE = (*BUILDERS, "c_table", "documents_index", "fm_count_benchmark", "fm_documents_with", "invert_roundtrip")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.driver.memory", "16g")
        .config("spark.sql.shuffle.partitions", str(4 * int(CPUS)))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from corpusbwt.plans.catalog import QUERIES, documents_index

    symbols = spark.read.parquet(f"{SF_DIR}/documents.parquet").agg(F.sum(F.length("text"))).first()[0]
    wanted = os.environ.get("BENCH_QUERIES")
    seconds = {}
    for name in wanted.split(",") if wanted else HEADLINE:
        begun = time.perf_counter()
        if name == "documents_index":
            documents_index(spark, SF_DIR)
        else:
            QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - begun, 3)
        print(name, seconds[name], file=sys.stderr, flush=True)
    rates = {n: round(symbols / seconds[n] / 1e6, 3) for n in (*BUILDERS, "documents_index") if n in seconds}
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "throughput": rates, "symbols": symbols, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()
