"""Spark builders, ranks, stored pages, searches, streams and sources against brute force on small sets."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusbwt.functions import sqlapi
from corpusbwt.functions.alphabet import Alphabet
from corpusbwt.operators import bwt, fm, joins, numbering, ranking, suffixsort
from corpusbwt.operators.stringset import assign_blocks, string_set
from corpusbwt.plans import builder, measures, planner
from corpusbwt.plans.store import StoredIndex, split_sizes
from corpusbwt.sources import index_source, tables
from corpusbwt.streaming import append as streaming
from tests.test_kernels import definition

TEXTS = ["aba", "ba", "ab", "", "abab", "ab", "über", "b" * 40, None]


@pytest.fixture(scope="module")
def strings(spark):
    return string_set(spark.createDataFrame(list(enumerate(TEXTS)), "id long, t string"), "t", ["id"]).cache()


@pytest.fixture(scope="module")
def wanted():
    return definition([t or "" for t in TEXTS])


def symbols(df):
    got = sorted((r["pos"], r["sym"]) for r in df.collect())
    assert [p for p, _ in got] == list(range(len(got)))
    return [s for _, s in got]


@pytest.mark.parametrize("method", list(suffixsort.SORTERS))
def test_sorters(strings, wanted, method):
    assert symbols(suffixsort.suffix_array(strings, method)) == wanted


def test_packed_words_and_prefix_buckets(strings, wanted):
    assert symbols(suffixsort.sort_msd_sieve(strings, (3,), alphabet=Alphabet.from_strings(strings, "s"))) == wanted
    assert symbols(suffixsort.sort_gather(strings, bucket="prefix")) == wanted


@pytest.mark.parametrize(
    "options",
    [{"blocks": 3}, {"blocks": 3, "order": "reverse"}, {"blocks": 2, "ranker": "rounds", "page": 8, "shard_symbols": 24}, {"blocks": 2, "ranker": "merge"}, {"blocks": 3, "overlap": True, "packing": "bits", "page": 8}],
    ids=str,
)
def test_block_append(spark, strings, wanted, tmp_path, options):
    index = builder.build(strings, str(tmp_path / "index"), **options)
    assert symbols(index.rows()) == wanted
    assert index.manifest.m == len(TEXTS) and index.manifest.n == len(wanted)
    assert measures.occupancy(index).agg(F.sum("bad")).first()[0] == 0
    again = StoredIndex.open(spark, index.path)
    assert again.manifest == index.manifest
    base = dict(zip([s.shard_id for s in index.manifest.shards], index.starts, strict=True))
    for page in index.pages().collect():
        before = index.symbols[base[page.shard_id] :][: page.start_in_shard]
        assert page.occ_in_shard == np.bincount(before, minlength=index.alphabet.sigma + 1).tolist()


def test_append_is_rebuild_and_replay_does_nothing(spark, strings, wanted, tmp_path):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "id long, t string")
    index = builder.build(string_set(df.where("id < 4"), "t", ["id"]), str(tmp_path / "index"), blocks=1, alphabet=Alphabet.from_strings(strings, "s"))
    builder.append(index, df.where("id >= 4 and id < 6"), "t", ["id"], batch_id=0)
    builder.append(index, df.where("id >= 6"), "t", ["id"], batch_id=1)
    builder.append(index, df.where("id >= 6"), "t", ["id"], batch_id=1)
    assert symbols(index.rows()) == wanted
    assert symbols(index.rebalance().rows()) == wanted


def test_shards_split_and_alphabets_grow(spark, tmp_path):
    texts = ["abab" * 3, "ba", "a", "bbbb", "cab", "über", "zz" * 8, "日本 ab", "", "ab" * 20, "c" * 9]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, t string")
    index = StoredIndex.create(spark, str(tmp_path / "index"), Alphabet.fixed("ab"), page=4, shard_symbols=16)
    for i in range(len(texts)):
        builder.append(index, df.where(F.col("id") == i), "t", ["id"], batch_id=i % 2, source=f"s{i // 2}")
    assert symbols(index.rows()) == definition(texts)
    assert len(index.manifest.shards) > 5 and max(s.n_sym for s in index.manifest.shards) <= 20
    assert measures.occupancy(index).agg(F.sum("bad")).first()[0] == 0
    assert index.alphabet.points == tuple(sorted({ord(c) for t in texts for c in t}))
    again = StoredIndex.open(spark, index.path)
    assert again.manifest == index.manifest and symbols(again.rebalance().rows()) == definition(texts)


@pytest.mark.parametrize("fill", [0.5, 0.75, 1.0])
def test_bulk_loads_keep_pages_half_full(fill):
    for p in (7, 4096):
        for n in (1, p // 2, p - 1, p, p + 1, 3 * p // 4 + 1, 2 * p - 1, 10 * p + 3):
            sizes = split_sizes(n, p, fill)
            assert sum(sizes) == n and max(sizes) <= p and (len(sizes) == 1 or min(sizes) >= p / 2)


def test_rank_strategies_agree(spark, strings, tmp_path):
    blocks = assign_blocks(strings, blocks=2).cache()
    old, new = blocks.where("block_id = 0"), blocks.where("block_id = 1")
    index = StoredIndex.create(spark, str(tmp_path / "index"), Alphabet.from_strings(strings, "s"), page=8, shard_symbols=16)
    index.bulk_load(bwt.bwt_once(old), old.count()).commit()
    rows = lambda df: sorted((r.sid, r.k, r.g) for r in df.collect())
    want = rows(ranking.ranks_theta(old, new))
    for strategy in ("replicated", "rounds", "merge"):
        assert rows(ranking.compute_ranks(new, index, strategy, old=old)) == want


@pytest.mark.parametrize("packing", ["bytes", "bits"])
def test_sharded_searches(spark, strings, tmp_path, packing):
    index = StoredIndex.create(spark, str(tmp_path / "index"), Alphabet.from_strings(strings, "s"), page=16, shard_symbols=30, spacing=4, packing=packing)
    index.bulk_load(bwt.bwt_once(strings), len(TEXTS)).commit()
    assert len(index.manifest.shards) > 2
    index.__dict__["symbols"] = None  # nothing may replicate it
    patterns = ["ab", "b", "ba", "bbbb", "zz", "über", "", None, "xab"]
    given = spark.createDataFrame(list(enumerate(patterns)), "pid long, pattern string")
    texts = [t or "" for t in TEXTS]
    places = lambda p: [(j, k) for j, t in enumerate(texts) for k in range(len(t) + 1) if t.startswith(p, k) and k + len(p) <= len(t)]
    assert {r.pid: r.n for r in fm.count(index, given, strategy="sharded").collect()} == {i: len(places(p or "")) for i, p in enumerate(patterns)}
    hits = sorted((r.pid, r.sid, r.k) for r in fm.locate(index, given, strategy="sharded").collect())
    assert hits == sorted((i, *x) for i, p in enumerate(patterns) for x in places(p or ""))
    if packing == "bytes":
        assert {(r.pid, r.sid) for r in fm.documents_with(index, given, strategy="sharded").collect()} == {h[:2] for h in hits}
        assert sorted(r.pid for r in fm.absent(index, given, strategy="sharded").collect()) == [4, 8]
        assert {r.sid: r.s for r in fm.invert(index, strategy="sharded").collect()} == dict(enumerate(texts))


def test_searches(spark, strings, tmp_path):
    index = builder.build(strings, str(tmp_path / "index"), blocks=2)
    patterns = ["ab", "b", "ba", "bbbb", "zz", "über", "", "aba"]
    given = spark.createDataFrame(list(enumerate(patterns)), "pid long, pattern string")
    texts = [t or "" for t in TEXTS]
    places = lambda p: [(j, k) for j, t in enumerate(texts) for k in range(len(t) + 1) if t.startswith(p, k) and k + len(p) <= len(t)]
    assert {r.pid: r.n for r in fm.count(index, given).collect()} == {i: len(places(p)) for i, p in enumerate(patterns)}
    for rate in (1, 4):
        hits = sorted((r.pid, r.sid, r.k) for r in fm.locate(index, given, rate=rate).collect())
        assert hits == sorted((i, *x) for i, p in enumerate(patterns) for x in places(p))
    assert [r.pattern for r in fm.absent(index, given).collect()] == ["zz"]
    assert {r.sid: r.s for r in fm.invert(index).collect()} == dict(enumerate(texts))
    assert {r.sid: r.s for r in bwt.invert_rows(index.rows()).collect()} == dict(enumerate(texts))
    found = fm.shared(index, spark.createDataFrame([(0, "xxabab!ba")], "pid long, pattern string"), 2).collect()
    assert sorted((r.start, r.len, r.n) for r in found) == [(2, 4, 1), (7, 2, len(places("ba")))]
    sqlapi.register(spark, index)
    given.createOrReplaceTempView("patterns")
    assert [r[0] for r in spark.sql("SELECT bwt_count(pattern) FROM patterns ORDER BY pid").collect()][:3] == [len(places(p)) for p in patterns[:3]]
    assert spark.sql("SELECT bwt_rank('a', 5)").first()[0] == sum(s == 97 for s in symbols(index.rows())[:5])
    assert [r.s for r in spark.sql("SELECT s FROM read_windows('abcde', 2) ORDER BY window").collect()] == ["ab", "cd", "e"]
    index_source.register(spark)
    read = spark.read.format("corpusbwt").load(index.path)
    assert symbols(read) == symbols(index.rows())
    assert read.where("pos < 3").count() == 3


def test_lcp_and_runs(strings, wanted):
    sa = suffixsort.sort_direct(strings)
    texts = sorted((t or "")[k:] for t in TEXTS for k in range(len(t or "") + 1))
    common = lambda a, b: next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
    assert [r.lcp for r in bwt.lcp(sa, strings).orderBy("pos").collect()] == [0] + [common(a, b) for a, b in zip(texts, texts[1:], strict=False)]
    runs = bwt.runs(sa.select("pos", "sym")).orderBy("run").collect()
    assert [s for r in runs for s in [r.sym] * r.len] == wanted


def test_memory_bound_needs_spacing_that_grows_with_the_alphabet(spark, tmp_path):
    text = "".join(chr(200 + i * 37 % 101) for i in range(60_000))
    df = string_set(spark.createDataFrame([(0, text)], "id long, t string"), "t", ["id"])
    within = {}
    for spacing in (0, 128):
        index = builder.build(df, str(tmp_path / f"index{spacing}"), blocks=1, spacing=spacing, packing="bits")
        within[spacing] = {r.part: r.within for r in measures.memory_bits(index).collect()}
    assert within[0] == {"payload": True, "counters": True, "total": True}
    assert not within[128]["counters"] and not within[128]["total"]


def test_numbering_and_joins(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("x"))
    assert [r.pos for r in numbering.with_row_index(df, ["x"]).orderBy("x").collect()] == list(range(1000))
    sums = numbering.running_sum(df, ["x"], "x", "s").orderBy("x").collect()
    assert [r.s for r in sums] == [x * (x - 1) // 2 for x in range(1000)]
    assert numbering.with_row_index(df.where("x < 0"), ["x"]).count() == 0
    right = spark.createDataFrame([(i * 100, f"r{i}") for i in range(1, 9)], "x long, name string")
    got = {r.x: r.found and r.found["name"] for r in joins.as_of(df, right, "x").collect()}
    assert got[99] is None and got[100] == "r1" and got[999] == "r8" and got[455] == "r4"
    ranges = spark.createDataFrame([(0, 10), (10, 500), (700, 701)], "lo long, hi long")
    assert joins.in_range(df, ranges, "x", "lo", "hi", cell=64).count() == 501
    plan = numbering.with_row_index(df, ["x"])._jdf.queryExecution().toString()
    assert "SinglePartition" not in plan


def test_plans_and_models(strings):
    assert planner.choose_sorter(1000, 101, 51) == "direct" and planner.choose_sorter(1000, 10**5, 10**4) == "local"
    assert planner.choose_sorter(10**9, 10**5, 10**4) == "doubling"
    rates = {"sort": 77.0, "rank": 37.0, "insert": 44.0}
    model = measures.pipeline_model(rates)
    assert round(model["rate"], 1) == 20.1 and model["bottleneck"] == "rank+insert"
    assert round(measures.counter_bits(4, 128, 1 << 16), 2) == 1.0
    assert planner.regime(1000, 100, 4096) == {"blocks": 10, "pages_all_touched": True}
    assert [r.steps for r in measures.work(assign_blocks(strings, blocks=1)).collect()] == [sum(len(t or "") for t in TEXTS)]


def test_stream_appends_each_batch_once(spark, strings, wanted, tmp_path):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "id long, t string")
    for i, cond in enumerate(("id < 5", "id >= 5")):
        df.where(cond).coalesce(1).write.parquet(str(tmp_path / "in" / f"{i}"))
    StoredIndex.create(spark, str(tmp_path / "index"), Alphabet.from_strings(strings, "s"))
    for part in ("0", "1"):
        stream = spark.readStream.schema(df.schema).parquet(str(tmp_path / "in" / part))
        streaming.append_stream(stream, str(tmp_path / "index"), str(tmp_path / f"state{part}"), text_col="t", order_cols=["id"]).awaitTermination()
    assert symbols(StoredIndex.open(spark, str(tmp_path / "index")).rows()) == wanted  # both streams count from 0


def test_event_windows(spark):
    at = dt.datetime(2024, 1, 1)
    events = spark.createDataFrame([(at + dt.timedelta(minutes=m), "a") for m in (0, 5, 30, 61)], "ts timestamp, event_type string")
    count = lambda kind: sorted(r.n for r in streaming.symbol_windows(events, kind).collect())
    assert count("tumbling") == [1, 3] and count("session") == [1, 1, 2] and sum(count("sliding")) == 16


def test_sources(spark, tmp_path):
    (tmp_path / "r.fa").write_text(">one x\nACGT\nAC\n>two\nGG\n")
    (tmp_path / "r.fq").write_text("@r1\nACGT\n+\nIIII\n@r2\nTT\n+\n@I\n")
    assert [(r.name, r.s) for r in tables.read_sequences(spark, str(tmp_path / "r.fa")).collect()] == [("one x", "ACGTAC"), ("two", "GG")]
    assert [(r.name, r.s) for r in tables.read_sequences(spark, str(tmp_path / "r.fq"), "fastq").collect()] == [("r1", "ACGT"), ("r2", "TT")]
    df = spark.createDataFrame([(0, "Hello, wörld"), (1, ""), (2, None)], "id long, t string")
    assert [r.s for r in tables.read_windows(df, ["id"], "t", 5).orderBy("id", "window").collect()] == ["Hello", ", wör", "ld", ""]
    runs = spark.createDataFrame([("a", "x", 3), ("a", "y", 1), ("b", "x", 2)], "lang string, source string, len long")
    assert {m: tables.runs_summary(runs, ["lang", "source"], m).count() for m in ("rollup", "cube", "sets")} == {"rollup": 6, "cube": 8, "sets": 5}
