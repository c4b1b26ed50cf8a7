"""Operators on Spark: nulls in any column, empty and long texts, repeated rows, empty tables, clashing columns, brute force."""

import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as vocab
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from corpusbwt.llm import byte_bpe, graph, licenses, line_dedup, media, near_dedup, packing, quality, registry, token_counts, url_filter, vector_graph

LONG = "alpha beta gamma delta epsilon zeta eta theta. " * 4000
TEXTS = ["one two three four five six seven", "one two three four five six seven", None, "", " \n ", LONG, LONG + "tail", "short text", "<|endoftext|> it's", "ünï 日本\x00"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, tokens string, row string, id long, key string"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", f"s{i % 3}", len(t or ""), 0.5, "x", "y", 9, None) for i, t in enumerate(TEXTS)]
    rows += [rows[0], (None, "no id here at all", None, None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


OPERATORS = {
    "round trip": byte_bpe.round_trip,
    "counts": token_counts.token_counts,
    "media": media.media_columns,
    "near duplicates": near_dedup.near_duplicates,
    "lines": line_dedup.line_report,
    "quality": lambda d: quality.scored(d, quality.Machine(0.0, np.zeros(quality.n_cells(1)), np.zeros((quality.n_cells(1), 2)))),
    "licences": lambda d: licenses.scan(d.withColumn("path", F.concat(F.lit("/a/"), "doc_id"))),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_one_row_for_each_row(docs, nothing, name):
    got = OPERATORS[name](docs).collect()
    assert sorted(str(r["doc_id"]) for r in got) == sorted(str(r["doc_id"]) for r in docs.collect())
    assert OPERATORS[name](nothing).collect() == []


def test_packing_places_every_id_once(docs, nothing):
    library = Tokenizer.from_file(vocab.path("byte_bpe_50k.json"))
    rows = packing.pack(docs, limit=64, with_ids=True).collect()
    want = {r.doc_id: [*library.encode(r.text or "", add_special_tokens=False).ids, 1] for r in docs.collect() if r.doc_id is not None}
    for key, ids in want.items():
        own = sorted({(r.start, r.length, r.ids_crc32, bytes(r.ids)) for r in rows if r.doc_id == key})
        whole = np.array(ids, "<u4")
        covered = set()
        for start, length, crc, raw in own:
            assert whole[start : start + length].tobytes() == raw and zlib.crc32(raw) == crc
            covered |= set(range(start, start + length))
        assert covered == set(range(len(ids)))
    fill: dict = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == fill.get(r.sequence_id, 0)
        fill[r.sequence_id] = r.offset + r.length
    assert all(n <= 64 and n & (n - 1) == 0 for n in fill.values())
    assert packing.pack(nothing).collect() == []


def brute_components(rows):
    lower = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
    sets = {}
    for key, text in rows:
        words = re.findall("[^\x20\x09-\x0d]+", (text or "").translate(lower))
        sets[key] = {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()
    name = {k: k for k in sets}

    def find(x):
        while name[x] != x:
            x = name[x]
        return x

    keys = sorted(sets)
    for i, a in enumerate(keys):
        for b in keys[:i]:
            common = len(sets[a] & sets[b])
            if common and 100 * common >= 75 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                name[max(x, y)] = min(x, y)
    return {k: (len(sets[k]), find(k)) for k in keys}


@pytest.mark.parametrize("block", [near_dedup.BLOCK, 4])
def test_near_duplicates_are_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(near_dedup, "BLOCK", block)
    rng = np.random.default_rng(8)
    words = [f"w{i}" for i in range(400)]
    rows = []
    for g in range(12):  # chains: each text changes a few words of the one before, so ends needn't be similar
        text = list(rng.choice(words, 90))
        for _ in range(9):
            rows.append(" ".join(text))
            for at in rng.integers(0, 90, 2):
                text[at] = str(rng.choice(words))
    passage = " ".join(rng.choice(words, 55))  # shared by many texts that are no duplicates
    rows += [" ".join(rng.choice(words, 30)) + " " + passage for _ in range(60)]
    base = list(rng.choice(words, 100))
    for g in range(3):  # a text too far from the next ones, which are near one another: no star round its bucket's first
        text = [*base[: 100 - 8 * g], *rng.choice(words, 8 * g)]
        for _ in range(12):
            rows.append(" ".join([*text[:95], *rng.choice(words, 5)]))
    rows += ["", "one", "one", "One", "a b c d", None, *rows[:5]]
    given = [(int(i) * 3, t) for i, t in zip(rng.permutation(len(rows)), rows, strict=True)]
    got = near_dedup.near_duplicates(spark.createDataFrame(given, "doc_id long, text string").repartition(4)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute_components(given)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(100, 160)] + [(5, i) for i in range(6, 40)] + [(200, 200), (39, 38)]
    got = {r.node: r.component for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 100 for i in range(100, 161)}, **{i: 5 for i in range(5, 40)}}


def test_lines_on_many_sites_stay_once(spark):
    rows = [(i, f"Unique {i}\n  Site NOTICE \n\nBody {i % 15}", f"s{i}") for i in range(40)] + [(99, "site notice", "s1"), (98, None, None)]
    got = {r.doc_id: r for r in line_dedup.line_report(spark.createDataFrame(rows, "doc_id long, text string, source string"), min_sites=16).collect()}
    assert got[0].text == rows[0][1] and got[0].n_removed == 0
    assert got[7].text == "Unique 7\n\nBody 7" and got[7].n_removed == 1 and got[99].text == "" and got[98].text is None
    kept = line_dedup.without_boilerplate(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert 99 not in {r.doc_id for r in kept} and 98 in {r.doc_id for r in kept} and len(kept) == 41
    plan = line_dedup.line_report(spark.createDataFrame(rows, "doc_id long, text string, source string"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_counts_near_the_threshold_are_exact(spark):
    rows = [(n * 1000 + i, f"line {n}", f"s{i}") for n in range(10, 22) for i in range(n)]
    lines = line_dedup._lines(spark.createDataFrame(rows, "doc_id long, text string, source string"), "doc_id", "text", "source")
    assert line_dedup.boilerplate(lines, 16).count() == 6


def test_long_passages_on_a_few_sites_go(spark):
    passage, copied = " ".join(f"word{i}" for i in range(60)), " ".join(f"copy{i}" for i in range(60))
    rows = [(i, f"Own {i}\n{passage}\nlocal", f"s{i}") for i in range(5)] + [(10 + i, f"Own {10 + i}\n{copied}", f"s{i}") for i in range(4)] + [(20 + i, f"Own {20 + i}\nlocal notice", "s0") for i in range(9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    got = {r.doc_id: r.text for r in corpus_pipeline.cut_lines(spark, docs, "").collect()}
    assert got == {i: t if i in (0, *range(10, 29)) else f"Own {i}" for i, t, _ in rows}


def test_quality_learns_and_holds_out(spark):
    rng = np.random.default_rng(9)
    good = [" ".join(rng.choice(["river", "stone", "quiet", "morning", "walked", "along"], 60)) + "." for _ in range(300)]
    bad = [" ".join(rng.choice(["BUY!!", "NOW!!", "$$$", "click|", "win%%"], 60)) for _ in range(100)]
    rows = [(i, t, len(t)) for i, t in enumerate(good + bad)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_chars long")
    labels = spark.createDataFrame([(i, int(i < 300)) for i in range(400)] + [(None, 1), (5, None)], "doc_id long, quality int")
    got = quality.scored(docs, quality.train(docs, labels)).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    held = [r for r in got if r.held_out]
    assert sum(r.predicted == (r.doc_id < 300) for r in held) >= 0.95 * len(held)
    assert all((r.score >= 0.3) == bool(r.predicted) for r in got)
    assert quality.accepted(docs, quality.train(docs, labels.limit(0))).columns == docs.columns


def test_url_parts_rules_and_verdicts(spark):
    urls = ["http://A.Net/x?q#f", "https://example.net/en/1", "x://sub.example.com/de/", "nourl", None, "http://b.org/fr/", "http://net", "a://b://c/d", "http://spam.example.org/en/1?u=://z", "http://org/fr/x#y"]
    rows = [(i, u, "<p>free spam bets</p>") for i, u in enumerate(urls)] + [(None, None, None)]
    got = {r.page_id: r for r in url_filter.judged(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert [(got[i].host, got[i].path, got[i].rule) for i in range(len(urls))] == [
        ("a.net", "/x", "net/"),
        ("example.net", "/en/1", "example.net/en/"),
        ("sub.example.com", "/de/", "example.com/de/"),
        ("", "", None),
        ("", "", None),
        ("b.org", "/fr/", "org/fr/"),
        ("net", "", None),
        ("b:", "//c/d", None),
        ("spam.example.org", "/en/1", None),
        ("org", "/fr/x", "org/fr/"),
    ]
    assert got[0].verdict == "block" and got[1].verdict == "allow" and got[8].verdict == "block" and len(got) == len(rows)


def test_odd_pages(spark):
    clashing = "page_id long, url string, html string, host string, n long, word string, name string, own string, odds string, held string"
    extra = ("h", 1, "w", "n", "o", "d", "x")
    assert url_filter.judged(spark.createDataFrame([], clashing)).count() == 0
    long = "https://" + "verylongname" * 500 + ".org/" + "path/" * 5000
    rows = [(1, "https://casino.org/x", None), (1, "https://casino.org/x", None), (2, long, "<b>very long name path</b>"), (None, "", ""), (3, "://", "text")]
    got = url_filter.judged(spark.createDataFrame([(*r, *extra) for r in rows], clashing)).collect()
    assert sorted((r.page_id or 0, len(r.host)) for r in got) == [(0, 0), (1, 10), (1, 10), (2, 6004), (3, 0)]
    assert {r.page_id: r.verdict for r in got if r.page_id in (1, 2)} == {1: "block", 2: "allow"}


def test_every_word_of_the_pages_counts(spark):
    common = " ".join("q" + "".join(chr(97 + i // 26**k % 26) for k in range(4)) for i in range(50_001))
    rows = [(0, "http://adultery.org/x", common), (1, "http://adulterynews.org/y", common), (2, "http://casino.org/x", "adultery news"), (3, None, None)] + [(10 + i, "http://news.org/x", None) for i in range(5)]
    got = {r.page_id: r for r in url_filter.judged(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert [got[i].verdict for i in (0, 1, 2, 10)] == ["allow", "allow", "block", "allow"] and len(got) == len(rows)
    counts, total, raised = url_filter.unigrams(spark.createDataFrame(rows, "page_id long, url string, html string"))
    assert counts.count() == 50_003 and total == 100_004 + sum(raised.values())
    names = spark.createDataFrame([("adulterynews",), ("qaaaaqbaaa",), ("zzz",)], "name string")
    assert {r.name: r.words for r in url_filter.segmented(names, counts, total, raised).collect()} == {"adulterynews": ["adultery", "news"], "qaaaaqbaaa": ["qaaaa", "qbaaa"], "zzz": ["zzz"]}


def test_licences_come_down_from_the_nearest_directory(spark):
    rows = [(0, "/a/LICENSE", "Released under the MIT License."), (1, "/a/b/c/x", "code"), (2, "/a/b/LICENSE", "Licensed under the Apache License, Version 2.0."), (3, "/a/y", "code\nAll rights reserved.\nmore and more and more and more words"), (4, "/z", "code"), (5, None, None), (6, "/a/w", "")]
    got = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, path string, text string")).collect()}
    assert {i: r.effective for i, r in got.items()} == {0: "MIT", 1: "Apache-2.0", 2: "Apache-2.0", 3: "proprietary", 4: None, 5: None, 6: "MIT"}
    assert got[1].inherited_from == "/a/b/" and got[3].inherited_from is None


def test_nearest_with_odd_vectors(spark):
    rng = np.random.default_rng(10)
    rows = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(60)]
    rows += [(100, rows[20][1]), (140, rows[20][1]), (160, None), (180, [0.0] * 8), (200, [float("nan")] + [1.0] * 7), (220, [None] + [1.0] * 7), (240, [1.0] * 3), (None, [1.0] * 8), rows[0]]
    got = vector_graph.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3), every=20).collect()
    use = {i: np.array(v) for i, v in rows if i is not None and v and len(v) == 8 and None not in v and np.isfinite(v).all() and any(v)}
    for q in (0, 20, 40, 100, 140):
        want = sorted((-float(use[q] @ v), i) for i, v in use.items() if i != q)[:20]
        own = sorted((r.rank, r.vec_id, r.score) for r in got if r.query_id == q)
        assert [i for _, i, _ in own] == [i for _, i in want] and [r for r, _, _ in own] == list(range(1, 21))
    assert {r.query_id for r in got} == {0, 20, 40, 100, 140}
    assert vector_graph.nearest(spark.createDataFrame([], "vec_id long, embedding array<float>")).collect() == []


def test_encode_then_decode(docs):
    ids = byte_bpe.encode(docs.where("doc_id is not null"))
    got = {r.doc_id: bytes(r.decoded) for r in byte_bpe.decode(ids).collect()}
    assert got == {i: (t or "").encode() for i, t in enumerate(TEXTS)}


def test_pipeline_stages(spark, small):
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality", "line_dedup", "near_dedup", "packing"]
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    for _, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = stage(spark, docs, small).cache()
        assert docs.columns == columns and {r.doc_id for r in docs.collect()} <= set(before)
    kept = sorted((r.doc_id, r.text) for r in docs.collect())
    assert {k for k, (_, c) in brute_components(kept).items() if k == c} == {k for k, _ in kept}
    assert set(registry.SQL) <= set(registry.QUERIES) and len(registry.QUERIES) == 10


def exact_components(rows, least=75):
    """As ``brute_components``, by an inverted index over the rarest shingles of each set, for tables of many rows."""
    lower = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
    name, classes, sizes = {}, {}, {}

    def find(x):
        while name[x] != x:
            x = name[x]
        return x

    def join(a, b):
        a, b = find(a), find(b)
        name[max(a, b)] = min(a, b)

    for key, text in rows:
        name[key] = key
        words = re.findall("[^\x20\x09-\x0d]+", (text or "").translate(lower))
        own = frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset()
        sizes[key] = len(own)
        if own and classes.setdefault(own, key) != key:
            join(key, classes[own])
    often = Counter(x for own in classes for x in own)
    filed = defaultdict(list)
    for own, key in sorted(classes.items(), key=lambda c: len(c[0])):
        rare = sorted(own, key=lambda x: (often[x], x))[: len(own) + 1 - -(-least * len(own) // 100)]
        for other, b in {id(c[0]): c for x in rare for c in filed[x]}.values():
            common = len(own & other)
            if 100 * common >= least * (len(own) + len(other) - common):
                join(key, b)
        for x in rare:
            filed[x].append((own, key))
    return {k: (sizes[k], find(k)) for k in name}


def test_near_duplicates_of_ten_thousand_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs).collect()}
    assert len(got) == 10_000 and got == exact_components([tuple(r) for r in docs.collect()])


@pytest.mark.parametrize("stage", range(4))
def test_pipeline_stages_take_odd_tables(docs, nothing, small, stage):
    name, function = corpus_pipeline.STAGES[stage]
    given = docs.withColumns({"doc": F.lit("x"), "hash": F.lit(1), "rep": F.lit(2), "digest": F.lit("y"), "lines": F.lit(3)})
    got = function(given.sparkSession, given, small)
    assert function(given.sparkSession, nothing, small).collect() == []
    rows = got.collect()
    if stage < 3:
        assert got.columns == given.columns
    if name == "near_dedup":
        ids = [r.doc_id for r in rows]
        assert ids.count(0) == 2 and 1 not in ids and {2, 3, 4, 7, 8, 9} <= set(ids) and ids.count(None) == 2
    if name == "line_dedup":
        assert sum(r.doc_id is None for r in rows) == 2 and {2, 3} <= {r.doc_id for r in rows}
    if name == "packing":
        assert {r.doc_id for r in rows} == {r.doc_id for r in given.collect()}
