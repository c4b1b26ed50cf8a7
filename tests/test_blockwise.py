"""Searches over blocks indexed side by side, against the definition and without any index that is built in turns."""

import pytest

from corpusbwt.operators import blockwise
from corpusbwt.plans import builder, catalog

TEXTS = ["abracadabra", "", None, "bra" * 50, "über\U0001f600x", "abracadabra", "\0a\0", "a" * 100, "".join(chr(0x4E00 + i % 700) for i in range(900)), "cadab", "bra" * 11]
PATTERNS = ["a", "bra", "abra", "zz", "", "ü", "\U0001f600x", "brabra", "\0", "a" * 60, None, "xx", "丁七丂", "xbrabrabracadaby", "a" * 101]


def places(text, pattern):
    return [k for k in range(len(text) + 1) if text.startswith(pattern, k)]


@pytest.fixture(params=[40, 1 << 20])
def blocks(spark, monkeypatch, request):
    monkeypatch.setattr(blockwise, "BLOCK", request.param)
    monkeypatch.setattr(blockwise, "MOST_PATTERNS", 70)
    out = blockwise.block_index(spark.createDataFrame([(100 + i, t) for i, t in enumerate(TEXTS)], "id long, t string").coalesce(1), "id", "t")
    assert (out.count() > 5) == (request.param == 40)
    return out


@pytest.fixture
def asked(spark):
    return spark.createDataFrame(list(enumerate(PATTERNS)), "pid long, pattern string")


def test_count(blocks, asked):
    assert {r.pid: r.n for r in blockwise.count(blocks, asked).collect()} == {i: sum(len(places(t or "", p or "")) for t in TEXTS) for i, p in enumerate(PATTERNS)}


@pytest.mark.parametrize("least", [1, 3])
def test_shared(blocks, asked, least):
    texts, want = [t or "" for t in TEXTS], []
    for i, p in enumerate(PATTERNS):
        p = p or ""
        start = [min(a for a in range(e + 1) if a == e or any(p[a:e] in t for t in texts)) for e in range(len(p) + 1)]
        for e in range(1, len(p) + 1):
            if e - start[e] >= least and not (e < len(p) and start[e + 1] <= start[e]):
                want.append((i, start[e], e - start[e], sum(len(places(t, p[start[e] : e])) for t in texts)))
    assert sorted((r.pid, r.start, r.len, r.n) for r in blockwise.shared(blocks, asked, least).collect()) == sorted(want)


def test_locate(blocks, asked):
    want = sorted((i, 100 + j, k) for i, p in enumerate(PATTERNS) for j, t in enumerate(TEXTS) for k in places(t or "", p or ""))
    assert sorted((r.pid, r.id, r.k) for r in blockwise.locate(blocks, asked).collect()) == want


def test_absent(blocks, asked):
    assert sorted(r.pid for r in blockwise.absent(blocks, asked).collect()) == [i for i, p in enumerate(PATTERNS) if not any(places(t or "", p or "") for t in TEXTS)]


def test_invert(blocks):
    assert {r.id: r.s for r in blockwise.invert(blocks).collect()} == {100 + i: t or "" for i, t in enumerate(TEXTS)}


def test_odd_sets(spark, blocks):
    twice = spark.createDataFrame([(1, "bra"), (1, "zz"), (None, "ü")], "pid long, pattern string")
    assert sorted((str(r.pid), r.n) for r in blockwise.count(blocks, twice).collect()) == [("1", 0), ("1", sum(len(places(t or "", "bra")) for t in TEXTS)), ("None", 1)]
    none = blockwise.block_index(spark.createDataFrame([], "id long, t string"), "id", "t")
    assert [r.n for r in blockwise.count(none, twice).collect()] == [0, 0, 0]
    assert not blockwise.count(blocks, twice.where("false")).collect()


@pytest.mark.parametrize("name", ["fm_count_benchmark", "fm_shared_passages", "fm_locate_benchmark", "fm_documents_with", "fm_absent_patterns", "invert_roundtrip"])
def test_no_search_waits_for_a_build_in_turns(spark, small, monkeypatch, name):
    """One index of all documents was ranked and inserted block after block before any search."""
    monkeypatch.setattr(catalog, "_BUILT", {})
    monkeypatch.setattr(builder, "build", lambda *a, **b: pytest.fail("a build in turns"))
    catalog.QUERIES[name](spark, small).collect()
