"""The range-by-range sorter against the definition, cut into many ranges and passes, on odd sets."""

import numpy as np
import pytest

from corpusbwt.operators import bwt, numbering, ranged, ranking, suffixsort
from corpusbwt.operators.stringset import string_set
from corpusbwt.plans import catalog
from corpusbwt.session import written
from corpusbwt.sources import tables

ODD = ["aba", "ba", "ab", "", "abab", "ab", "über", "b" * 40, None, "\0", "\0\0a", "a\0", "x\U0001f600y"]
SETS = {
    "odd": ODD,
    "wide": ["".join(chr(0x4E00 + (i * 7 + j * j) % 700) for j in range(i % 30)) for i in range(60)],
    "copies": ["abcabcabcabc" * (i % 3) for i in range(90)],
    "empty": [],
}


@pytest.fixture
def narrow(monkeypatch):
    """Many ranges of few suffixes, a few of them a pass."""
    monkeypatch.setattr(ranged, "RANGE_BYTES", 500)
    monkeypatch.setattr(ranged, "SAMPLED", 400)
    monkeypatch.setattr(ranged, "PASS_SHARE", 0.5)


def both(a, b):
    return a.exceptAll(b).count(), b.exceptAll(a).count()


@pytest.mark.parametrize("name", list(SETS))
def test_ranges_and_passes(spark, narrow, name):
    strings = written(string_set(spark.createDataFrame(list(enumerate(SETS[name])), "id long, t string"), "t", ["id"]))
    want = written(suffixsort.sort_direct(strings))
    found = ranged.sort_ranged(strings, places=True, prefix=2 if name == "odd" else 0)
    assert found.n == want.count() and (name == "empty" or len(found.sizes) > 1)
    assert both(found.suffix_array(), want) == (0, 0)
    assert both(found.transform(), want.select("pos", "sym")) == (0, 0)
    assert both(found.runs(), bwt.runs(want.select("pos", "sym"))) == (0, 0)


@pytest.mark.parametrize("name", ["bwt_brute_array", "bwt_short_reads", "bwt_dna", "bwt_gather"])
def test_no_query_carries_suffix_texts_or_takes_one_task(spark, small, name):
    """Rows with suffix texts filled the disk, and one task for the whole set its memory."""
    plan = catalog.QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "suf" not in plan and "Coalesce" not in plan and "_part" not in plan


def test_windows_of_odd_texts(spark):
    texts = ["a" * 202, "", None, "\U0001f600" * 103 + "\n\r z", "x\ny" * 90]
    docs = spark.createDataFrame(list(enumerate(texts)), "id long, t string")
    for width in (1, 101):
        got = {(r.id, r.window): r.s for r in tables.read_windows(docs, ["id"], "t", width).collect()}
        assert got == {(i, w): t[w * width : (w + 1) * width] for i, t in enumerate(texts) if t is not None for w in range(max(1, -(-len(t) // width)))}


def test_suffixes_are_not_broadcast(spark, monkeypatch):
    """Suffixes are far larger than the stored strings, by which Spark would send them through the driver."""
    strings = written(string_set(spark.createDataFrame([(i, f"Customer#{i:09d}") for i in range(200)], "id long, t string"), "t", ["id"]))
    new, old = strings.where("sid >= 100"), strings.where("sid < 100")
    ranks, joined, number = written(ranking.ranks_merge(old, new)), [], numbering.with_row_index
    monkeypatch.setattr(numbering, "with_row_index", lambda df, *a: joined.append(df) or number(df, *a))
    ranking.ordered_new(new, ranks)
    joined.append(ranking.reorder(ranks, written(suffixsort.sort_direct(new))))
    assert len(joined) == 2
    for one in joined:
        assert "BroadcastHashJoin" not in one._jdf.queryExecution().executedPlan().toString()


def test_neighbours_are_not_broadcast(spark):
    strings = written(string_set(spark.createDataFrame([(i, f"name {i % 7}") for i in range(200)], "id long, t string"), "t", ["id"]))
    found = bwt.neighbours(suffixsort.sort_local(strings))
    assert "BroadcastHashJoin" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.count() == strings.count() * 7


def test_small_alphabets_share_bytes(spark, monkeypatch):
    """Words of eight letters left most suffixes of four letters tied, with the splitters and with each other."""
    monkeypatch.setattr(ranged, "RANGE_BYTES", 2000)
    rng, texts = np.random.default_rng(3), {}
    for size in (4, 15, 16, 40):
        drawn = ["".join(chr(97 + x) for x in rng.integers(0, size, n)) for n in rng.integers(0, 60, 20)]
        texts[size] = [*drawn, *drawn[:5], "".join(chr(97 + i) for i in range(size)), drawn[0] * 3, "a" * 90, "a" * 91]
    for size, held in texts.items():
        strings = written(string_set(spark.createDataFrame(list(enumerate(held)), "id long, t string"), "t", ["id"]))
        found = ranged.sort_ranged(strings, places=True)
        assert both(found.suffix_array(), suffixsort.sort_direct(strings)) == (0, 0) and len(found.sizes) > 1
        assert ranged._code_bits(found.points[1:]) == (4 if size <= 15 else 8)


def test_words_are_sorted_to_their_ends():
    """Sorted in pieces that fit a number with group and place, against the words as tuples; equal ones stay in order."""
    rng = np.random.default_rng(4)
    for top in (2, 1 << 20, 1 << 63):
        texts = [(*(int(x) << 8 | 1 for x in rng.integers(0, top >> 8 or 2, rng.integers(0, 4))), int(rng.integers(0, 3)) << 8) for _ in range(3000)]
        counts, words = np.array([len(t) for t in texts]), np.array([w for t in texts for w in t], np.uint64)
        assert ranged._ordered(words, counts).tolist() == sorted(range(len(texts)), key=lambda i: texts[i])


def test_projection_is_taken_once(spark):
    """The windows' conditions took it again for every place in which they name the text."""
    docs = spark.createDataFrame([(0, "Über, Zebra 1"), (1, None), (2, "\U0001f600"), (3, "")], "id long, t string")
    found = tables.dna_projection(docs, "t")
    assert {r.id: r.t for r in found.collect()} == {0: "caccacca", 1: None, 2: "", 3: ""}
    plan = tables.read_windows(found, ["id"], "t", 3)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("lower") == 1
