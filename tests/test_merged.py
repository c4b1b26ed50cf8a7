"""Groups of strings built side by side and merged by sorted ranks, cut small, on odd sets."""

import threading
from functools import partial

import numpy as np
import pytest

from corpusbwt.baselines import builders
from corpusbwt.functions import kernels
from corpusbwt.operators import merged, suffixsort
from corpusbwt.operators.stringset import string_set
from corpusbwt.plans import catalog
from corpusbwt.session import written
from tests.test_kernels import definition
from tests.test_ranged import SETS


@pytest.fixture
def narrow(monkeypatch):
    """Groups of few suffixes, small pieces, and transforms that are sent in parts."""
    monkeypatch.setattr(merged, "GROUP", 60)
    monkeypatch.setattr(merged, "PIECE", 16)
    monkeypatch.setattr(merged, "MOST_SENT", 150)


def symbols(found):
    got = sorted((r.pos, r.sym) for r in found.transform().collect())
    assert [p for p, _ in got] == list(range(len(got)))
    return [s for _, s in got]


@pytest.mark.parametrize("name", list(SETS))
def test_groups_are_merged(spark, narrow, name):
    texts = SETS[name][:24]
    strings = written(string_set(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "t", ["id"]))
    want = definition([t or "" for t in texts]) if texts else []
    assert symbols(merged.transform(strings, builders.appended)) == want
    if name == "odd":
        for build in (builders.backward_single, builders.column_wise):
            assert symbols(merged.transform(strings, build, blocks=3)) == want


def test_packed_ranks():
    """The compact engine against listed positions, with chains of strings alone and together, and a start for each string."""
    rng = np.random.default_rng(5)
    for sigma, n in ((1, 300), (5, 70_000), (150, 140_000), (254, 1000)):
        symbols = rng.integers(0, sigma + 1, n).astype(np.uint8)
        packed, listed = kernels.PackedRanks(symbols, sigma), kernels.RankEngine(symbols, sigma, positions=True)
        sizes = np.concatenate([rng.integers(0, 40, 60), [700, 0, 900]])
        bounds = np.concatenate([[0], np.cumsum(sizes)])
        codes, start = rng.integers(1, sigma + 1, bounds[-1]), rng.integers(0, 50, len(sizes))
        assert (kernels.chain_ranks(packed, codes, bounds, start) == kernels.chain_ranks(listed, codes, bounds, start)).all()
        every = np.arange(n + 1)
        for c in {0, 1, sigma}:
            assert (packed.rank(np.full(n + 1, c), every) == np.concatenate([[0], np.cumsum(symbols == c)])).all()


@pytest.mark.parametrize("name", ["bwt_block_append_array", "bwt_whole_documents", "bwt_backward_old_in_new", "bwt_column_wise", "bwt_block_append", "bwt_block_append_long", "conversations_append"])
def test_no_set_takes_one_task(spark, small, name, monkeypatch):
    """One task for the whole set, or for a fixed share of it, took too long and too much memory."""

    def refused(*args, **options):
        raise AssertionError("a block is sorted by one task, whatever its size")

    monkeypatch.setattr(suffixsort, "places_local", refused)
    plan = catalog.QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "Coalesce" not in plan


@pytest.mark.parametrize("name", ["block_ranks_g", "insert_positions"])
def test_ranks_need_no_suffix_texts(spark, small, name, monkeypatch):
    """Rows with suffix texts filled the disk."""

    def refused(*args, **options):
        raise AssertionError("suffix texts are sorted")

    monkeypatch.setattr(catalog.rows, "bwt_once", refused)
    monkeypatch.setattr(catalog.ranking, "ordered_new", refused)
    assert catalog.QUERIES[name](spark, small).count() == 244990


@pytest.mark.parametrize("seed", range(3))
def test_two_symbols_a_step(spark, narrow, seed):
    """Two symbols a step through packed pairs, in groups and between them, against single steps."""
    rng = np.random.default_rng(seed)
    texts = ["".join("acgt"[x] for x in rng.integers(0, 4, n)) for n in rng.integers(0, 14, 40)]
    strings = written(string_set(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "t", ["id"]))
    points = np.array([0, *map(ord, "acgt")], np.int32)
    assert symbols(merged.transform(strings, partial(builders.appended, q=2), blocks=2, q=2, points=points)) == definition(texts)
    codes, bounds = merged._coded(texts, points)
    packed = kernels.PackedRanks(builders.brute(codes, bounds).astype(np.uint8), 4)
    for start in (0, 17):
        assert (kernels.chain_ranks(packed, codes, bounds, start, 2) == kernels.chain_ranks(packed, codes, bounds, start)).all()


def test_two_symbol_steps_store_no_row_a_suffix(spark, small, monkeypatch):
    """Blocks went through rows with suffix, rank and place, which filled the disk."""

    def refused(*args, **options):
        raise AssertionError("rows of suffixes are stored")

    monkeypatch.setattr(catalog.builder, "build", refused)
    assert catalog.QUERIES["bwt_dna_two_symbol_steps"](spark, small).count() == 380435


def test_neighbours_are_merged_side_by_side(spark, narrow, monkeypatch):
    """Merges of a few groups waited for each other, however many there were."""
    met, insert = threading.Barrier(2, timeout=60), merged.inserted
    waiting = [met.wait, met.wait]

    def one(*args):
        if waiting:
            waiting.pop()()
        return insert(*args)

    monkeypatch.setattr(merged, "inserted", one)
    monkeypatch.setattr(merged, "MOST_SENT", 1 << 20)
    texts = SETS["copies"][:32]
    strings = written(string_set(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "t", ["id"]))
    assert symbols(merged.transform(strings, builders.appended, blocks=4)) == definition(texts) and not waiting


def test_ranks_in_parts_are_summed(spark, narrow):
    """Ranks in every part were held side by side, so a task took few strings and made each part's counters for them alone."""
    texts = SETS["copies"][:24]
    strings = written(string_set(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "t", ["id"]))
    parts = merged.groups(strings, builders.appended)
    assert len(parts) > 2
    found = merged.chained(strings, parts, lambda sid, sizes, ranks: [np.repeat(sid, sizes + 1), ranks.astype(np.int64)], "sid long, g long")
    assert sorted(r.g for r in found.collect()) == list(range(sum(len(t) + 1 for t in texts)))


def test_sorted_places():
    """Places travel in the numbers that are sorted, where both fit; equal keys stay in order then."""
    rng = np.random.default_rng(6)
    for bits, n in ((3, 1000), (40, 5000), (64, 1000), (1, 1)):
        key = rng.integers(0, 1 << min(bits, 62), n).astype(np.uint64)
        order, lead = kernels.sorted_places(key, bits)
        assert (key[order] == np.sort(key)).all() and lead.sum() == len(np.unique(key))
        if bits < 64:
            assert (order == np.argsort(key, kind="stable")).all()
