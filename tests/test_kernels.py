"""Array kernels and array builders against the definition, on the worked example and on 300 random sets."""

import random

import numpy as np
import pytest

from corpusbwt.baselines import builders
from corpusbwt.functions import kernels
from corpusbwt.functions.alphabet import pack_bits, unpack_bits
from corpusbwt.plans.store import split_sizes


def definition(strings):
    """Symbols (code points) before all suffixes, sorted by text and, between equal ones, by string."""
    order = sorted((s[k:], j, k) for j, s in enumerate(strings) for k in range(len(s) + 1))
    return [ord(strings[j][k - 1]) if k else 0 for _, j, k in order]


def dense(strings):
    points, bounds = kernels.flat_codes(strings)
    alphabet, codes = np.unique(points, return_inverse=True)
    return np.concatenate([[0], alphabet]), codes + 1, bounds


def random_sets(n=300):
    rng = random.Random(7)
    for _ in range(n):
        letters = rng.choice(["a", "ab", "acgt"])
        yield ["".join(rng.choice(letters) for _ in range(rng.randint(0, 7))) for _ in range(rng.randint(1, 9))]


VARIANTS = {
    "brute": builders.brute,
    "one block": lambda c, b: builders.block_append(c, b, 1),
    "two blocks": lambda c, b: builders.block_append(c, b, 2),
    "seven blocks": lambda c, b: builders.block_append(c, b, 7),
    "a string a block": lambda c, b: builders.block_append(c, b, len(c) + len(b)),
    "reversed blocks": lambda c, b: builders.block_append(c, b, 3, reverse=True),
    "two symbols a step": lambda c, b: builders.block_append(c, b, 3, q=2),
    "old ranked in new": lambda c, b: builders.backward_single(c, b, 3),
    "column-wise": builders.column_wise,
    "column-wise on disk": lambda c, b: builders.column_wise(c, b, "disk"),
    "tree": builders.tree_insert,
    "no sieve": lambda c, b: kernels.symbols_before(c, b)[kernels.suffix_order(c, b, sieve=False)[0]],
}


def test_worked_example():
    table, codes, bounds = dense(["aba", "ba", "ab"])
    assert "".join(chr(p) if p else "$" for p in table[builders.brute(codes, bounds)]) == "aabbb$$aa$"
    old, edges = codes[:5], bounds[:3]
    engine = kernels.RankEngine(builders.brute(old, edges).astype(np.uint8), 2)
    assert kernels.chain_ranks(engine, codes[5:], np.array([0, 2]), 2).tolist() == [4, 5, 2]
    assert kernels.new_positions(np.array([2, 4, 5])).tolist() == [2, 5, 7]


@pytest.mark.parametrize("name", VARIANTS)
def test_random_sets(name):
    for strings in random_sets():
        table, codes, bounds = dense(strings)
        assert table[VARIANTS[name](codes, bounds)].tolist() == definition(strings), strings


def test_rank_is_the_count_of_smaller_old_suffixes():
    for strings in random_sets(100):
        table, codes, bounds = dense(strings)
        cut = len(strings) // 2
        if not cut:
            continue
        old, edges = builders.part_of(codes, bounds, 0, cut)
        new, new_edges = builders.part_of(codes, bounds, cut, len(strings))
        engine = kernels.RankEngine(builders.brute(old, edges).astype(np.uint8), max(1, len(table) - 1), spacing=64)
        got = kernels.chain_ranks(engine, new, new_edges, cut)
        texts = [s[k:] for s in strings[:cut] for k in range(len(s) + 1)]
        assert got.tolist() == [sum(t <= s[k:] for t in texts) for s in strings[cut:] for k in range(len(s) + 1)]
        order, _ = kernels.suffix_order(new, new_edges)
        assert (np.diff(got[order]) >= 0).all()


def test_long_strings_and_high_prefixes():
    strings = ["ab" * 400, "ab" * 400, "", "ab" * 399 + "b", "a" * 1000]
    table, codes, bounds = dense(strings)
    assert table[builders.brute(codes, bounds)].tolist() == definition(strings)
    assert table[builders.block_append(codes, bounds, 3)].tolist() == definition(strings)


def test_sieve_counts_fall_and_end_at_zero():
    _, codes, bounds = dense(["banana", "bandana", "banana", ""])
    left = kernels.suffix_order(codes, bounds)[1]
    assert left[-1] == 0 and sorted(left, reverse=True) == left


def test_spacing_and_packing():
    assert kernels.auto_spacing(4) == 64 and kernels.auto_spacing(101) == 512
    for bits in (1, 3, 7):
        codes = np.random.default_rng(0).integers(0, 1 << bits, 1001)
        assert (unpack_bits(pack_bits(codes, bits), bits, 1001) == codes).all()


def test_page_splits_stay_half_full():
    for p in (2, 7, 64):
        for n in range(p + 1, 10 * p):
            sizes = split_sizes(n, p)
            assert sum(sizes) == n and max(sizes) <= p and min(sizes) * 2 >= p


@pytest.mark.parametrize("positions", [False, True])
def test_pairs_are_made_once_in_bounded_memory(positions):
    """Pairs took several arrays of 8 bytes a row, and were made anew for every batch of strings."""
    import tracemalloc

    codes = np.random.default_rng(3).integers(0, 5, 3_000_000).astype(np.uint8)
    engine = kernels.RankEngine(codes, 4, positions=positions)
    row = np.arange(len(codes))
    first = codes.astype(np.int64)
    earlier = codes[engine.step(first, row)].astype(np.int64)
    want = np.where((first > 0) & (earlier > 0), earlier * 5 + first, 0)
    tracemalloc.start()
    made = engine.pairs()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (made.symbols == want).all() and engine.pairs() is made
    assert positions or peak < 24 * len(codes)


@pytest.mark.parametrize("sigma", [3, 300])
def test_tree_stays_balanced(sigma):
    """A full leaf led to new sums over all leaves, and every insertion walked a list of groups that grew with the set."""
    rng = np.random.default_rng(5)
    tree, held = builders.SymbolTree(sigma, leaf=4, fan=4), []
    for _ in range(1500):
        at, symbol, asked = int(rng.integers(0, len(held) + 1)), int(rng.integers(0, sigma + 1)), int(rng.integers(0, sigma + 1))
        assert tree.insert(at, symbol, asked) == held[:at].count(asked)
        held.insert(at, symbol)
    assert tree.symbols().tolist() == held and tree.smaller(2) == sum(s < 2 for s in held)
    depth, node = 1, tree.root
    while not node[3]:
        assert len(node[0]) <= 4
        depth, node = depth + 1, node[2][0]
    assert 4 <= depth <= 9
