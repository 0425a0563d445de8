"""Kernels on the literal fixtures: moves are counted exactly."""

import random

import numpy as np
import pytest

from triewalk.kernel.cursor import OpCounter, SortedCursor, first_above, first_at_least
from triewalk.kernel.hashwalk import hash_walk
from triewalk.kernel.meet import SkipMeet, drain, meet_arrays
from triewalk.kernel.trie import TrieCursor
from triewalk.kernel.views import CompareView, ConstView, EqualView, ExistsView, JoinView, NotView, UnionView
from triewalk.kernel.walk import ColumnTrie, bit_rows, count_moves, walk, walk_batches

A, B, C = [0, 1, 3, 4, 5, 6, 7, 8, 9, 11], [0, 2, 6, 7, 8, 9], [2, 4, 5, 8, 10]
TRI = [[(0, 0), (2, 0)], [(0, 1), (1, 0)], [(1, 1), (2, 1)]]
TRIE = [(1, 3, 4), (1, 3, 5), (1, 4, 6), (1, 4, 8), (1, 4, 9), (1, 5, 2), (3, 5, 2)]


def test_meet_trace():
    ops = OpCounter(trace=True)
    assert drain(SkipMeet([SortedCursor(x, ops, n) for x, n in zip((A, B, C), "ABC", strict=True)])) == [8]
    assert [(w, t or "step", at) for w, _, t, at in ops.log] == [("A", 2, 3), ("B", 3, 6), ("C", 6, 8), ("A", 8, 8), ("B", 8, 8), ("C", "step", 10), ("A", 10, 11), ("B", 11, None)]


@pytest.mark.parametrize("n", [4, 100, 10000])
def test_density_needs_four_skips(n):
    ops = OpCounter()
    sets = (range(2 * n), range(n, 3 * n), [*range(n), *range(2 * n, 3 * n)])
    assert drain(SkipMeet([SortedCursor(x, ops) for x in sets])) == []
    assert (ops.total("skip"), ops.total("step")) == (4, 0)


def test_meet_edges():
    assert drain(SkipMeet([SortedCursor([1, 2])])) == [1, 2]
    assert SkipMeet([SortedCursor([]), SortedCursor([1])]).done
    inner = SkipMeet([SortedCursor(A), SortedCursor(B)])
    assert drain(SkipMeet([inner, SortedCursor(C)])) == [8]
    big = [-(2**63), -1, 2**63 - 1]
    assert drain(SkipMeet([SortedCursor(big), SortedCursor(big)])) == big
    assert first_above(big, 2**63 - 1, 0, 3) == 3 and first_at_least(big, 0, 0, 3) == 2


def test_meet_random_moves_bounded():
    rng = random.Random(3)
    for _ in range(200):
        sets = [sorted(rng.sample(range(60), rng.randint(0, 40))) for _ in range(rng.randint(1, 4))]
        want = sorted(set.intersection(*map(set, sets)))
        ops = OpCounter()
        assert drain(SkipMeet([SortedCursor(s, ops) for s in sets])) == want
        assert ops.total() <= len(sets) * min(map(len, sets)) + len(sets)
        assert meet_arrays([np.array(s, dtype=np.int64) for s in sets]).tolist() == want


def test_trie_navigation():
    t = TrieCursor.of(TRIE, 3)
    for want in (1, 3, 4):
        t.open()
        assert t.key == want
    t.step()
    assert t.key == 5
    t.step()
    assert t.done
    t.up()
    t.step()
    t.open()
    assert t.key == 6
    t.up(), t.up()
    t.step()
    assert t.key == 3


def test_grid_and_projection_counts():
    grid = [(i, j) for i in range(16) for j in range(16)]
    rows, ops = count_moves([([0, 1], grid), ([1, 2], grid), ([0, 2], grid)], 3)
    assert len(rows) == 4096
    assert [ops.total(k) for k in ("open", "up", "step", "skip")] == [546, 546, 4368, 4095]
    few = [(a, b) for a in range(8) for b in range(32)]
    rows, ops = count_moves([([0, 1], few), ([1, 2], [(b, a) for a, b in few]), ([0, 2], [(a, 0) for a in range(256)])], 3)
    assert (len(rows), ops.total()) == (256, 2091)


def test_walks_agree_with_brute_force():
    rng = random.Random(0)
    for _ in range(200):
        r = [list({(rng.randint(0, 5), rng.randint(0, 5)) for _ in range(rng.randint(0, 20))}) for _ in range(3)]
        want = sorted((a, b, c) for a, b in r[0] for x, c in r[1] if x == b and (a, c) in r[2])
        atoms = [([0, 1], r[0]), ([1, 2], r[1]), ([0, 2], r[2])]
        assert count_moves(atoms, 3)[0] == want
        assert sorted(hash_walk(atoms, 3, OpCounter())) == want
        if all(r):
            tries = [ColumnTrie.of([np.array(c) for c in zip(*x, strict=True)]) for x in r]
            costs = np.zeros(3, dtype=np.int64)
            got = sorted(tuple(map(int, row)) for b in walk_batches(tries, TRI, 3, costs) for row in zip(*b, strict=True))
            assert got == want


@pytest.mark.parametrize("far", [1, 1000, 1 << 57])
def test_lists_agree_with_brute_force(far):
    """Dense slices are met as rows of bits, others are searched; both give each prefix's values as a list."""
    rng = random.Random(far)
    for most in (5, 40):
        for _ in range(40):
            r = [list({(rng.randint(0, most), rng.randint(0, most) * far - far) for _ in range(rng.randint(1, 15 * most))}) for _ in range(3)]
            r[0] = [(a, b // far + 1) for a, b in r[0]]  # b as S has it
            want = sorted((a, b, c) for a, b in r[0] for x, c in r[1] if x == b and (a, c) in r[2])
            tries = [ColumnTrie.of([np.array(c, dtype=np.int64) for c in zip(*x, strict=True)]) for x in r]
            got = []
            for *prefix, n, values in walk_batches(tries, TRI, 7, lists=True):
                assert n.sum() == len(values)
                got += zip(*(np.repeat(p, n).tolist() for p in prefix), values.tolist(), strict=True)
            assert sorted(got) == want


def test_bit_rows_keep_to_neighbourhoods():
    """Ten thousand blocks of eight values take bytes a first value, not a bit a value of all blocks; slices that lie far apart take none."""
    first = np.arange(80_000)
    near = ColumnTrie.of([np.repeat(first, 8), (np.repeat(first, 8) // 8) * 8 + np.tile(np.arange(8), 80_000)])
    names, one, _ = bit_rows([near, near], [(0, 1), (1, 1)])
    assert len(names) == 80_000 and len(one.bits) == 80_000
    wide = ColumnTrie.of([np.repeat(first, 2), np.stack([first // 2, 79_999 - first // 2], axis=1).ravel()])
    assert bit_rows([wide, wide], [(0, 1), (1, 1)]) is None


def test_tiny_instance_costs():
    r, s, t = [(7, 4)], [(4, 1), (4, 4), (4, 5), (4, 9)], [(7, 2), (7, 3), (7, 5)]
    tries = [ColumnTrie.of([np.array(c) for c in zip(*x, strict=True)]) for x in (r, s, t)]
    costs = np.zeros(3, dtype=np.int64)
    rows = [tuple(map(int, row)) for b in walk_batches(tries, TRI, costs=costs) for row in zip(*b, strict=True)]
    assert rows == [(7, 4, 5)] and costs.tolist() == [1, 1, 3]


def test_views():
    assert drain(UnionView([SortedCursor([1, 4]), SortedCursor([2, 4, 9])])) == [1, 2, 4, 9]
    u = UnionView([SortedCursor([1, 4]), SortedCursor([2, 4, 9])])
    assert drain(SkipMeet([u, SortedCursor([0, 4, 9])])) == [4, 9]
    assert drain(SkipMeet([ConstView(4), SortedCursor(C)])) == [4]
    pairs = TrieCursor.of([(1, 2), (3, 3), (5, 1), (6, 6)], 2)
    assert list(walk([pairs, EqualView()], [[0, 1], [0, 1]])) == [(3, 3), (6, 6)]
    grid = [(i, j) for i in range(3) for j in range(3)]
    make = lambda: JoinView([TrieCursor.of(grid, 2), TrieCursor.of([(0, 1), (2, 2)], 2)], [[0], [0, 1], [1]])
    assert list(ExistsView(make(), 2, 3).rows()) == [(a, b) for a in range(3) for b in (0, 2)]
    assert NotView(lambda: TrieCursor.of(grid, 2))((1, 7)) and not NotView(lambda: TrieCursor.of(grid, 2))((1, 2))
    assert CompareView("<", 0, 1)((1, 2)) and not CompareView("<", 0, 1)((2, 2))
