"""Pairs counted 64 at a time, against the automaton and against pairs counted one by one."""

import random

import numpy as np
import pytest

from driftlattice.operators import counting, pairs


def grid_of(n, lengths, share, seed=1):
    """Random ticks of n symbols in batches of some ticks."""
    rng, words = np.random.default_rng(seed), -(-n // 64)
    has = np.zeros((sum(lengths), words * 64), np.uint8)
    has[:, :n] = rng.random((sum(lengths), n)) < share
    return has, pairs.TickBits([f"s{i}" for i in range(n)], 0, np.packbits(has, axis=1, bitorder="little").view(np.uint64), np.append(0, np.cumsum(lengths)))


def automaton(has, a, b):
    n = 0
    for tick in has:
        n += int(tick[(a, b)[n % 2]])
    return n // 2


@pytest.mark.parametrize("share", [0.05, 0.3, 0.8])
def test_counts_of_all_pairs_equal_the_automaton(share):
    """Ties, batches of one tick and of 64, symbols that do not occur, and pairs of a symbol with itself."""
    lengths = [30, 1, 64, 2, 12]
    has, grid = grid_of(70, lengths, share)
    for words in (slice(0, 1), slice(1, 2), slice(0, 2)):
        counted = pairs.Counting(grid, words)
        for low, high in ((0, 9), (60, 70)):
            for j, planes in enumerate(counted.counts(low, high, 1)):
                part = has[grid.edges[j] : grid.edges[j + 1]]
                for a in range(low, high):
                    for b in range(words.start * 64, min(70, words.stop * 64), 7):
                        word, bit = np.array([(a - low) * counted.w + b // 64 - words.start]), np.array([b % 64])
                        assert pairs.values(planes, word, bit)[0] == automaton(part, a, b)


def test_windows_best_are_whole_whatever_the_blocks():
    lengths, m, k = [9] * 10, 4, 6
    _, grid = grid_of(100, lengths, 0.4, 2)
    every = np.stack([pairs.mask_pairs(x[:, None], x[None, :]).astype(int) for x in (pairs.masks(grid, j, np.arange(100)) for j in range(10))])
    for step in (100, 33):
        got = [pairs.window_rows(pairs.Counting(grid, slice(w, w + 1)), [(x, min(100, x + step)) for x in range(0, 100, step)], m, k, pairs.pilot(grid, m, k)) for w in (0, 1)]
        rows = [row for part in got for batch in part for row in zip(*(c.to_pylist() for c in batch.columns))]
        for end in range(m - 1, 10):
            total = every[end - m + 1 : end + 1].sum(0)
            bound = np.sort(total.ravel())[-k]
            want = {(a, b, total[a, b]) for a, b in np.argwhere(total >= bound).tolist()}
            assert {(a, b, n) for _, e, a, b, n, _ in rows if e == end and n >= bound} == want


def test_work_does_not_rest_on_equal_ticks(spark):
    """Symbols with the same ticks are symbols of their own: nothing is shared that real tables would not share."""
    rng = random.Random(3)
    rows = [(b, 100 * b + t, s + c) for b in range(3, 6) for t in range(20) for s in "abcd" if rng.random() < 0.5 for c in "xyz"]
    grid = pairs.tick_bits(spark.createDataFrame(rows + [(9, 901, "late"), (4, 401, None)], "batch_id long, tick long, symbol string"))
    assert grid.names == sorted({s for *_, s in rows} | {"late"}) and (grid.lo, grid.batches()) == (3, 3)
    for j in range(3):
        ticks = sorted({t for b, t, _ in rows if b == 3 + j})
        masks = pairs.masks(grid, j, np.arange(len(grid.names))).tolist()
        assert masks == [sum(1 << i for i, t in enumerate(ticks) if (3 + j, t, s) in rows) for s in grid.names]


def test_no_batch_and_no_symbol(spark):
    empty = spark.createDataFrame([], "batch_id long, tick long, symbol string")
    assert counting.pair_windows(empty, 3, 5).collect() == []
    one = spark.createDataFrame([(0, 1, "a"), (0, 2, "a")], "batch_id long, tick long, symbol string")
    assert counting.pair_windows(one, 3, 5).collect() == []
    assert [tuple(r) for r in counting.pair_windows(one, 1, 5).select("window_end", "key", "wfreq", "rank").collect()] == [(0, "a>a", 1, 1)]


def test_pairs_met_twice_do_not_raise_a_bound():
    """A report's bound is the k-th best of different pairs, and is no higher than that of all pairs."""
    _, grid = grid_of(20, [12] * 8, 0.5, 4)
    report = pairs.Report(np.full(8, 3), 1, False)
    a, b = np.divmod(np.arange(400), 20)
    every = pairs.report_bounds(grid, 3, 6, {"x": report}, a, b)["x"]
    some = pairs.report_bounds(grid, 3, 6, {"x": report}, a[:40], b[:40])["x"]
    twice = pairs.report_bounds(grid, 3, 6, {"x": report}, np.tile(a[:40], 3), np.tile(b[:40], 3))["x"]
    assert (twice == some).all() and (some <= every).all() and (some < every).any()
