"""Counting against hand values, exhaustive search, and the sliced and kernel routes."""

import itertools
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from driftlattice.functions import episodes as E
from driftlattice.operators import batching, counting
from driftlattice.params import partial, serial
from driftlattice.sources import adapters


def seqs(spark, *texts):
    return spark.createDataFrame([(k, 0, list(t)) for k, t in enumerate(texts)], "batch_id long, seg int, seq array<string>")


def cands(spark, *names):
    return spark.createDataFrame([(n.replace("+", ">").split(">"),) for n in names], "nodes array<string>")


HAND = {
    "ABCABXC": {"A": 2, "A>B": 2, "A>B>C": 2, "A>A": 1, "A>B>A>B": 1, "A+B": 2, "A+A+B": 1, "A+B+C": 2},
    "AABBAB": {"A": 3, "A>B": 2, "A>B>C": 0, "A>A": 1, "A>B>A>B": 1, "A+B": 2, "A+A+B": 1, "A+B+C": 0},
    "ABABABAB": {"A": 4, "A>B": 4, "A>B>C": 0, "A>A": 2, "A>B>A>B": 2, "A+B": 4, "A+A+B": 2, "A+B+C": 0},
    "BAC": {"A": 1, "A>B": 0, "A>B>C": 0, "A>A": 0, "A>B>A>B": 0, "A+B": 1, "A+A+B": 0, "A+B+C": 1},
}


def test_hand_values(spark):
    rows = seqs(spark, *HAND)
    got = {}
    for ell, names in ((1, ["A"]), (2, ["A>B", "A>A"]), (3, ["A>B>C"]), (4, ["A>B>A>B"])):
        got.update({(r.batch_id, r.key): r.freq for r in counting.count_serial(rows, cands(spark, *names), ell, ties=False, zeros=True).collect()})
    got.update({(r.batch_id, r.key): r.freq for r in counting.count_parallel(rows, cands(spark, "A+B", "A+A+B", "A+B+C"), ties=False, zeros=True).collect()})
    for b, text in enumerate(HAND):
        for key, want in HAND[text].items():
            assert got[b, key] == want, (text, key)


def test_ties_follow_the_tick_rule(spark):
    ticks = [["A", "B"], ["B"], ["A"], ["A", "B"], ["B", "C"]]
    rows = spark.createDataFrame([(0, 0, ticks)], "batch_id long, seg int, seq array<array<string>>")
    count = lambda name, ell: counting.count_serial(rows, cands(spark, name), ell, zeros=True).first().freq
    assert [count("A", 1), count("B", 1), count("A>B", 2), count("A>B>C", 3), count("B>A", 2)] == [3, 4, 2, 1, 1]
    got = {r.key: r.freq for r in counting.count_parallel(rows, cands(spark, "A+B", "A+B+C"), zeros=True).collect()}
    assert got == {"A+B": 3, "A+B+C": 1}


def most_disjoint(seq, nodes):
    """Largest number of non-overlapped occurrences: shortest completions taken greedily from every start, by exhaustive search."""
    spans = set()
    for places in itertools.combinations(range(len(seq)), len(nodes)):
        if all(seq[i] == n for i, n in zip(places, nodes)):
            spans.add((places[0], places[-1]))
    best = {}

    def search(at):
        if at not in best:
            best[at] = max([0, *(1 + search(b + 1) for a, b in spans if a >= at)])
        return best[at]

    return search(0)


@settings(max_examples=60, deadline=None)
@given(st.text("ABC", max_size=10), st.text("ABC", min_size=1, max_size=3))
def test_greedy_is_best(seq, nodes):
    moves = 0
    for y in seq:
        moves += nodes[moves % len(nodes)] == y
    assert moves // len(nodes) == most_disjoint(seq, nodes)


def test_routes_agree_for_any_slicing(spark):
    rng = random.Random(5)
    rows = [(b, tick, rng.choice("ABCD")) for b in range(3) for tick in sorted(rng.choices(range(120), k=90))]
    frame = spark.createDataFrame(rows, "batch_id long, tick long, symbol string")
    names = [("A", "B", "C"), ("A", "A", "B"), ("D", "C", "D"), ("A", "B", "A")]
    c = spark.createDataFrame([(list(n),) for n in names], "nodes array<string>")
    want = {(r.batch_id, r.key): r.freq for r in counting.count_serial(batching.sequences(frame), c, 3).collect()}
    for slices in (1, 2, 7):
        s = batching.sequences(frame, slices=slices)
        assert {(r.batch_id, r.key): r.freq for r in counting.count_segmented(s, c, 3).collect()} == want
        assert {(r.batch_id, ">".join(names[r.cand])): r.freq for r in counting.count_kernel(s, names).where("freq > 0").collect()} == want


def test_input_order_and_partitions_do_not_matter(spark):
    rng = random.Random(6)
    rows = [(0, t, rng.choice("AB")) for t in range(60)]
    shuffled = rng.sample(rows, len(rows))
    a, b = (batching.sequences(spark.createDataFrame(x, "batch_id long, tick long, symbol string").repartition(n)).collect() for x, n in ((rows, 1), (shuffled, 5)))
    assert a == b


def test_waits_equal_the_automaton():
    rng = np.random.default_rng(1)
    for _ in range(50):
        seq = rng.integers(0, 4, rng.integers(0, 40))
        width = len(seq) + 1
        keys = np.sort(seq * width + np.arange(len(seq)))
        nodes = rng.integers(0, 4, (5, 3))
        start = rng.integers(0, 3, 5)
        got = counting.waits(keys, width, nodes, start)
        for row, r, n in zip(nodes, start, got):
            moves = int(r)
            for y in seq:
                moves += row[moves % 3] == y
            assert moves - r == n


def test_carried_state_counts_at_least_as_much(spark):
    rows = seqs(spark, "AB", "CAB", "C")
    carried = counting.count_carried(rows, cands(spark, "A>B>C"), 3, ties=False).groupBy().sum("freq").first()[0]
    reset = counting.count_serial(rows, cands(spark, "A>B>C"), 3, ties=False, zeros=True).groupBy().sum("freq").first()[0]
    assert (carried, reset) == (2, 0)


def test_partial_order_diamond(spark):
    spec = partial(["A", "B", "C", "D"], [("A", "B"), ("A", "C"), ("B", "D"), ("C", "D")])
    got = [r.freq for r in counting.count_partial(seqs(spark, "ABCDACBD", "BACD", "AABBCCDD"), spec, ties=False).orderBy("batch_id").collect()]
    assert got == [2, 0, 1]


def test_occurrences_list_their_ticks(spark):
    frame = spark.createDataFrame([(0, [(t, [x]) for t, x in enumerate("AXBABB")])], "batch_id long, ticks array<struct<tick: long, symbols: array<string>>>")
    got = [(r.occ_no, r.node, r.tick) for r in counting.occurrences(frame, serial("A>B")).orderBy("occ_no", "node").collect()]
    assert got == [(0, 0, 0), (0, 1, 2), (1, 0, 3), (1, 1, 4)]


def test_itemsets(spark):
    baskets = spark.createDataFrame([(0, ["a", "b", "c"]), (0, ["a", "c"]), (0, ["b"]), (0, [])], "batch_id long, items array<string>")
    assert {(r.key, r.freq) for r in counting.itemset_counts(baskets, 2).collect()} == {("a+b", 1), ("a+c", 2), ("b+c", 1)}


def test_wrong_inputs_are_refused(spark):
    with pytest.raises(ValueError):
        partial(["A", "A"], [])
    with pytest.raises(ValueError):
        partial(["A", "B"], [("A", "B"), ("B", "A")])
    with pytest.raises(ValueError):
        serial("A>>B")
    with pytest.raises(ValueError):
        adapters.validate_events(spark.createDataFrame([(1,)], "tick long"))
    bad = spark.createDataFrame([("all", None, None, "a")], adapters.EVENT_FRAME)
    with pytest.raises(Exception, match="tick and a symbol"):
        adapters.validate_events(bad).collect()


def test_late_events(spark):
    rows = [("s", 10, 1), ("s", 5, 2), ("s", 30, 3), ("s", 12, 4)]
    frame = spark.createDataFrame(rows, "stream_key string, tick long, arrival long")
    assert [r.late for r in batching.late_split(frame, 10).orderBy("arrival").collect()] == [False, False, False, True]


def test_empty_batch_and_unknown_symbol(spark):
    rows = seqs(spark, "", "AB")
    assert counting.count_serial(rows, cands(spark, "Z>A"), 2, ties=False).count() == 0
    assert rows.select(E.serial_frequency(F.col("seq"), F.array(F.lit("A")), 1)).count() == 2


def slow_parallel(ticks, nodes):
    from collections import Counter

    done, have, n = 0, Counter(), Counter(nodes)
    for tick in ticks:
        for x in tick:
            if have[x] < n[x]:
                have[x] += 1
        if have == n:
            done, have = done + 1, Counter()
    return done


def test_kernels_of_all_classes_equal_brute_force(spark):
    rng = random.Random(13)
    batches = {b: [sorted(set(rng.choices("abcde", k=rng.randint(1, 3)))) for _ in range(40)] for b in range(3)} | {7: []}
    whole = spark.createDataFrame([(b, 0, x) for b, x in batches.items()], "batch_id long, seg int, seq array<array<string>>")
    cut = spark.createDataFrame([(b, k, x[13 * k : 13 * k + 13] if k < 2 else x[26:]) for b, x in batches.items() for k in range(3)], "batch_id long, seg int, seq array<array<string>>")
    multisets = [tuple(x) for n in (1, 2, 3) for x in itertools.combinations_with_replacement("abcdz", n)]
    sets_ = [tuple(x) for n in (1, 2, 3) for x in itertools.combinations("abcdz", n)]
    serials = [tuple(x) for n in (1, 2, 3) for x in itertools.product("abz", repeat=n)]

    def slow_serial(ticks, nodes):
        n = 0
        for tick in ticks:
            n += nodes[n % len(nodes)] in tick
        return n // len(nodes)

    slow = {"parallel": slow_parallel, "itemset": lambda ticks, nodes: sum(set(nodes) <= set(t) for t in ticks), "serial": slow_serial}
    for klass, cands, tables in (("parallel", multisets, [whole]), ("itemset", sets_, [whole, cut]), ("serial", serials, [whole, cut])):
        want = {(b, c): slow[klass](x, c) for b, x in batches.items() for c in cands}
        for table in tables:
            got = {(r.batch_id, cands[r.cand]): r.freq for r in counting.count_kernel(table, cands, klass).collect()}
            assert got == want
            every = spark.createDataFrame([(b, list(c)) for b in batches for c in cands], "batch_id long, nodes array<string>")
            assert {(r.batch_id, tuple(r.nodes)): r.freq for r in counting.count_grid(table, every, klass).collect()} == want
    with pytest.raises(Exception):
        counting.count_kernel(cut, [("a", "b")], "parallel").collect()


def test_grid_blocks_split_the_candidates(spark, monkeypatch):
    monkeypatch.setattr(counting, "GRID_BLOCK", 3)
    table = spark.createDataFrame([(0, 0, list("abcabc")), (1, 0, list("cba"))], "batch_id long, seg int, seq array<string>")
    cands = [[x, y] for x in "abc" for y in "abc"]
    every = spark.createDataFrame([(0, c) for c in cands] + [(1, ["a", "b"])], "batch_id long, nodes array<string>")
    got = {(r.batch_id, ">".join(r.nodes)): r.freq for r in counting.count_grid(table, every).collect()}
    assert got == {**{(0, "a>a"): 1, (0, "b>b"): 1, (0, "c>c"): 1, (0, "a>b"): 2, (0, "b>c"): 2, (0, "a>c"): 2, (0, "b>a"): 1, (0, "c>b"): 1, (0, "c>a"): 1}, (1, "a>b"): 0}
    assert counting.count_grid(table, every.limit(0)).count() == 0


def test_pair_windows_equal_all_pairs_counted(spark, monkeypatch):
    """The k best pairs of each window without the table of all pairs; symbols with equal ticks share a count, ties are whole."""
    import random

    from driftlattice.plans import window

    rng = random.Random(5)
    rows = [(b, t, s) for b in range(2, 9) for t in range(b * 100, b * 100 + rng.choice((3, 20, 40))) for s in "abcdefg" if rng.random() < 0.4]
    rows += [(b, t, s.upper()) for b, t, s in rows if s in "abc"] + [(1, 100, "z"), (12, 1200, "z"), (6, 600, None)]
    frame = spark.createDataFrame(rows, "batch_id long, tick long, symbol string").where("symbol IS NOT NULL")
    symbols = frame.select("symbol").distinct()
    m = counting.count_serial(batching.sequences(frame), counting.enumerate_all(symbols, 2), 2).select("batch_id", "key", "freq")
    for k in (1, 5, 500):
        want = window.window_truth(m, 3, k, *window.batch_range(m)).select("window_end", "key", "wfreq", "rank").collect()
        got = counting.pair_windows(frame, 3, k, block=3).select("window_end", "key", "wfreq", "rank").collect()
        assert sorted(map(tuple, got)) == sorted(map(tuple, want)) and want
    assert counting.pair_windows(spark.createDataFrame([(0, t, "a") for t in range(65)], "batch_id long, tick long, symbol string"), 3, 5) is None


def test_pair_quality_equals_the_closed_forms_of_all_counts(spark):
    """All variants without the table of all pairs; classes of equal ticks weigh as many pairs as they hold."""
    import random

    from driftlattice.plans import metrics, variants, window

    rng = random.Random(6)
    rows = [(b, t, s) for b in range(1, 9) for t in range(b * 100, b * 100 + rng.choice((12, 25))) for s in "abcde" if rng.random() < 0.4]
    frame = spark.createDataFrame(rows + [(b, t, s.upper()) for b, t, s in rows if s in "ab"], "batch_id long, tick long, symbol string")
    m = counting.count_serial(batching.sequences(frame), counting.enumerate_all(frame.select("symbol").distinct(), 2), 2).select("batch_id", "key", "freq").cache()
    lo, hi = window.batch_range(m)
    want = metrics.quality(variants.all_reports(m, 4, 5, 0.5, lo, hi), window.window_truth(m, 4, 5, lo, hi)).drop("n_common")
    got = variants.pair_quality(frame, 4, 5, 0.5, block=2).select(*want.columns)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
