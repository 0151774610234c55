"""Planted streams by the places of their symbols, against the stream as a table and the kernels that read it."""

import itertools
import random
from functools import partial

import numpy as np
import pytest

from driftlattice.operators import batching, counting
from driftlattice.params import MineParams
from driftlattice.plans import streams
from driftlattice.queries import planted as P
from driftlattice.sources import adapters


def test_place_counts_equal_brute_force(monkeypatch):
    rng = random.Random(1)
    monkeypatch.setattr(counting, "PAIR_BLOCK", 7)
    every = [x for ell in (1, 2, 3) for x in itertools.product("abcdefg", repeat=ell)]
    for _ in range(30):
        seq = [rng.choice("abcdef") for _ in range(rng.randint(1, 60))]
        places = {s: np.array([i for i, x in enumerate(seq) if x == s]) for s in set(seq)}
        for cands in (every + [tuple(rng.choice("abcdef") for _ in range(4)) for _ in range(50)], [("a", "b"), ("c", "c")]):
            want = []
            for p in cands:
                n = 0
                for y in seq:
                    n += p[n % len(p)] == y
                want.append(n // len(p))
            assert counting.place_counts(places, cands) == want


@pytest.mark.parametrize("alphabet, noise, patterns, drift", [(1000, 5, 50, ((15, 20),)), (50, 12, 10, ((3, 5), (8, 9)))])
def test_places_are_those_of_the_stream(spark, tiny, alphabet, noise, patterns, drift):
    events = spark.read.parquet(f"{tiny}/events.parquet")
    span = adapters.planted_span(events, 30)
    want = sorted((r.tick, r.symbol) for r in adapters.planted_stream(events, alphabet, patterns, noise, span, drift).collect())
    ids = np.array([r.event_id for r in events.select("event_id").collect()])
    made = adapters.planted_places(ids, alphabet, patterns, noise, span, drift)
    assert sorted((t, s) for s, ticks in made.items() for t in ticks.tolist()) == want


def test_methods_on_places_equal_methods_on_sequences(spark, tiny, monkeypatch):
    """The whole of measured(), beside the same methods over sequences of the same stream; nothing of the stream is shuffled."""
    monkeypatch.setattr(P, "KS", P.KS | {5: 5})
    got = P.measured(spark, tiny, {"x": (200, 2, 5, 6, ((2, 4),)), "y": (100, 1, 5, 5)}, "places", m=3, delta=1.0)
    rows = None
    for key, args in {"x": (200, 2, 5, 6, ((2, 4),)), "y": (100, 1, 5, 5)}.items():
        one = batching.sequences(P.planted_frame(spark, tiny, *args)).selectExpr(f"'{key}' AS stream_key", "batch_id", "seq")
        rows = one if rows is None else rows.unionByName(one)
    want = streams.evaluate(rows, {k: MineParams(m=3, k=5, ell=4, delta=1.0) for k in "xy"}, P.methods)
    assert sorted(map(repr, got.collect())) == sorted(map(repr, want.collect()))


def test_runs_counted_as_units_equal_brute_force(monkeypatch):
    """Symbols that only occur in whole runs are counted by their first one, and places beyond the bound are made again."""
    rng = random.Random(2)
    runs = ["abc", "de", "f", "g"]
    ids = {}
    for b in range(3):
        ids[b] = np.array([rng.randrange(4) for _ in range(rng.randint(1, 40))])

    def stream(kinds):
        return "".join(runs[k] for k in kinds)

    made = []

    def make(kinds):
        made.append(len(kinds))
        return {s: np.array([i for i, x in enumerate(stream(kinds)) if x == s]) for s in set(stream(kinds))}

    asked = []
    monkeypatch.setattr(streams, "place_counts", lambda places, cands, *rest: asked.extend(cands) or counting.place_counts(places, cands, *rest))
    cands = [x for ell in (1, 2, 3) for x in itertools.product("abcdefg", repeat=ell)] + [tuple(rng.choice("abcdefg") for _ in range(4)) for _ in range(1500)]
    for room in (1 << 20, 0):
        monkeypatch.setattr(streams, "KEPT_PLACES", room)
        places = streams.Places(ids, make)
        for b, kinds in ids.items():
            seq, got = stream(kinds), places.counter(b)(cands)
            assert places.events[b] == len(seq)
            for p in cands:
                n = 0
                for y in seq:
                    n += p[n % len(p)] == y
                assert got[p] == n // len(p), (p, seq)
    assert made == [len(x) for x in ids.values()] * 3  # once with room; without, once more for each batch
    assert {x for p in asked for x in p} <= set("adfg") and len(asked) < 2 * 3 * len(cands) / 3


def test_a_data_set_is_mined_only_for_queries_that_need_it(spark, tiny, monkeypatch):
    mined = []

    def measured(spark, d, named, name):
        mined.append(sorted(named))
        return spark.createDataFrame([(k,) for k in named], "stream_key string")

    monkeypatch.setattr(P, "measured", measured)
    have = {}
    monkeypatch.setattr(P, "kept", lambda *_: have)
    assert {k: v.first()[0] for k, v in P.of_sets(spark, tiny, ("C1", "C2", "C3")).items()} == {"C1": "C1", "C2": "C2", "C3": "A2"}
    P.of_sets(spark, tiny, P.SETS)
    assert mined == [["A2", "C1", "C2"], ["A1", "A3", "B1", "B3"]]


def test_methods_run_on_what_each_batch_counted_ahead():
    """Batches are found apart; the methods on their rows equal those on the whole stream, and make no batch again."""
    span = 200 * adapters.STEP
    ids = {b: np.arange(200 * b, 200 * (b + 1)) for b in range(6)}
    ids[3] = ids[3][ids[3] % 7 != 0]  # ids may lack some
    again, own = [], MineParams(m=3, k=5, ell=4, delta=1.0)

    def make(e):
        return adapters.planted_places(e, 100, 5, 2, span, ((2, 4),))

    def results(places):
        symbols = [(x,) for x in sorted({x for unit in places.units.values() for x in unit})]
        return streams.result_rows("x", streams.line_of_methods({b: places.counter(b) for b in places.ids}, symbols, own, P.methods(3)), 4, places.events, 3)

    rows = []
    for b in ids:
        one = streams.Places({b: ids[b]}, make)
        one.ahead(b, own)
        rows.append(one.row(b, "x"))
    apart = streams.Places.of_rows(rows, lambda e: again.append(len(e)) or make(e))
    assert all(np.array_equal(apart.ids[b], ids[b]) for b in ids)
    assert results(apart) == results(streams.Places(ids, make))
    assert again == []


def test_symbols_whose_unit_differs_by_batch_are_counted_by_batch():
    """b follows each a in two batches only, and c has its run broken in one."""
    texts = {0: "ababcd", 1: "abba", 2: "aab", 3: "cd", 4: "dcabcd"}
    places = streams.Places({b: np.array([b]) for b in texts}, lambda e: {s: np.array([i for i, x in enumerate(texts[int(e[0])]) if x == s]) for s in set(texts[int(e[0])])})
    counters = {b: places.counter(b) for b in texts}
    cands = [x for ell in (1, 2, 3) for x in itertools.product("abcd", repeat=ell)]
    for b, seq in texts.items():
        got = counters[b](cands)
        for p in cands:
            n = 0
            for y in seq:
                n += p[n % len(p)] == y
            assert got[p] == n // len(p), (p, seq)


def test_streams_of_the_same_base_events_share_counts(monkeypatch):
    """What one stream counts is not counted again for others that hold the symbols at the same places; results are those of each stream alone."""
    span = 200 * adapters.STEP
    ids = {b: np.arange(200 * b, 200 * (b + 1)) for b in range(5)}
    made = {key: partial(adapters.planted_places, alphabet=a, n_patterns=n, noise_copies=c, span=span, drift=((2, 4),)) for key, a, c, n in (("x", 100, 2, 5), ("y", 60, 1, 5), ("z", 100, 2, 3))}
    params, asked = dict.fromkeys(made, MineParams(m=3, k=3, ell=4, delta=1.0)), []
    monkeypatch.setattr(streams, "place_counts", lambda places, cands, held, again: asked.extend((p, i in again) for i, p in enumerate(cands)) or counting.place_counts(places, cands, held, again))

    def results(key, places):
        symbols = [(x,) for x in sorted({x for unit in places.units.values() for x in unit})]
        return streams.result_rows(key, streams.line_of_methods({b: places.counter(b) for b in places.ids}, symbols, params[key], P.methods(3)), 4, places.events, 3)

    for b in ids:
        del asked[:]
        streams.found_rows(b, ids[b], ["x", "y"], params, made)
        planted = [(p, again) for p, again in asked if len(p) > 1 and all(x[0] == "p" for x in p)]
        assert planted and len(planted) == len(set(planted))
    tables = [streams.found_table(streams.found_rows(b, ids[b], list(made), params, made)) for b in ids]
    rows = [row for table in tables for row in streams.table_rows(table)]
    for key in made:
        alone = streams.Places(ids, made[key])
        assert results(key, streams.Places.of_rows([r for r in rows if r["stream_key"] == key], made[key])) == results(key, alone)


def test_accuracy_of_several_streams_is_that_of_each(spark):
    rows = [(key, variant, "topk", end, pattern, 5, 1) for key, variant, end, pattern in [
        ("x", "window_recount", 2, "a"), ("x", "window_recount", 3, "b"), ("x", "lookahead", 2, "a"), ("x", "lookahead", 3, "a"), ("y", "window_recount", 2, "b"), ("y", "lookahead", 2, "a"), ("y", "lookahead", 2, "b")]]
    results = spark.createDataFrame(rows, "stream_key string, variant string, kind string, window_end long, key string, wfreq long, rank long")
    got = sorted(map(tuple, P.quality_of(results, ("stream_key",)).collect()))
    assert got == sorted((key, *r) for key in "xy" for r in P.quality_of(results.where(f"stream_key = '{key}'")).collect())
    assert got == [("x", "lookahead", 2, 1, 1, 1.0, 1.0), ("x", "lookahead", 3, 1, 1, 0.0, 0.0), ("x", "previous_window", 3, 1, 1, 0.0, 0.0), ("y", "lookahead", 2, 2, 1, 0.5, 1.0)]
