"""The incremental lattice against mining from scratch, the worked examples, and the closed forms."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from driftlattice.functions import thresholds as T
from driftlattice.params import MineParams, VariantSpec
from driftlattice.plans import lattice as L
from driftlattice.plans import metrics, variants, window


def counter(seq):
    def count(patterns):
        out = {}
        for p in patterns:
            n = 0
            for y in seq:
                n += p[n % len(p)] == y
            out[p] = n // len(p)
        return out

    return count


@pytest.mark.parametrize("relation", ["contig", "subseq"])
def test_advance_equals_scratch(relation):
    rng = random.Random(3)
    for _ in range(25):
        letters = "abcdef"[: rng.randint(3, 6)]
        symbols = [(a,) for a in letters]
        params = MineParams(m=3, k=rng.choice([2, 5, 8]), ell=4 if len(letters) < 5 else 3, delta=rng.choice([1.0, 2.0, "estimate"]), relation=relation)
        prev, weights = None, [rng.random() for _ in letters]
        for s in range(6):
            weights = [max(0.02, w + rng.uniform(-0.3, 0.3)) for w in weights]
            seq = rng.choices(letters, weights, k=rng.choice([0, 8, 40, 80]))
            prev, stats = L.advance(prev, counter(seq), symbols, params, lambda d: 2 * d, L.delta_rule(params), s)
            scratch = L.mine_batch(L.Memo(counter(seq)), symbols, params.ell, stats.f_min, "serial", relation)
            every = counter(seq)(list(itertools.product(letters, repeat=params.ell)))
            assert prev.frequent == scratch.frequent and prev.border == scratch.border
            assert stats.fk == L.kth(every.values(), params.k)


def test_worked_update():
    """A border pattern turns frequent and carries longer ones with it; a fallen one takes its super-patterns along."""
    before, after = "YYYABCDABCDABCDCDXCDXCDX", "BBBAAACDXYCDXYCDXY"
    symbols = [(x,) for x in "ABCDXY"]
    old = L.mine_batch(L.Memo(counter(before)), symbols, 4, 3)
    names = lambda level: {"".join(p) for p in level}
    assert names(old.frequent[1]) == {"AB", "AC", "AD", "BC", "BD", "CC", "CD", "CX", "DC", "DD", "DX"} and len(old.border[1]) == 25
    assert names(old.frequent[2]) == {"ABC", "ABD", "ACD", "BCD", "CCD", "CDC", "CDD", "CDX", "DCD"} and len(old.border[2]) == 17
    assert names(old.frequent[3]) == {"ABCD", "CDCD"} and len(old.border[3]) == 12
    params = MineParams(k=1, ell=4, delta=0.0)
    new, stats = L.advance(old, counter(after), symbols, params, lambda d: 0.0, L.delta_rule(params), 1)
    scratch = L.mine_batch(L.Memo(counter(after)), symbols, 4, 3)
    assert stats.f_min == 3 and new.frequent == scratch.frequent and new.border == scratch.border
    assert names(new.frequent[1]) == {"CD", "CX", "CY", "DX", "DY", "XY"} and len(new.border[1]) == 30
    assert [names(n) for n in new.new[1:]] == [{"CY", "DY", "XY"}, {"CDY", "CXY", "DXY"}, {"CDXY"}]


def test_candidates_need_a_new_parent():
    frequent = {("a", "b"), ("b", "c"), ("c", "d")}
    assert L.join_candidates(frequent) == {("a", "b", "c"), ("b", "c", "d")}
    assert L.join_candidates(frequent, {("c", "d")}) == {("b", "c", "d")}
    assert L.join_candidates({("a", "b"), ("a", "c"), ("b", "c")}, None, "itemset") == {("a", "b", "c")}
    assert L.join_candidates({("a",), ("b",)}, None, "parallel") == {("a", "a"), ("a", "b"), ("b", "b")}


def test_join_as_equi_join(spark):
    rng = random.Random(1)
    frequent = {tuple(rng.choices("abcd", k=3)) for _ in range(30)}
    new = set(rng.sample(sorted(frequent), 5))
    df = spark.createDataFrame([(0, list(p), p in new) for p in frequent], "batch_id long, nodes array<string>, is_new boolean")
    assert {tuple(r.nodes) for r in L.join_candidates_df(df).collect()} == L.join_candidates(frequent, new)


def test_guard_raises_the_threshold():
    rng = random.Random(2)
    params = MineParams(m=2, k=3, ell=3, delta=5.0, max_candidates=20)
    prev = None
    for s in range(3):
        prev, stats = L.advance(prev, counter(rng.choices("abcdef", k=120)), [(x,) for x in "abcdef"], params.with_(max_candidates=400 if s == 0 else 20), lambda d: 40 * d, L.delta_rule(params), s)
        assert stats.capped == (s > 0)
    assert all(len(f) + len(b) <= 20 for f, b in zip(prev.frequent, prev.border))


def test_joins_beyond_the_guard_are_not_made():
    many = {(str(x),) for x in range(20_000)}
    with pytest.raises(OverflowError):
        L.join_candidates(many, most=10**6)  # 4 * 10**8 of them
    with pytest.raises(OverflowError):
        L.join_candidates(many, {("7",)}, most=39_998)
    assert len(L.join_candidates(many, {("7",)}, most=39_999)) == 39_999


def test_a_short_batch_takes_the_deepest_affordable_threshold():
    """Where a batch holds fewer events, the drift reaches below one occurrence; the guard's threshold is found without counting all pairs."""
    rng = random.Random(5)
    letters = [f"s{i}" for i in range(40)]
    params = MineParams(m=2, k=3, ell=3, max_candidates=2000)
    long, short = rng.choices(letters, k=4000), rng.choices(letters, k=400)
    symbols = [(x,) for x in letters]
    theta, delta = (lambda d: 2 * d), L.delta_rule(params)
    prev, _ = L.advance(None, counter(long), symbols, params, theta, delta, 0)
    lattice, stats = L.advance(prev, counter(short), symbols, params, theta, delta, 1)
    affordable, f = [], 1
    while f < 400:
        try:
            affordable.append((f, L.mine_batch(L.Memo(counter(short)), symbols, 3, f, max_candidates=2000)))
        except OverflowError:
            pass
        f = math.ceil(f * 1.25)
    f_min, want = affordable[0]
    assert f_min > 2 and stats.capped and stats.f_min == f_min and stats.n_counted < 1600
    assert (lattice.frequent, lattice.border) == (want.frequent, want.border)


@pytest.mark.parametrize("klass,relation,repeats", [("serial", "contig", True), ("serial", "subseq", True), ("serial", "contig", False), ("parallel", "contig", True), ("itemset", "contig", True)])
def test_the_k_best_are_whole_beyond_the_guard(klass, relation, repeats):
    """Levels may hold fewer candidates than the k best need; these are found nevertheless, with all ties."""
    rng = random.Random(8)
    letters = [f"s{i}" for i in range(9)]
    ticks = [rng.sample(letters, 4) for _ in range(60)] if klass == "itemset" else rng.choices(letters, k=400)

    def count(patterns):
        if klass == "serial":
            return counter(ticks)(patterns)
        if klass == "itemset":
            return {p: sum(set(p) <= set(t) for t in ticks) for p in patterns}
        out = {}
        for p in patterns:
            need, n = list(p), 0
            for y in ticks:
                if y in need:
                    need.remove(y)
                if not need:
                    need, n = list(p), n + 1
            out[p] = n
        return out

    every = itertools.product(letters, repeat=3) if klass == "serial" else itertools.combinations_with_replacement(letters, 3)
    every = count([p for p in every if (repeats and klass != "itemset") or len(set(p)) == 3])
    for most, k in ((60, 40), (8, 40), (60, 10_000), (8, 1)):
        params = MineParams(m=2, k=k, ell=3, klass=klass, relation=relation, repeats=repeats, max_candidates=most)
        with pytest.raises(OverflowError):
            L.mine_batch(L.Memo(count), {(x,) for x in letters}, 3, L.kth(every.values(), k), klass, relation, repeats, most)
        memo = L.Memo(count)
        lattice, fk = L.mine_topk(memo, [(x,) for x in letters], k, 3, params)
        assert fk == L.kth(every.values(), k)
        assert {p: c for p, c in lattice.top().items() if c >= fk} == {p: c for p, c in every.items() if c >= fk}


def test_window_truth_is_whole_beyond_the_guard():
    data, symbols = stream(), [(x,) for x in "abcde"]
    counters = {s: counter(seq) for s, seq in data.items()}
    for run in (L.window_recount, lambda *x: L.union_variants(*x, sticky=True)):
        whole, guarded = (run(counters, symbols, MineParams(m=4, k=30, ell=3, max_candidates=most)) for most in (2_000_000, 24))
        assert sorted(guarded.topk) == sorted(whole.topk) and whole.topk
        assert [s.fk for s in guarded.stats] == [s.fk for s in whole.stats]


def stream(seed=4, batches=9, letters="abcde", size=70):
    rng = random.Random(seed)
    weights = [rng.random() + 0.2 for _ in letters]
    out = {}
    for s in range(batches):
        weights = [max(0.1, w + rng.uniform(-0.1, 0.1)) for w in weights]
        out[s] = rng.choices(letters, weights, k=size)
    return out


@pytest.mark.parametrize("name,v", [("lookahead", None), ("persistent_depth", 2.0), ("heuristic_depth", 3.0)])
def test_lattice_runs_equal_the_closed_forms(spark, name, v):
    data, params = stream(), MineParams(m=4, k=5, ell=3, delta=1.0)
    symbols = [(x,) for x in "abcde"]
    spec = VariantSpec(name, v)
    run = L.run_variant({s: counter(x) for s, x in data.items()}, symbols, spec, params)
    rows = [(s, ">".join(p), n) for s, x in data.items() for p, n in counter(x)(list(itertools.product("abcde", repeat=3))).items() if n]
    m = spark.createDataFrame(rows, "batch_id long, key string, freq long").cache()
    want = {(r.window_end, r.key, r.wfreq, r["rank"]) for r in variants.report(m, spec, 4, 5, 1.0, 0, 8).collect()}
    assert set(run.topk) == want
    for sticky, union in ((False, "batch_union"), (True, "sticky_union")):
        got = L.union_variants({s: counter(x) for s, x in data.items()}, symbols, params, sticky).topk
        assert set(got) == {(r.window_end, r.key, r.wfreq, r["rank"]) for r in variants.report(m, VariantSpec(union), 4, 5, 1.0, 0, 8).collect()}
    truth = {(r.window_end, r.key, r.wfreq, r["rank"]) for r in window.window_truth(m, 4, 5, 0, 8).collect()}
    assert set(L.window_recount({s: counter(x) for s, x in data.items()}, symbols, params).topk) == truth
    delta = max(abs(a - b) for p in {k for _, k, _ in rows} for a, b in zip(*[[dict(((s, k), n) for s, k, n in rows).get((s + i, p), 0) for s in range(8)] for i in (0, 1)]))
    assert set(L.run_variant({s: counter(x) for s, x in data.items()}, symbols, VariantSpec("exact_depth"), params.with_(delta=float(delta))).topk) == truth


def test_sticky_has_the_same_candidates_and_no_smaller_counts():
    data, params = stream(8), MineParams(m=3, k=4, ell=2, delta=1.0)
    symbols = [(x,) for x in "abcde"]
    plain, sticky = (L.union_variants({s: counter(x) for s, x in data.items()}, symbols, params.with_(k=1000 if wide else 4), st).topk for st, wide in ((False, False), (True, False)))
    best = {}
    for s, key, n, _ in sticky:
        best[s, key] = n
    for s, key, n, _ in plain:
        assert best.get((s, key), n) >= n or (s, key) not in best


def test_missing_counts_as_interval():
    data, params = stream(9), MineParams(m=4, k=3, ell=3, delta=1.0)
    run = L.run_variant({s: counter(x) for s, x in data.items()}, [(x,) for x in "abcde"], VariantSpec("lookahead"), params)
    for s, key, _, _ in run.topk:
        low, high = L.interval(run, params, key, s)
        true = sum(counter(data[j])([tuple(key.split(">"))])[tuple(key.split(">"))] for j in range(s - 3, s + 1))
        assert low <= true <= high


EX1 = {"ABCD": [9, 10, 8, 8], "MNOP": [9, 9, 8, 8], "EFGH": [1, 12, 12, 0], "WXYZ": [12, 1, 11, 0], "IJKL": [0, 12, 0, 11], "PQRS": [10, 0, 0, 9]}


def test_batch_tops_miss_the_window_top(spark):
    m = spark.createDataFrame([(b, k, n) for k, x in EX1.items() for b, n in enumerate(x) if n], "batch_id long, key string, freq long")
    truth = window.window_truth(m, 4, 2, 0, 3)
    assert {(r.key, r.wfreq) for r in truth.collect()} == {("ABCD", 35), ("MNOP", 34)}
    got = variants.report(m, VariantSpec("batch_union"), 4, 2, 1.0, 0, 3)
    assert {(r.key, r.wfreq) for r in got.collect()} == {("EFGH", 24), ("WXYZ", 23), ("IJKL", 23)}
    from pyspark.sql import functions as F

    q = metrics.quality(got.withColumn("variant", F.lit("v")), truth).first()
    assert (q.precision, q.recall) == (0.0, 0.0)


def test_slack_table():
    for m, want in {5: (2, 2.5, 3.4375, 5, 6.25, 8), 10: (2, 5, 6.875, 10, 12.5, 18), 15: (2, 7.5, 10.3125, 15, 18.75, 28)}.items():
        got = (T.slack_lookahead(1), T.slack_persistent(m, 0.75 * m, 1), T.slack_heuristic(m, 0.75 * m, 1), T.slack_persistent(m, 0.5 * m, 1), T.slack_heuristic(m, 0.5 * m, 1), T.slack_exact(m, 1))
        assert got == pytest.approx(want) and list(got) == sorted(got)
    assert T.slack_persistent(10, 1, 3) == T.slack_exact(10, 3) and T.slack_persistent(10, 10, 3) == 0


def test_bounds_table():
    assert T.bound_lower(42, 4, 3, 1) == 40 and T.bound_upper(42, 4, 3, 1) == 54 and T.bound_upper(42, 4, 3, 1, "tight") == 48
    for (m, v, phi), (cond, mu) in {(10, 1, 20): (9, 9.512492), (10, 10, 3): (1, 1), (10, 5, 8): (3, 4), (4, 2, 4): (1.5, 2)}.items():
        assert T.phi_condition(m, v) == cond and T.mu(m, v, phi) == pytest.approx(mu, abs=1e-6)
    assert T.error_bound_special("all", 0.1, 10, 10) == T.error_bound(0.1, 10, 10, 10, 3)


@pytest.mark.parametrize("call", [
    lambda: MineParams(m=0), lambda: MineParams(k=0), lambda: MineParams(ell=0), lambda: MineParams(delta="guess"), lambda: VariantSpec("nothing"), lambda: VariantSpec("persistent_depth"),
    lambda: VariantSpec("persistent_depth", 11.0).checked(10), lambda: T.slack_persistent(10, 0.5, 1), lambda: T.bound_upper(1, 4, 3, 1, "x"),
])
def test_wrong_parameters(call):
    with pytest.raises(ValueError):
        call()


@pytest.mark.parametrize("klass", ["serial", "parallel", "itemset"])
def test_streams_evaluate_every_class_like_brute_force(spark, klass):
    """One task per stream; all methods against closed forms over exhaustive counts, in every pattern class."""
    import pyarrow as pa

    from driftlattice.operators import counting
    from driftlattice.plans import streams

    rng = random.Random(23)
    data = {s: [sorted(set(rng.choices("abcde", [5, 4, 3, 2, 1 + s % 3], k=2))) for _ in range(60)] for s in range(7)}
    params = MineParams(m=3, k=4, ell=2, klass=klass, delta=2.0)
    methods = lambda m: {"window_recount": VariantSpec("window_recount"), "batch_union": VariantSpec("batch_union"), "sticky_union": VariantSpec("sticky_union"), "lookahead": VariantSpec("lookahead"), "heur": VariantSpec("heuristic_depth", 1.5)}
    seqs = spark.createDataFrame([("one", s, x) for s, x in data.items()] + [("two", s, x[::-1]) for s, x in data.items()], "stream_key string, batch_id long, seq array<array<string>>")
    rows = streams.evaluate(seqs, {"one": params, "two": params}, methods).where("kind = 'topk'").collect()
    make = itertools.product("abcde", repeat=2) if klass == "serial" else itertools.combinations_with_replacement("abcde", 2) if klass == "parallel" else itertools.combinations("abcde", 2)
    cands = list(make)
    for key, flip in (("one", 1), ("two", -1)):
        counts = [(s, counting.MARK[klass].join(c), n) for s, x in data.items() for c, n in streams.local_counter(pa.array(x[::flip]), klass)(cands).items() if n]
        m = spark.createDataFrame(counts, "batch_id long, key string, freq long")
        for name, spec in methods(3).items():
            want = {(r.window_end, r.key, r.wfreq, r["rank"]) for r in variants.report(m, spec, 3, 4, 2.0, 0, 6).collect()}
            assert {(r.window_end, r.key, r.wfreq, r["rank"]) for r in rows if r.stream_key == key and r.variant == name} == want, (klass, name)


def test_exact_windows_equal_the_truth():
    data, params = stream(9), MineParams(m=4, k=5, ell=3)
    symbols = [(x,) for x in "abcde"]
    each = {s: counter(x)(list(itertools.product("abcde", repeat=3))) for s, x in data.items()}
    delta = max(abs(each[s][p] - each[s + 1][p]) for s in range(8) for p in each[0])
    for d in (float(delta), 100.0):
        got = L.exact_window_topk({s: counter(x) for s, x in data.items()}, symbols, params, d)
        assert got.topk == L.window_recount({s: counter(x) for s, x in data.items()}, symbols, params).topk


def test_estimated_drift_and_intervals():
    """Drift is the quantile of the changes of patterns tracked in the batch before; unknown counts widen the report."""
    data = stream(9)
    params = MineParams(m=4, k=3, ell=3, delta="estimate", missing="interval", known="frequent")
    run = L.run_variant({s: counter(x) for s, x in data.items()}, [(x,) for x in "abcde"], VariantSpec("lookahead"), params)
    for st in run.stats[1:]:
        before = run.lattices[st.batch_id - 1].top()
        now = counter(data[st.batch_id])(list(before))
        change = sorted(abs(now[p] - n) for p, n in before.items())
        place = 0.75 * (len(change) - 1)
        want = change[int(place)] + (place % 1) * (change[min(int(place) + 1, len(change) - 1)] - change[int(place)])
        assert st.delta == pytest.approx(max(1.0, want)) and st.theta == pytest.approx(2 * st.delta)
    run = L.run_variant({s: counter(x) for s, x in data.items()}, [(x,) for x in "abcde"], VariantSpec("lookahead"), params.with_(delta=0.5, k=12))
    assert run.bounds and any(high > low for _, _, low, high in run.bounds)
    for s, key, low, high in run.bounds:
        p = tuple(key.split(">"))
        assert low <= sum(counter(data[j])([p])[p] for j in range(s - 3, s + 1)) <= high


def test_planted_patterns_are_the_truth(spark, tiny):
    """On a planted stream the recount reports planted episodes, and the deeper methods find them all."""
    from driftlattice.operators import batching
    from driftlattice.plans import streams
    from driftlattice.queries import planted as P

    seqs = batching.sequences(P.planted_frame(spark, tiny, 200, 2, 5, 5)).select(F.lit("x").alias("stream_key"), "batch_id", "seq")
    rows = streams.evaluate(seqs, {"x": MineParams(m=3, k=5, ell=4, delta=1.0)}, P.methods).collect()
    truth = {(r.window_end, r.key) for r in rows if r.kind == "topk" and r.variant == "window_recount"}
    assert truth and {f"p{p}_0>p{p}_1>p{p}_2>p{p}_3" for p in range(5)} & {k for _, k in truth}
    assert all(len({x.split("_")[0] for x in k.split(">")}) == 1 for _, k in truth)
    for name in ("heur_half", "persist_half"):
        assert {(r.window_end, r.key) for r in rows if r.kind == "topk" and r.variant == name} == truth
    cost = {r.variant: r.state_bytes for r in rows if r.kind == "stats"}
    assert cost["window_recount"] > cost["lookahead"] > 0 and cost["batch_union"] > 0
