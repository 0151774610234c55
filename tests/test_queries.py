"""Queries against DuckDB on the smallest tables, the lemmas on data, and the streams."""

import os

import duckdb
import pytest

from driftlattice.operators import batching
from driftlattice.params import MineParams, VariantSpec
from driftlattice.plans import theory, window
from driftlattice.queries import ORACLES, QUERIES
from driftlattice.queries.common import K, counts, days
from driftlattice.sources import adapters

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = ("q15", "q30", "q46", "q47", "q48", "q54", "q55", "q56", "q53")


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return c


def plain(x):
    return None if x is None or x != x else float(x) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)


@pytest.mark.parametrize("name", [n for n in ORACLES if not n.startswith(SLOW)])
def test_query_equals_sql(spark, tiny, duck, name):
    df = QUERIES[name](spark, tiny)
    cols = sorted(df.columns)
    want = duck.execute(ORACLES[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == cols
    order = [names.index(c) for c in cols]
    left = sorted(repr([plain(v) for v in (r[c] for c in cols)]) for r in df.collect())
    right = sorted(repr([plain(r[i]) for i in order]) for r in want.fetchall())
    assert left == right


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)


def test_lemmas_hold_on_data(spark, tiny):
    m, (lo, hi) = counts(spark, tiny), days(spark, tiny)
    assert theory.fk_drift(m, K, lo, hi).where("residual < 0").count() == 0
    drift = theory.rank_drift(m, K, lo, hi).collect()
    assert all(r.residual_in >= 0 and r.residual_out > 0 for r in drift if r.residual_out is not None)
    assert theory.bounds(m, K, 10, lo, hi).where("seen_min < lower OR seen_max > upper_tight").count() == 0


def test_window_group_limit_reaches_the_shuffle(spark, tiny):
    plan = window.topk_with_ties(counts(spark, tiny), K, "batch_id")._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan


def test_scan_is_pruned(spark, tiny):
    plan = QUERIES["q60_scan_filter_project"](spark, tiny)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "l_comment" not in plan


def test_stream_miner_equals_a_bounded_run(spark, tmp_path):
    import random

    from driftlattice.plans import lattice as L
    from driftlattice.streaming.miner import EventLedger, StreamMiner, run_available

    rng = random.Random(7)
    span = 1_000_000
    rows = [("all", None, b * span + t, rng.choice("abc")) for b in range(5) for t in sorted(rng.sample(range(span), 30))]
    folder = str(tmp_path / "in")
    for k in range(3):
        spark.createDataFrame(rows[k * 50 : (k + 1) * 50], adapters.EVENT_FRAME).coalesce(1).write.mode("append").parquet(folder)
    params = MineParams(batch_seconds=1, m=2, k=3, ell=2, delta=1.0, missing="interval")
    miner = StreamMiner(spark, VariantSpec("lookahead"), params, lateness=span, ledger=EventLedger(spark, str(tmp_path / "ledger")))
    stream = spark.readStream.schema(adapters.EVENT_FRAME).option("maxFilesPerTrigger", 1).parquet(folder)
    run_available(stream, miner, str(tmp_path / "checkpoint"))
    got = miner.finish()
    seqs = batching.sequences(adapters.with_batches(spark.createDataFrame(rows, adapters.EVENT_FRAME), span))
    want = L.run_variant({s: L.spark_counter(seqs, s) for s in range(5)}, [(x,) for x in "abc"], VariantSpec("lookahead"), params)
    assert miner.late_events == 0 and want.topk
    assert set(got.topk) == set(want.topk) and set(got.bounds) == set(want.bounds)
    kept = {(r.window_end, r.key, r.wfreq, r["rank"]) for r in miner.ledger.reports().collect()}
    assert kept == set(want.topk)


def test_late_events_are_set_aside_or_reopen(spark, tmp_path):
    from driftlattice.streaming.miner import EventLedger, StreamMiner

    frame = lambda ticks: spark.createDataFrame([("all", None, t, "a") for t in ticks], adapters.EVENT_FRAME)
    params = MineParams(batch_seconds=1e-5, m=1, k=1, ell=1, delta=1.0)
    for policy, want in (("drop", {0: 2, 1: 1}), ("reopen", {0: 3, 1: 1})):
        miner = StreamMiner(spark, VariantSpec("lookahead"), params, policy=policy, ledger=EventLedger(spark, str(tmp_path / policy)))
        for epoch, ticks in enumerate(([1, 4, 12], [21], [7])):
            miner(frame(ticks), epoch)
        got = {s: n for s, _, n, _ in miner.finish().topk}
        assert {s: got[s] for s in want} == want
        assert miner.late_events == (1 if policy == "drop" else 0)


def test_keyed_streams(spark, tmp_path):
    from driftlattice.streaming.miner import keyed_counts

    rows = [(k, None, t, x) for k, text in (("u", "ABAB"), ("w", "BA")) for t, x in enumerate(text)]
    folder = str(tmp_path / "in")
    spark.createDataFrame(rows, adapters.EVENT_FRAME).coalesce(1).write.parquet(folder)
    stream = keyed_counts(spark.readStream.schema(adapters.EVENT_FRAME).parquet(folder), [("A", "B"), ("B", "A")])
    query = stream.writeStream.format("memory").queryName("keyed").outputMode("update").trigger(availableNow=True).start()
    query.awaitTermination()
    assert {(r.stream_key, r.key, r.freq) for r in spark.table("keyed").collect()} == {("u", "A>B", 2), ("u", "B>A", 1), ("w", "A>B", 0), ("w", "B>A", 1)}


def test_poisson_stream_is_seeded(spark):
    make = lambda: adapters.poisson_stream(spark, 20, 0.2, [[1, 2, 3]], 3, 50.0)
    a, b = (sorted((r.tick, r.symbol) for r in make().collect()) for _ in range(2))
    assert a == b and a


def test_folder_exists(tiny):
    assert os.path.isdir(tiny)
