from driftlattice import sqlapi
from driftlattice.plans import window
from driftlattice.queries.common import counts, event_batches


def test_table_function_equals_the_plan(spark, tiny):
    sqlapi.register_functions(spark)
    event_batches(spark, tiny).select("batch_id", "tick", "symbol").where("batch_id < 3").createOrReplaceTempView("dl_events")
    got = spark.sql("SELECT * FROM mine_episodes(5, 2, TABLE(SELECT * FROM dl_events) PARTITION BY batch_id ORDER BY tick)").collect()
    m = counts(spark, tiny, ell=2).where("batch_id < 3")
    want = {(r.batch_id, r.key, r.freq) for r in window.topk_with_ties(m, 5, "batch_id").collect()}
    assert {(r.batch_id, r.key, r.freq) for r in got} == want


def test_views(spark, tiny):
    sqlapi.register_views(counts(spark, tiny), 10, 25, 1.0)
    assert spark.sql("SELECT count(*) FROM window_topk JOIN window_truth USING (window_end, key)").first()[0] > 0
    assert spark.table("batch_topk").columns == ["batch_id", "key", "freq", "rank"]


def test_aggregate_counts_like_the_automaton(spark):
    from driftlattice.sqlapi import register_functions

    register_functions(spark)
    rows = [("u", t, x) for t, x in enumerate("ABCABXC")] + [("w", 1, "A"), ("w", 1, "B"), ("w", 0, "B"), ("w", 2, "B"), ("w", None, "A"), ("w", 3, None)]
    spark.createDataFrame(rows, "k string, tick long, symbol string").repartition(3).createOrReplaceTempView("ev_agg")
    got = {r.k: (r.ab, r.abc, r.a) for r in spark.sql("SELECT k, nonoverlap_count(tick, symbol, 'A>B') AS ab, nonoverlap_count(tick, symbol, 'A>B>C') AS abc, nonoverlap_count(tick, symbol, 'A') AS a FROM ev_agg GROUP BY k").collect()}
    assert got == {"u": (2, 2, 2), "w": (1, 0, 1)}


def test_event_files(spark, tmp_path):
    import pytest

    from driftlattice.sources.adapters import event_files

    (tmp_path / "a.csv").write_text("2024-01-01 00:00:01,A,u\n2024-01-01 00:00:02,B,w\n")
    (tmp_path / "a.json").write_text('{"ts": "2024-01-01T00:00:01", "symbol": "A", "key": "u"}\n{"ts": "2024-01-01T00:00:02", "symbol": "B", "key": "w"}\n')
    (tmp_path / "bad.csv").write_text("2024-01-01 00:00:01,,u\n")
    want = [("u", 1_000_000, "A"), ("w", 2_000_000, "B")]
    for kind in ("csv", "json"):
        assert sorted((r.stream_key, r.tick, r.symbol) for r in event_files(spark, str(tmp_path / f"a.{kind}"), kind, key="key").collect()) == want
    with pytest.raises(Exception):
        event_files(spark, str(tmp_path / "bad.csv"), "csv").collect()
    with pytest.raises(ValueError):
        event_files(spark, "x", "xml")
