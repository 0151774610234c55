"""Queries on tables made of shifted copies, where many events share a time."""

import duckdb
import pytest

from driftlattice.queries import ORACLES, QUERIES


@pytest.fixture(scope="module")
def copies(tiny, tmp_path_factory):
    """Events of the smallest tables three times, with event and user ids shifted and times as they are."""
    folder = tmp_path_factory.mktemp("copies")
    n = duckdb.sql(f"SELECT max(event_id) + 1 FROM '{tiny}/events.parquet'").fetchall()[0][0]
    duckdb.sql(f"COPY (SELECT * REPLACE (event_id + {n} * i AS event_id, user_id + 1500 * i AS user_id) FROM '{tiny}/events.parquet', (SELECT unnest(range(3)) AS i) ORDER BY hash(event_id, i)) TO '{folder}/events.parquet'")
    return str(folder)


def same_as_sql(spark, folder, name):
    df = QUERIES[name](spark, folder)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet'")
    want = con.execute(f"SELECT {', '.join(df.columns)} FROM ({ORACLES[name]})").fetchall()
    return sorted(map(tuple, df.collect())) == sorted(want) and len(want) > 0


@pytest.mark.parametrize("name", ["q02_serial_l1", "q03_serial_l2", "q13_mine_threshold", "q23_lookahead", "q49_stream_replay"])
def test_events_of_one_time_are_steps_of_their_own(spark, copies, name):
    assert same_as_sql(spark, copies, name)


def rows_read(spark):
    """Rows that Spark's tasks have read from files so far."""
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None)
    return sum(stages.apply(i).inputRecords() for i in range(stages.size()))


@pytest.mark.parametrize("name", ["q37_thresholds", "q91_batch_union_run", "q92_sticky_union_run", "q94_persist_half_run", "q95_persist_34_run", "q96_heur_half_run", "q97_heur_34_run"])
def test_each_run_reads_the_table(spark, copies, name):
    """Also when another query has counted everything before."""
    QUERIES["q90_recount_run"](spark, copies).collect()
    n = duckdb.sql(f"SELECT count(*) FROM '{copies}/events.parquet'").fetchall()[0][0]
    before = rows_read(spark)
    assert same_as_sql(spark, copies, name)
    assert rows_read(spark) - before >= n
