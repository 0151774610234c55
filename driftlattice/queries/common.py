"""Shared inputs of the queries, and the SQL fragments of their counterparts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.operators import batching, counting
from driftlattice.sources import adapters
from driftlattice.sources.ledger import once, written

DAY = adapters.DAY
#: Published defaults, and the small fixed drift that lets variants differ on the events table.
M, K, ELL, DELTA = 10, 25, 4, 1.0


def event_batches(spark: SparkSession, sf_dir: str, span: int = DAY) -> DataFrame:
    return adapters.with_batches(adapters.events(spark, sf_dir), span)


def event_seqs(spark: SparkSession, sf_dir: str, span: int = DAY, slices: int = 1) -> DataFrame:
    """Every event is a step of its own; events of one time follow their ids."""
    return batching.sequences(event_batches(spark, sf_dir, span), slices=slices, ties=False)


def event_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_type").alias("symbol")).where("symbol IS NOT NULL").distinct()


def counts(spark: SparkSession, sf_dir: str, span: int = DAY, ell: int = ELL) -> DataFrame:
    """The count matrix of all serial episodes of a size: the ledger that reports are made from."""

    def build():
        cands = counting.enumerate_all(event_symbols(spark, sf_dir), ell)
        return counting.count(event_seqs(spark, sf_dir, span), cands, ell, ties=False).select("batch_id", "key", "freq")

    return once(spark, sf_dir, f"counts-{span}-{ell}", build)


def event_counters(spark: SparkSession, sf_dir: str, span: int = DAY) -> tuple[dict, list]:
    """Counters of all batches of the events table, and its symbols. Every run has its own, so each method's counts come from the table."""
    from driftlattice.plans.lattice import shared_counters

    low, high = days(spark, sf_dir, span)
    seqs = written(event_seqs(spark, sf_dir, span), "batch_id")
    return shared_counters(seqs, range(low, high + 1)), [(r.symbol,) for r in event_symbols(spark, sf_dir).orderBy("symbol").collect()]


def days(spark: SparkSession, sf_dir: str, span: int = DAY) -> tuple[int, int]:
    """First and last batch of the events table, from two scalars."""
    low, high = event_batches(spark, sf_dir, span).agg(F.min("batch_id"), F.max("batch_id")).first()
    return (low or 0), (high if high is not None else -1)


# ---------------------------------------------------------------- SQL fragments


def ev_sql(span: int = DAY, name: str = "ev") -> str:
    return f"""{name} AS (SELECT event_id, event_type, user_id, epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00') AS tick,
  CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / {span}.0) AS BIGINT) AS batch_id FROM events)"""


def moves_sql(seq: str, nodes: str, ell: int, meets: str = "x.t = {n}") -> str:
    """Moves of the serial automaton over a list of {{t, n}} structs."""
    hit = meets.replace("{n}", f"{nodes}[a.n % {ell} + 1]")
    return f"list_reduce({seq}, lambda a, x: {{'t': x.t, 'n': a.n + CASE WHEN {hit} THEN 1 ELSE 0 END}}, {{'t': {seq}[1].t, 'n': 0}}).n"


def eps_sql(ell: int, name: str, symbols: str = "sy") -> str:
    letters = [f"s{i}" for i in range(ell)]
    return f"{name} AS (SELECT [{', '.join(x + '.s' for x in letters)}] AS nodes FROM {', '.join(symbols + ' ' + x for x in letters)})"


def m_sql(ell: int = ELL, span: int = DAY, name: str = "m", zeros: bool = False, ev: str = "ev", base: bool = True) -> str:
    """CTEs up to `name`(batch_id, key, freq), all serial episodes of a size."""
    head = f"""{ev_sql(span, ev)},
{ev}_seqs AS (SELECT batch_id, list({{'t': event_type, 'n': 0}} ORDER BY tick, event_id) AS seq FROM {ev} GROUP BY batch_id),
sy AS (SELECT DISTINCT event_type AS s FROM events WHERE event_type IS NOT NULL),
""" if base else ""
    keep = "" if zeros else " WHERE freq > 0"
    return head + f"""{eps_sql(ell, name + '_eps')},
{name} AS MATERIALIZED (SELECT * FROM (SELECT batch_id, array_to_string(nodes, '>') AS key, nodes, CAST({moves_sql('seq', 'nodes', ell)} // {ell} AS BIGINT) AS freq FROM {ev}_seqs, {name}_eps){keep})"""


def fk_sql(k: int = K, m: str = "m", name: str = "fk") -> str:
    return f"{name} AS (SELECT batch_id, min(freq) AS fk FROM (SELECT *, row_number() OVER (PARTITION BY batch_id ORDER BY freq DESC) AS r FROM {m}) WHERE r <= {k} GROUP BY batch_id)"


def ends_sql(m: int = M, ev: str = "ev", name: str = "ends") -> str:
    """All full windows: (window_end)."""
    return f"{name} AS (SELECT unnest(range(lo + {m} - 1, hi + 1)) AS window_end FROM (SELECT min(batch_id) AS lo, max(batch_id) AS hi FROM {ev}))"


def top_sql(source: str, k: int = K) -> str:
    """SELECT of (window_end, key, wfreq, rank) with ties, over a relation with window_end, key, wfreq."""
    return f"SELECT window_end, key, wfreq, rank FROM (SELECT *, rank() OVER (PARTITION BY window_end ORDER BY wfreq DESC) AS rank FROM {source}) WHERE rank <= {k}"
