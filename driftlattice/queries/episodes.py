"""Counting and level-wise mining (q01 to q15)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftlattice.operators import batching, counting
from driftlattice.params import MineParams, VariantSpec, partial, serial
from driftlattice.plans import lattice, window
from driftlattice.queries.common import DELTA, ELL, K, counts, days, eps_sql, ev_sql, event_batches, event_seqs, event_symbols, fk_sql, m_sql, moves_sql
from driftlattice.sources import adapters
from driftlattice.sources.ledger import written

DIAMOND = partial(["view", "click", "cart", "purchase"], [("view", "click"), ("view", "cart"), ("click", "purchase"), ("cart", "purchase")])


def q01(spark, d):
    return batching.batch_ledger(event_batches(spark, d))


def _serial(ell):
    def run(spark: SparkSession, d: str) -> DataFrame:
        cands = counting.enumerate_all(event_symbols(spark, d), ell)
        return counting.count(event_seqs(spark, d), cands, ell, ties=False).select("batch_id", "key", "freq")

    return run


def q06(spark, d):
    cands = counting.enumerate_all(event_symbols(spark, d), 3, kind="parallel")
    return counting.count(event_seqs(spark, d), cands, 3, "parallel", ties=False).select("batch_id", "key", "freq")


def _four(spark, d):
    """The four first event types in name order stand for the diamond's labels."""
    return [r.symbol for r in event_symbols(spark, d).orderBy("symbol").limit(4).collect()]


def q07(spark, d):
    a, b, c, e = _four(spark, d)
    spec = partial([a, b, c, e], [(a, b), (a, c), (b, e), (c, e)])
    return counting.count_partial(event_seqs(spark, d), spec, ties=False).select("batch_id", F.concat_ws(",", *[F.lit(x) for x in (a, b, c, e)]).alias("key"), "freq")


def q08(spark, d):
    rows = spark.read.parquet(f"{d}/lineitem.parquet")
    frame = adapters.with_batches(adapters.adapt(rows, F.col("l_shipdate"), F.col("l_returnflag"), origin="1995-01-01 00:00:00"), 30 * adapters.DAY)
    flags = rows.select(F.col("l_returnflag").alias("symbol")).distinct()
    return counting.count_serial(batching.sequences(frame), counting.enumerate_all(flags, 3), 3).select("batch_id", "key", "freq")


def q09(spark, d):
    names = _four(spark, d)[:3]
    ticks = batching.to_ticks(event_batches(spark, d)).groupBy("batch_id").agg(F.array_sort(F.collect_list(F.struct("tick", "symbols"))).alias("ticks"))
    return counting.occurrences(ticks, serial(">".join(names)))


def q10(spark, d):
    cands = counting.enumerate_all(event_symbols(spark, d), 3)
    seqs = event_seqs(spark, d)
    carried = counting.count_carried(seqs, cands, 3, ties=False).groupBy("key").agg(F.sum("freq").alias("carried"))
    reset = counting.count_serial(seqs, cands, 3, ties=False).groupBy("key").agg(F.sum("freq").alias("reset"))
    return carried.join(reset, "key", "left").select("key", "carried", F.coalesce("reset", F.lit(0)).alias("reset"))


def q11(spark, d):
    cands = counting.enumerate_all(event_symbols(spark, d), ELL)
    return counting.count_segmented(event_seqs(spark, d, slices=8), cands, ELL, ties=False).select("batch_id", "key", "freq")


def q12(spark, d):
    m = counts(spark, d)
    return window.topk_with_ties(m, K, "batch_id").join(F.broadcast(window.kth_frequency(m, K)), "batch_id").select("batch_id", "key", "freq", "rank", "fk")


def _mined(spark, d):
    fk = window.kth_frequency(counts(spark, d), K).select("batch_id", F.greatest(F.lit(1), F.col("fk") - 2).alias("f_min"))
    return lattice.mine_batches(event_seqs(spark, d), event_symbols(spark, d), fk, ELL)


def q13(spark, d):
    return _mined(spark, d).where("status = 'F'").select("batch_id", "size", "key", "freq")


def q14(spark, d):
    return _mined(spark, d).where("status = 'B'").select("batch_id", "size", "key", "freq")


def incremental(spark: SparkSession, d: str, spec: VariantSpec = VariantSpec("lookahead"), params: MineParams = MineParams(delta=DELTA), last: int | None = None):
    """The incremental lattice over all batches of the events table (optionally up to one)."""
    low, high = days(spark, d)
    seqs = written(event_seqs(spark, d, params.span), "batch_id")
    symbols = [(r.symbol,) for r in event_symbols(spark, d).collect()]
    batches = range(low, (high if last is None else min(high, last)) + 1)
    return lattice.run_variant({s: lattice.spark_counter(seqs, s) for s in batches}, symbols, spec, params)


def q15(spark, d):
    result = incremental(spark, d)
    rows = []
    for s, lat in result.lattices.items():
        for size, (f, b, n) in enumerate(zip(lat.frequent, lat.border, lat.new), 1):
            rows += [(s, size, ">".join(p), c, "F", p in n) for p, c in f.items()] + [(s, size, ">".join(p), c, "B", False) for p, c in b.items()]
    return spark.createDataFrame(rows, "batch_id long, size long, key string, freq long, status string, is_new boolean")


QUERIES = {
    "q01_batch_ledger": q01, "q02_serial_l1": _serial(1), "q03_serial_l2": _serial(2), "q04_serial_l3": _serial(3), "q05_serial_l4": _serial(4), "q06_parallel_l3": q06,
    "q07_partial_diamond": q07, "q08_serial_ties": q08, "q09_occurrences": q09, "q10_boundary_carry": q10, "q11_segmented_count": q11, "q12_batch_topk": q12,
    "q13_mine_threshold": q13, "q14_border": q14, "q15_incremental_lattice": q15,
}

_SEQS = f"{ev_sql()}, ev_seqs AS (SELECT batch_id, list({{'t': event_type, 'n': 0}} ORDER BY tick, event_id) AS seq FROM ev GROUP BY batch_id), sy AS (SELECT DISTINCT event_type AS s FROM events WHERE event_type IS NOT NULL)"


def _serial_sql(ell):
    return f"WITH {m_sql(ell)} SELECT batch_id, key, freq FROM m"


_PARALLEL = """list_reduce(seq, lambda a, x: {'t': x.t, 'n': CASE
  WHEN x.t = nodes[1] AND a.n % 2 = 0 THEN CASE WHEN a.n % 8 = 6 THEN (a.n // 8 + 1) * 8 ELSE a.n + 1 END
  WHEN x.t = nodes[2] AND (a.n // 2) % 2 = 0 THEN CASE WHEN a.n % 8 = 5 THEN (a.n // 8 + 1) * 8 ELSE a.n + 2 END
  WHEN x.t = nodes[3] AND (a.n // 4) % 2 = 0 THEN CASE WHEN a.n % 8 = 3 THEN (a.n // 8 + 1) * 8 ELSE a.n + 4 END
  ELSE a.n END}, {'t': '', 'n': 0}).n // 8"""
_DIAMOND = """list_reduce(seq, lambda a, x: {'t': x.t, 'n': CASE
  WHEN x.t = l[1] AND a.n % 8 = 0 THEN a.n + 1
  WHEN x.t = l[2] AND a.n % 2 = 1 AND (a.n // 2) % 2 = 0 THEN a.n + 2
  WHEN x.t = l[3] AND a.n % 2 = 1 AND (a.n // 4) % 2 = 0 THEN a.n + 4
  WHEN x.t = l[4] AND a.n % 8 = 7 THEN (a.n // 8 + 1) * 8
  ELSE a.n END}, {'t': '', 'n': 0}).n // 8"""
_SIZES = ",\n".join(m_sql(e, name=f"m{e}", zeros=True, base=e == 1) for e in range(1, 5))
_ALL = f"""{_SIZES},
f4 AS (SELECT * FROM m4 WHERE freq > 0), {fk_sql(m='f4')},
al AS (SELECT 1 AS size, * FROM m1 UNION ALL SELECT 2, * FROM m2 UNION ALL SELECT 3, * FROM m3 UNION ALL SELECT 4, * FROM m4),
lat AS (SELECT al.*, freq >= greatest(1, fk - 2) AS f FROM al JOIN fk USING (batch_id)),
lt AS (SELECT a.batch_id, a.size, a.key, a.freq, a.f FROM lat a WHERE a.size = 1 OR
  ((SELECT p.f FROM lat p WHERE p.batch_id = a.batch_id AND p.size = a.size - 1 AND p.key = array_to_string(a.nodes[2:], '>')) AND
   (SELECT p.f FROM lat p WHERE p.batch_id = a.batch_id AND p.size = a.size - 1 AND p.key = array_to_string(a.nodes[:a.size - 1], '>'))))"""

ORACLES = {
    "q01_batch_ledger": f"WITH {ev_sql()} SELECT batch_id, count(*) AS n_events, count(DISTINCT event_type) AS n_symbols, min(tick) AS first_tick, max(tick) AS last_tick FROM ev GROUP BY batch_id",
    "q02_serial_l1": _serial_sql(1), "q03_serial_l2": _serial_sql(2), "q04_serial_l3": _serial_sql(3), "q05_serial_l4": _serial_sql(4),
    "q06_parallel_l3": f"WITH {_SEQS}, eps AS (SELECT [a.s, b.s, c.s] AS nodes FROM sy a JOIN sy b ON b.s >= a.s JOIN sy c ON c.s >= b.s) SELECT * FROM (SELECT batch_id, array_to_string(nodes, '+') AS key, CAST({_PARALLEL} AS BIGINT) AS freq FROM ev_seqs, eps) WHERE freq > 0",
    "q07_partial_diamond": f"WITH {_SEQS}, lab AS (SELECT list(s ORDER BY s)[:4] AS l FROM sy) SELECT batch_id, array_to_string(l, ',') AS key, CAST({_DIAMOND} AS BIGINT) AS freq FROM ev_seqs, lab",
    "q08_serial_ties": f"""WITH ticks AS (SELECT CAST(floor((epoch_us(l_shipdate) - epoch_us(TIMESTAMP '1995-01-01')) / {30 * adapters.DAY}.0) AS BIGINT) AS batch_id, l_shipdate AS tick, list(DISTINCT l_returnflag) AS t FROM lineitem GROUP BY 1, 2),
seqs AS (SELECT batch_id, list({{'t': t, 'n': 0}} ORDER BY tick) AS seq FROM ticks GROUP BY batch_id), sy AS (SELECT DISTINCT l_returnflag AS s FROM lineitem), {eps_sql(3, 'eps')}
SELECT * FROM (SELECT batch_id, array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', 3, 'list_contains(x.t, {n})')} // 3 AS BIGINT) AS freq FROM seqs, eps) WHERE freq > 0""",
    "q09_occurrences": f"""WITH RECURSIVE {ev_sql()}, lab AS (SELECT list(s ORDER BY s)[:3] AS l FROM (SELECT DISTINCT event_type AS s FROM events)),
walk(batch_id, n, tick) AS (
  SELECT batch_id, CAST(0 AS BIGINT), CAST(-9223372036854775807 AS BIGINT) FROM ev GROUP BY batch_id
  UNION ALL
  SELECT w.batch_id, w.n + 1, min(e.tick) FROM walk w, lab, ev e WHERE e.batch_id = w.batch_id AND e.event_type = l[w.n % 3 + 1] AND e.tick > w.tick GROUP BY w.batch_id, w.n),
whole AS (SELECT batch_id, max(n) // 3 * 3 AS n FROM walk GROUP BY batch_id)
SELECT w.batch_id, (w.n - 1) // 3 AS occ_no, (w.n - 1) % 3 AS node, w.tick FROM walk w JOIN whole h ON w.batch_id = h.batch_id AND w.n BETWEEN 1 AND h.n""",
    "q10_boundary_carry": f"""WITH {m_sql(3)}, one AS (SELECT list({{'t': event_type, 'n': 0}} ORDER BY tick, event_id) AS seq FROM ev),
c AS (SELECT array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', 3)} // 3 AS BIGINT) AS carried FROM one, m_eps)
SELECT c.key, carried, CAST(coalesce((SELECT sum(freq) FROM m WHERE m.key = c.key), 0) AS BIGINT) AS reset FROM c""",
    "q11_segmented_count": _serial_sql(4),
    "q12_batch_topk": f"WITH {m_sql()}, {fk_sql()} SELECT batch_id, key, freq, rank, fk FROM (SELECT *, rank() OVER (PARTITION BY batch_id ORDER BY freq DESC) AS rank FROM m) JOIN fk USING (batch_id) WHERE rank <= {K}",
    "q13_mine_threshold": f"WITH {_ALL} SELECT batch_id, CAST(size AS BIGINT) AS size, key, freq FROM lt WHERE f",
    "q14_border": f"WITH {_ALL} SELECT batch_id, CAST(size AS BIGINT) AS size, key, freq FROM lt WHERE NOT f",
    "q15_incremental_lattice": f"WITH {_ALL} SELECT a.batch_id, CAST(a.size AS BIGINT) AS size, a.key, a.freq, CASE WHEN a.f THEN 'F' ELSE 'B' END AS status, a.f AND NOT coalesce(p.f, false) AS is_new FROM lt a LEFT JOIN lt p ON p.batch_id = a.batch_id - 1 AND p.key = a.key AND p.size = a.size",
}
