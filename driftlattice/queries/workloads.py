"""The methods on other streams made of the given tables (q40 to q45, q82)."""

from __future__ import annotations

from pyspark.sql import functions as F

from driftlattice.operators import batching, counting
from driftlattice.plans import variants, window
from driftlattice.queries.common import DAY, ev_sql, eps_sql, moves_sql
from driftlattice.sources import adapters
from driftlattice.sources.ledger import once, written
from driftlattice.params import MineParams
from driftlattice.queries.windows import _quality_ctes

START = "1995-01-01 00:00:00"


def top_windows(counts, m, k):
    counts = written(counts)
    bounds = window.batch_range(counts)
    lo, hi = bounds or (0, -1)
    return window.window_truth(counts, m, k, lo, hi)


MONTH = 30 * DAY


def baskets(spark, d):
    """(batch_id, l_orderkey, items): the brands of each order, by months of 30 days."""
    line, part, orders = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("lineitem", "part", "orders"))
    items = line.join(part, line.l_partkey == part.p_partkey).join(orders, line.l_orderkey == orders.o_orderkey)
    items = items.select(F.floor(adapters.micros(F.col("o_orderdate"), START) / F.lit(MONTH)).cast("long").alias("batch_id"), "l_orderkey", "p_brand")
    return items.groupBy("batch_id", "l_orderkey").agg(F.sort_array(F.collect_set("p_brand")).alias("items"))


def q40(spark, d):
    return top_windows(counting.itemset_counts(baskets(spark, d), 2), 10, 10)


def measured(spark, d, seqs, name, params):
    """All methods on one stream, by the algorithms; kept for the application."""
    from driftlattice.plans import streams
    from driftlattice.queries.planted import methods

    return once(spark, d, name, lambda: streams.evaluate(seqs.select(F.lit(name).alias("stream_key"), "batch_id", "seq"), {name: params}, methods))


def q40_variants(spark, d):
    """The methods on itemset streams: a basket is a tick, and an itemset occurs in every basket that holds it."""
    from driftlattice.queries.planted import quality_of

    seqs = baskets(spark, d).groupBy("batch_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("l_orderkey", "items"))), lambda x: x["items"]).alias("seq"))
    return quality_of(measured(spark, d, seqs, "baskets", MineParams(m=10, k=10, ell=2, klass="itemset", delta=2.0)))


def q41(spark, d):
    frame = adapters.with_batches(adapters.events(spark, d, key=F.col("user_id")), 7 * DAY)
    seqs = batching.sequences(frame, per=("stream_key", "batch_id"), ties=False)
    symbols = frame.select("symbol").distinct()
    pairs = seqs.crossJoin(F.broadcast(counting.enumerate_all(symbols, 2)))  # as many pairs as symbols squared
    return _summed(pairs, 2, False, "stream_key")


def _summed(pairs, ell, ties, key):
    from driftlattice.functions import episodes as E

    freq = pairs.select(key, F.array_join("nodes", ">").alias("key"), E.serial_frequency(F.col("seq"), F.col("nodes"), ell, ties).alias("freq")).where("freq > 0")
    return freq.groupBy("key").agg(F.sum("freq").alias("freq"), F.countDistinct(key).alias("n_streams"))


def q42(spark, d):
    talk = spark.read.parquet(f"{d}/conversations.parquet")
    frame = adapters.adapt(talk, None, F.col("role"), F.col("conv_id"), tick=F.col("turn")).withColumn("batch_id", F.lit(0).cast("long"))
    seqs = batching.sequences(frame, per=("stream_key", "batch_id"))
    return _summed(seqs.crossJoin(F.broadcast(counting.enumerate_all(frame.select("symbol").distinct(), 2))), 2, True, "stream_key")


GAPS = r"[\x20\x09-\x0D]+"


def q43(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet")
    words = docs.select("doc_id", "lang", F.posexplode(F.split(F.lower("text"), GAPS)).alias("pos", "symbol")).where("symbol <> ''")
    common = words.groupBy("lang", "symbol").agg(F.count(F.lit(1)).alias("n"))
    common = window.topk_with_ties(common, 5, "lang", "n").select("lang", "symbol")
    kept = words.join(F.broadcast(common), ["lang", "symbol"])
    seqs = kept.groupBy("lang", "doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "symbol"))), lambda x: x["symbol"]).alias("seq"))
    pairs = common.select("lang", F.col("symbol").alias("a")).join(common.select("lang", F.col("symbol").alias("b")), "lang").select("lang", F.array("a", "b").alias("nodes"))
    from driftlattice.functions import episodes as E

    freq = seqs.join(F.broadcast(pairs), "lang").select("lang", F.array_join("nodes", ">").alias("key"), E.serial_frequency(F.col("seq"), F.col("nodes"), 2).alias("freq"))
    return freq.groupBy("lang", "key").agg(F.sum("freq").alias("freq")).where("freq > 0")


def supplier_frame(spark, d):
    rows = spark.read.parquet(f"{d}/lineitem.parquet")
    return adapters.with_batches(adapters.adapt(rows, F.col("l_shipdate"), F.col("l_suppkey"), origin=START), MONTH)


def supplier_seqs(spark, d):
    return batching.sequences(supplier_frame(spark, d))


def supplier_counts(spark, d):
    """All pairs of all suppliers in months of 30 days."""

    def build():
        every = spark.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_suppkey").cast("string").alias("symbol")).distinct()
        return counting.count(supplier_seqs(spark, d), counting.enumerate_all(every, 2), 2).select("batch_id", "key", "freq")

    return once(spark, d, "suppliers", build)


def q44(spark, d):
    out = counting.pair_windows(supplier_frame(spark, d), 10, 25)
    return top_windows(supplier_counts(spark, d), 10, 25) if out is None else out


def q44_variants(spark, d):
    """Every method against the recount on the supplier stream, in closed form over the counts of all pairs."""
    from driftlattice.queries.windows import DELTA, q30

    out = variants.pair_quality(supplier_frame(spark, d), 10, 25, DELTA)
    if out is not None:
        return out
    m = supplier_counts(spark, d)
    lo, hi = window.batch_range(m) or (0, -1)
    return q30(m, lo, hi)


def q45(spark, d):
    orders, customer = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("orders", "customer"))
    rows = orders.join(customer, orders.o_custkey == customer.c_custkey)
    frame = adapters.with_batches(adapters.adapt(rows, F.col("o_orderdate"), F.col("o_orderstatus"), F.col("c_mktsegment"), origin=START), 365 * DAY)
    seqs = batching.sequences(frame, per=("stream_key", "batch_id"))
    from driftlattice.functions import episodes as E

    status = orders.select(F.col("o_orderstatus").alias("symbol")).distinct()
    out = seqs.crossJoin(F.broadcast(counting.enumerate_all(status, 2))).select("stream_key", "batch_id", F.array_join("nodes", ">").alias("key"), E.serial_frequency(F.col("seq"), F.col("nodes"), 2, True).alias("freq"))
    return out.where("freq > 0")


def q82(spark, d):
    orders, customer, nation = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("orders", "customer", "nation"))
    rows = orders.join(customer, orders.o_custkey == customer.c_custkey).join(F.broadcast(nation), customer.c_nationkey == nation.n_nationkey)
    frame = adapters.with_batches(adapters.adapt(rows, F.col("o_orderdate"), F.col("n_name"), origin=START), 30 * DAY)
    names = nation.select(F.col("n_name").alias("symbol"))
    return top_windows(counting.count_serial(batching.sequences(frame), counting.enumerate_all(names, 2), 2).select("batch_id", "key", "freq"), 12, 25)


QUERIES = {
    "q40_itemset_topk": q40, "q40b_itemset_variants": q40_variants, "q41_user_streams": q41, "q42_conversations": q42, "q43_doc_tokens": q43, "q44_supplier_stream": q44, "q44b_supplier_variants": q44_variants, "q45_order_status": q45,
    "q82_nation_symbols": q82,
}


def _truth(m: int, k: int) -> str:
    return f"""ends AS (SELECT unnest(range(lo + {m} - 1, hi + 1)) AS window_end FROM (SELECT min(batch_id) AS lo, max(batch_id) AS hi FROM m)),
s AS (SELECT window_end, key, CAST(sum(freq) AS BIGINT) AS wfreq FROM m JOIN ends ON batch_id BETWEEN window_end - {m - 1} AND window_end GROUP BY 1, 2)
SELECT window_end, key, wfreq, rank FROM (SELECT *, rank() OVER (PARTITION BY window_end ORDER BY wfreq DESC) AS rank FROM s) WHERE rank <= {k}"""


def _tie_counts(rows: str, symbols: str, ell: int) -> str:
    """CTEs up to m(batch_id, key, freq) from rows(batch_id, tick, symbol) under the tick rule."""
    return f"""r AS ({rows}), sy AS ({symbols}), tk AS (SELECT batch_id, tick, list(DISTINCT symbol) AS t FROM r WHERE symbol IN (SELECT s FROM sy) GROUP BY 1, 2),
sq AS (SELECT batch_id, list({{'t': t, 'n': 0}} ORDER BY tick) AS seq FROM tk GROUP BY 1), {eps_sql(ell, 'eps')},
m AS MATERIALIZED (SELECT * FROM (SELECT batch_id, array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', ell, 'list_contains(x.t, {n})')} // {ell} AS BIGINT) AS freq FROM sq, eps) WHERE freq > 0)"""


def _batch(column: str, span: int) -> str:
    return f"CAST(floor((epoch_us({column}) - epoch_us(TIMESTAMP '{START}')) / {span}.0) AS BIGINT)"


_BASKETS = f"""it AS (SELECT DISTINCT {_batch('o_orderdate', MONTH)} AS batch_id, l_orderkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey),
m AS MATERIALIZED (SELECT a.batch_id, a.p_brand || '+' || b.p_brand AS key, count(*) AS freq FROM it a JOIN it b ON a.l_orderkey = b.l_orderkey AND a.batch_id = b.batch_id AND a.p_brand < b.p_brand GROUP BY 1, 2)"""
_SUPPLIERS = _tie_counts("SELECT " + _batch("l_shipdate", MONTH) + " AS batch_id, l_shipdate AS tick, CAST(l_suppkey AS VARCHAR) AS symbol FROM lineitem", "SELECT DISTINCT symbol AS s FROM r", 2)
ORACLES = {
    "q40_itemset_topk": f"WITH {_BASKETS}, {_truth(10, 10)}",
    "q40b_itemset_variants": f"WITH {_BASKETS}, {_quality_ctes(10, 10, 2.0, ev='m')} SELECT * FROM qual",
    "q41_user_streams": f"""WITH {ev_sql(7 * DAY)}, sq AS (SELECT user_id, batch_id, list({{'t': event_type, 'n': 0}} ORDER BY tick) AS seq FROM ev GROUP BY 1, 2), sy AS (SELECT DISTINCT event_type AS s FROM events), {eps_sql(2, 'eps')},
f AS (SELECT user_id, array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', 2)} // 2 AS BIGINT) AS freq FROM sq, eps) SELECT key, CAST(sum(freq) AS BIGINT) AS freq, count(DISTINCT user_id) AS n_streams FROM f WHERE freq > 0 GROUP BY key""",
    "q42_conversations": f"""WITH tk AS (SELECT conv_id, turn, list(DISTINCT role) AS t FROM conversations WHERE role IS NOT NULL AND turn IS NOT NULL GROUP BY 1, 2), sq AS (SELECT conv_id, list({{'t': t, 'n': 0}} ORDER BY turn) AS seq FROM tk GROUP BY 1), sy AS (SELECT DISTINCT role AS s FROM conversations WHERE role IS NOT NULL), {eps_sql(2, 'eps')},
f AS (SELECT conv_id, array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', 2, 'list_contains(x.t, {n})')} // 2 AS BIGINT) AS freq FROM sq, eps) SELECT key, CAST(sum(freq) AS BIGINT) AS freq, count(DISTINCT conv_id) AS n_streams FROM f WHERE freq > 0 GROUP BY key""",
    "q43_doc_tokens": rf"""WITH a AS (SELECT doc_id, lang, regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+') AS w FROM documents WHERE text IS NOT NULL),
w AS (SELECT doc_id, lang, unnest(range(len(w))) AS pos, unnest(w) AS symbol FROM a), c AS (SELECT lang, symbol FROM (SELECT lang, symbol, rank() OVER (PARTITION BY lang ORDER BY count(*) DESC) AS r FROM w WHERE symbol <> '' GROUP BY 1, 2) WHERE r <= 5),
sq AS (SELECT lang, doc_id, list({{'t': symbol, 'n': 0}} ORDER BY pos) AS seq FROM w JOIN c USING (lang, symbol) GROUP BY 1, 2), eps AS (SELECT a.lang, [a.symbol, b.symbol] AS nodes FROM c a JOIN c b USING (lang)),
f AS (SELECT lang, array_to_string(nodes, '>') AS key, {moves_sql('seq', 'nodes', 2)} // 2 AS freq FROM sq JOIN eps USING (lang)) SELECT lang, key, CAST(sum(freq) AS BIGINT) AS freq FROM f GROUP BY 1, 2 HAVING sum(freq) > 0""",
    "q44_supplier_stream": f"WITH {_SUPPLIERS}, {_truth(10, 25)}",
    "q44b_supplier_variants": f"WITH {_SUPPLIERS}, {_quality_ctes(ev='m')} SELECT * FROM qual",
    "q45_order_status": f"""WITH tk AS (SELECT c_mktsegment AS k, {_batch('o_orderdate', 365 * DAY)} AS batch_id, o_orderdate AS tick, list(DISTINCT o_orderstatus) AS t FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2, 3),
sq AS (SELECT k, batch_id, list({{'t': t, 'n': 0}} ORDER BY tick) AS seq FROM tk GROUP BY 1, 2), sy AS (SELECT DISTINCT o_orderstatus AS s FROM orders), {eps_sql(2, 'eps')}
SELECT * FROM (SELECT k AS stream_key, batch_id, array_to_string(nodes, '>') AS key, CAST({moves_sql('seq', 'nodes', 2, 'list_contains(x.t, {n})')} // 2 AS BIGINT) AS freq FROM sq, eps) WHERE freq > 0""",
    "q82_nation_symbols": f"WITH {_tie_counts('SELECT ' + _batch('o_orderdate', 30 * DAY) + ' AS batch_id, o_orderdate AS tick, n_name AS symbol FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey', 'SELECT n_name AS s FROM nation', 2)}, {_truth(12, 25)}",
}
