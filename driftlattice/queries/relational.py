"""Operators, functions and windows that surround the methods (q60 to q81, q83 to q90)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from driftlattice.operators.joins import as_of, interval_join
from driftlattice.sources import adapters

HOUR = 3_600_000_000


def _t(spark, d, *names):
    got = [spark.read.parquet(f"{d}/{n}.parquet") for n in names]
    return got[0] if len(got) == 1 else got


def _day(ts="ts"):
    return F.floor(adapters.micros(F.col(ts)) / F.lit(adapters.DAY)).cast("long").alias("day")


def q60(spark, d):
    x = _t(spark, d, "lineitem").where((F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit("1997-01-01").cast("timestamp_ntz")) & F.col("l_discount").between(0.03, 0.06))
    return x.select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))


def q61(spark, d):
    line, orders, customer, nation, region = _t(spark, d, "lineitem", "orders", "customer", "nation", "region")
    x = line.join(orders, line.l_orderkey == orders.o_orderkey).join(customer, orders.o_custkey == customer.c_custkey).join(nation, customer.c_nationkey == nation.n_nationkey).join(region, nation.n_regionkey == region.r_regionkey)
    return x.groupBy("r_name").agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.count(F.lit(1)).alias("n_lines"))


def q62(spark, d):
    line, part = _t(spark, d, "lineitem", "part")
    return line.join(part.hint("shuffle_hash"), line.l_partkey == part.p_partkey).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n_lines"), F.sum("l_quantity").alias("quantity"))


def q63(spark, d):
    ev = _t(spark, d, "events").select("event_id", "user_id", "event_type", adapters.micros(F.col("ts")).alias("tick"))
    first = ev.agg(F.min("event_type")).first()[0]
    marks = ev.where(F.col("event_type") == first).select("user_id", F.col("tick").alias("mark"))
    return interval_join(ev, marks, ["user_id"], "tick", "mark", 24 * HOUR).select("event_id", "user_id", "mark", "tick")


def q64(spark, d):
    orders = _t(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate", adapters.micros(F.col("o_orderdate")).alias("at"))
    out = as_of(orders, orders, ["o_custkey"], "at", F.col("o_orderdate"), "previous")
    return out.select("o_orderkey", "o_custkey", adapters.micros(F.col("previous")).alias("previous"))


def q65(spark, d):
    customer, orders = _t(spark, d, "customer", "orders")
    key = customer.c_custkey == orders.o_custkey
    some = customer.join(orders, key, "left_semi").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n_with"))
    none = customer.join(orders, key, "left_anti").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n_without"))
    return some.join(none, "c_mktsegment", "full_outer").select("c_mktsegment", F.coalesce("n_with", F.lit(0)).alias("n_with"), F.coalesce("n_without", F.lit(0)).alias("n_without"))


def q66(spark, d):
    n = _t(spark, d, "events").groupBy(_day(), "event_type").agg(F.count(F.lit(1)).alias("n"))
    cur, prev = n.withColumnRenamed("n", "now"), n.select((F.col("day") + 1).alias("day"), "event_type", F.col("n").alias("before"))
    return cur.join(prev, ["day", "event_type"], "full_outer").select("day", "event_type", (F.coalesce("now", F.lit(0)) - F.coalesce("before", F.lit(0))).alias("change"))


def q67(spark, d):
    return _t(spark, d, "events").groupBy(_day()).agg(F.countDistinct("user_id").alias("n_users"), F.countDistinct("event_type").alias("n_types"))


def q67b(spark, d):
    """Approximate distinct users by two sketches: rows only, sketches differ between engines."""
    return _t(spark, d, "events").groupBy(_day()).agg(F.approx_count_distinct("user_id").alias("n_users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("n_users_hll"))


def q68(spark, d):
    _t(spark, d, "events").select(_day(), "event_type").createOrReplaceTempView("dl_day_types")
    return spark.sql("SELECT day, event_type, count(*) AS n, CAST(grouping_id(day, event_type) AS BIGINT) AS level FROM dl_day_types GROUP BY GROUPING SETS ((day, event_type), (day), ())")


def q69(spark, d):
    return _t(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def q70(spark, d):
    return _t(spark, d, "orders").select(F.year("o_orderdate").cast("long").alias("year"), "o_orderstatus").rollup("year", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def q71(spark, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    r = Window.partitionBy("p_brand").orderBy("p_type")
    return _t(spark, d, "part").select(
        "p_partkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(r).cast("long").alias("rk"), F.dense_rank().over(r).cast("long").alias("dr"),
        F.ntile(4).over(w).cast("long").alias("quarter"), F.round(F.percent_rank().over(r), 6).alias("pr"), F.round(F.cume_dist().over(r), 6).alias("cd"),
    )


def q72(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(spark, d, "events").select("event_id", F.timestamp_diff("MICROSECOND", F.col("ts"), F.lead("ts").over(w)).alias("gap"), F.lag("event_type").over(w).alias("before"), F.first("event_type").over(w).alias("first_type"), F.nth_value("event_type", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second_type"))


def q73(spark, d):
    n = _t(spark, d, "events").groupBy(_day()).agg(F.count(F.lit(1)).alias("n"))
    return n.select("day", F.sum("n").over(Window.orderBy("day").rowsBetween(-9, 0)).alias("ten_rows"), F.sum("n").over(Window.orderBy("day").rangeBetween(-9, 0)).alias("ten_days"), F.max("n").over(Window.orderBy("day").rangeBetween(-9, 0)).alias("most"))


def q74(spark, d):
    ev = _t(spark, d, "events").select("user_id", F.floor(adapters.micros(F.col("ts")) / F.lit(7 * adapters.DAY)).alias("week"))
    one, two = (ev.where(F.col("week") == k).select("user_id") for k in (0, 1))
    return one.intersect(two).withColumn("weeks", F.lit("both")).unionByName(one.subtract(two).withColumn("weeks", F.lit("first"))).unionByName(two.subtract(one).withColumn("weeks", F.lit("second")))


def q75(spark, d):
    t = F.col("text")
    return _t(spark, d, "documents").select("doc_id", F.length(F.regexp_replace(t, r"[\x20\x09-\x0D]+", " ")).cast("long").alias("n_normal"), F.size(F.split(t, "\n")).cast("long").alias("n_lines"), F.regexp_extract(t, r"([A-Za-z]+)", 1).alias("first_word"), F.reverse(F.substring(t, 1, 3)).alias("head"), F.levenshtein("lang", "source").cast("long").alias("apart"))


def q76(spark, d):
    ev = _t(spark, d, "events").select(F.concat_ws(":", "event_type", adapters.composite(F.col("props"))).alias("symbol"))
    n = ev.groupBy("symbol").agg(F.count(F.lit(1)).alias("n"))
    return n.orderBy(F.desc("n"), "symbol").limit(25)


def q77(spark, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    square = F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)
    return _t(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(square), 6).alias("norm"), F.round(F.array_max(v), 6).alias("most"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n_positive"))


def q78(spark, d):
    ev = _t(spark, d, "events").select(_day(), "event_type")
    names = [r[0] for r in ev.select("event_type").distinct().orderBy("event_type").limit(5).collect()]
    wide = ev.groupBy("day").pivot("event_type", names).agg(F.count(F.lit(1)))
    return wide.select("day", *[F.coalesce(F.col(f"`{n}`"), F.lit(0)).alias(f"t{k}") for k, n in enumerate(names)])


def q79(spark, d):
    ev = _t(spark, d, "events").select(F.col("user_id"), F.col("ts").cast("timestamp_ntz").alias("ts"))
    s = ev.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("began"))
    return s.select("user_id", adapters.micros(F.col("began")).alias("began"), "n")


def q80(spark, d):
    from driftlattice.functions import episodes as E

    tags = _t(spark, d, "pages").select("page_id", adapters.tag_symbols(F.col("html")).alias("seq"))
    common = tags.select(F.explode("seq").alias("symbol")).groupBy("symbol").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "symbol").limit(5).select("symbol")
    pairs = common.select(F.col("symbol").alias("a")).crossJoin(common.select(F.col("symbol").alias("b"))).select(F.array("a", "b").alias("nodes"))
    f = tags.crossJoin(F.broadcast(pairs)).select(F.array_join("nodes", ">").alias("key"), E.serial_frequency(F.col("seq"), F.col("nodes"), 2).alias("freq"))
    return f.groupBy("key").agg(F.sum("freq").alias("freq"), F.sum((F.col("freq") > 0).cast("long")).alias("n_pages"))


def q81(spark, d):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return _t(spark, d, "lineitem").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("l_suppkey", F.col("rn").cast("long").alias("rn"), "l_orderkey", "l_extendedprice")


def q83(spark, d):
    """Unpivot of the day by type matrix."""
    wide = q78(spark, d)
    return wide.unpivot(["day"], [c for c in wide.columns if c != "day"], "slot", "n").where("n > 0")


def q84(spark, d):
    """Seeded sample by a hash of the key: the same rows in any engine and partitioning."""
    return _t(spark, d, "events").where(F.substring(F.md5(F.col("event_id").cast("string")), 1, 1) == "0").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def q85(spark, d):
    """Maps: symbol to its last position of each day."""
    ev = _t(spark, d, "events").select(_day(), "event_type", adapters.micros(F.col("ts")).alias("tick"))
    last = ev.groupBy("day", "event_type").agg(F.max("tick").alias("last"))
    m = last.groupBy("day").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "last")))).alias("m"))
    return m.select("day", F.explode(F.transform_values("m", lambda k, v: F.col("day") * adapters.DAY + adapters.DAY - v)).alias("event_type", "to_end"))


def q86(spark, d):
    """Sliding windows by the built-in window function: m-fold copies of events, kept for comparison with the ledger's sums."""
    ev = _t(spark, d, "events").select(F.col("ts").cast("timestamp_ntz").alias("ts"), "event_type")
    w = ev.groupBy(F.window("ts", "10 days", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(adapters.micros(F.col("w.start")).alias("start"), "event_type", "n")


QUERIES = {
    "q60_scan_filter_project": q60, "q61_join_equi_star": q61, "q62_join_shuffle_hash": q62, "q63_join_range": q63, "q64_join_asof": q64, "q65_semi_anti": q65, "q66_outer_batch_diff": q66,
    "q67_distinct": q67, "q67b_distinct_approx": q67b, "q68_grouping_sets": q68, "q69_cube": q69, "q70_rollup": q70, "q71_rank_family": q71, "q72_lag_lead_gap": q72, "q73_frames": q73, "q74_set_ops": q74,
    "q75_strings": q75, "q76_json_composite": q76, "q77_arrays": q77, "q78_pivot": q78, "q79_session": q79, "q80_pages_tags": q80, "q81_topn_per_group": q81, "q83_unpivot": q83, "q84_hash_sample": q84,
    "q85_maps": q85, "q86_sliding_window": q86,
}

_TICK = "epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')"
_DAY = f"CAST(floor(({_TICK}) / {adapters.DAY}.0) AS BIGINT)"
_TYPES = "ty AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS k FROM (SELECT DISTINCT event_type FROM events) QUALIFY k < 5)"
_PIVOT = f"WITH {_TYPES}, e AS (SELECT {_DAY} AS day, k FROM events LEFT JOIN ty USING (event_type)) SELECT day, " + ", ".join(f"count(*) FILTER (k = {k}) AS t{k}" for k in range(5)) + " FROM e GROUP BY day"

ORACLES = {
    "q60_scan_filter_project": "SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) AS revenue FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' AND l_discount BETWEEN 0.03 AND 0.06",
    "q61_join_equi_star": "SELECT r_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n_lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    "q62_join_shuffle_hash": "SELECT p_brand, count(*) AS n_lines, sum(l_quantity) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1",
    "q63_join_range": f"WITH e AS (SELECT event_id, user_id, event_type, {_TICK} AS tick FROM events) SELECT e.event_id, e.user_id, m.tick AS mark, e.tick FROM e JOIN e m ON e.user_id = m.user_id AND m.event_type = (SELECT min(event_type) FROM events) AND e.tick > m.tick AND e.tick <= m.tick + {24 * HOUR}",
    "q64_join_asof": "SELECT o_orderkey, o_custkey, epoch_us((SELECT max(p.o_orderdate) FROM orders p WHERE p.o_custkey = o.o_custkey AND p.o_orderdate < o.o_orderdate)) - epoch_us(TIMESTAMP '2024-01-01') AS previous FROM orders o",
    "q65_semi_anti": "SELECT c_mktsegment, count(*) FILTER (EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS n_with, count(*) FILTER (NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS n_without FROM customer GROUP BY 1",
    "q66_outer_batch_diff": f"WITH n AS (SELECT {_DAY} AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT day, event_type, coalesce(a.n, 0) - coalesce(b.n, 0) AS change FROM n a FULL JOIN (SELECT day + 1 AS day, event_type, n FROM n) b USING (day, event_type)",
    "q67_distinct": f"SELECT {_DAY} AS day, count(DISTINCT user_id) AS n_users, count(DISTINCT event_type) AS n_types FROM events GROUP BY 1",
    "q68_grouping_sets": f"WITH e AS (SELECT {_DAY} AS day, event_type FROM events) SELECT day, event_type, count(*) AS n, CAST(grouping(day, event_type) AS BIGINT) AS level FROM e GROUP BY GROUPING SETS ((day, event_type), (day), ())",
    "q69_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "q70_rollup": "SELECT year, o_orderstatus, count(*) AS n FROM (SELECT year(o_orderdate) AS year, o_orderstatus FROM orders) GROUP BY ROLLUP (year, o_orderstatus)",
    "q71_rank_family": """SELECT p_partkey, row_number() OVER w AS rn, rank() OVER r AS rk, dense_rank() OVER r AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER r, 6) AS pr, round(cume_dist() OVER r, 6) AS cd FROM part
WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey), r AS (PARTITION BY p_brand ORDER BY p_type)""",
    "q72_lag_lead_gap": """SELECT event_id, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS gap, lag(event_type) OVER w AS "before", first_value(event_type) OVER w AS first_type,
nth_value(event_type, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "q73_frames": f"WITH n AS (SELECT {_DAY} AS day, count(*) AS n FROM events GROUP BY 1) SELECT day, CAST(sum(n) OVER (ORDER BY day ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS ten_rows, CAST(sum(n) OVER (ORDER BY day RANGE BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS ten_days, max(n) OVER (ORDER BY day RANGE BETWEEN 9 PRECEDING AND CURRENT ROW) AS most FROM n",
    "q74_set_ops": f"WITH e AS (SELECT user_id, floor(({_TICK}) / {7 * adapters.DAY}.0) AS week FROM events), a AS (SELECT DISTINCT user_id FROM e WHERE week = 0), b AS (SELECT DISTINCT user_id FROM e WHERE week = 1) SELECT user_id, 'both' AS weeks FROM (FROM a INTERSECT FROM b) UNION ALL SELECT user_id, 'first' FROM (FROM a EXCEPT FROM b) UNION ALL SELECT user_id, 'second' FROM (FROM b EXCEPT FROM a)",
    "q75_strings": r"SELECT doc_id, length(regexp_replace(text, '[\x20\x09-\x0D]+', ' ', 'g')) AS n_normal, CAST(len(string_split(text, chr(10))) AS BIGINT) AS n_lines, regexp_extract(text, '([A-Za-z]+)', 1) AS first_word, reverse(substr(text, 1, 3)) AS head, levenshtein(lang, source) AS apart FROM documents",
    "q76_json_composite": "SELECT event_type || ':' || json_extract_string(props, '$.k') AS symbol, count(*) AS n FROM events GROUP BY 1 ORDER BY n DESC, symbol LIMIT 25",
    "q77_arrays": "SELECT vec_id, round(sqrt(list_reduce(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)), lambda a, b: a + b)), 6) AS norm, round(CAST(list_max(embedding) AS DOUBLE), 6) AS most, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS n_positive FROM embeddings",
    "q78_pivot": _PIVOT,
    "q79_session": f"WITH g AS (SELECT user_id, {_TICK} AS tick, CASE WHEN ({_TICK}) - lag({_TICK}) OVER (PARTITION BY user_id ORDER BY ts) < {6 * HOUR} THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY tick ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(tick) AS began, count(*) AS n FROM s GROUP BY user_id, k",
    "q80_pages_tags": """WITH t AS (SELECT page_id, list_transform(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1), lambda y: {'t': y, 'n': 0}) AS seq FROM pages),
c AS (SELECT x.t AS s FROM (SELECT unnest(seq) AS x FROM t) GROUP BY 1 ORDER BY count(*) DESC, s LIMIT 5), eps AS (SELECT [a.s, b.s] AS nodes FROM c a, c b),
f AS (SELECT array_to_string(nodes, '>') AS key, coalesce(list_reduce(seq, lambda a, x: {'t': x.t, 'n': a.n + CASE WHEN x.t = nodes[a.n % 2 + 1] THEN 1 ELSE 0 END}, {'t': '', 'n': 0}).n // 2, 0) AS freq FROM t, eps)
SELECT key, CAST(sum(freq) AS BIGINT) AS freq, CAST(sum(CASE WHEN freq > 0 THEN 1 ELSE 0 END) AS BIGINT) AS n_pages FROM f GROUP BY 1""",
    "q81_topn_per_group": "SELECT l_suppkey, rn, l_orderkey, l_extendedprice FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS rn FROM lineitem) WHERE rn <= 3",
    "q83_unpivot": f"SELECT day, slot, n FROM (UNPIVOT ({_PIVOT}) ON t0, t1, t2, t3, t4 INTO NAME slot VALUE n) WHERE n > 0",
    "q84_hash_sample": "SELECT event_type, count(*) AS n FROM events WHERE substr(md5(CAST(event_id AS VARCHAR)), 1, 1) = '0' GROUP BY 1",
    "q85_maps": f"SELECT day, event_type, day * {adapters.DAY} + {adapters.DAY} - max(tick) AS to_end FROM (SELECT {_DAY} AS day, event_type, {_TICK} AS tick FROM events) GROUP BY 1, 2",
    "q86_sliding_window": f"WITH e AS (SELECT {_DAY} AS day, event_type FROM events), s AS (SELECT unnest(range(day - 9, day + 1)) AS w, event_type FROM e) SELECT w * {adapters.DAY} AS start, event_type, count(*) AS n FROM s GROUP BY 1, 2",
}
