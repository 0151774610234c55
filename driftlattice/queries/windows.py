"""Drift, depth, variants, theory and measures on the events stream (q16 to q37, q46 to q52, q87, q90 to q99)."""

from __future__ import annotations

from pyspark.sql import functions as F

from driftlattice.functions import thresholds as T
from driftlattice.operators import batching
from driftlattice.params import MineParams, VariantSpec
from driftlattice.plans import lattice, metrics, theory, variants, window
from driftlattice.queries.common import DAY, DELTA, ELL, K, M, counts, days, ends_sql, ev_sql, event_counters, fk_sql, m_sql, top_sql
from driftlattice.sources import adapters

PHIS = (1, 2, 3, 5, 8, 10, 20)
VS = (1, 5, 8, 10)
PHI = 20.0
SPECS = {
    "q20_window_truth": VariantSpec("window_recount"), "q21_batch_union": VariantSpec("batch_union"), "q22_sticky_union": VariantSpec("sticky_union"), "q23_lookahead": VariantSpec("lookahead"),
    "q24_persist_half": VariantSpec("persistent_depth", 5.0), "q25_persist_34": VariantSpec("persistent_depth", 7.5), "q26_heur_half": VariantSpec("heuristic_depth", 5.0), "q27_heur_34": VariantSpec("heuristic_depth", 7.5),
}


def _matrix(fn):
    def run(spark, d):
        return fn(counts(spark, d), *days(spark, d))

    return run


def _variant(spec):
    return _matrix(lambda m, lo, hi: variants.report(m, spec, M, K, DELTA, lo, hi))


def q28(spark, d):
    m, (lo, hi) = counts(spark, d), days(spark, d)
    delta = theory.delta_exact(m, lo, hi).agg(F.max("delta")).first()[0] or 0
    return variants.report(m, VariantSpec("exact_depth"), M, K, float(delta), lo, hi)


def q30(m, lo, hi, k=K, win=M, delta=DELTA):
    return metrics.quality(variants.all_reports(m, win, k, delta, lo, hi), window.window_truth(m, win, k, lo, hi)).select("variant", "window_end", "n_pred", "n_true", "precision", "recall")


def q37(m, lo, hi):
    """How deep each variant has to mine each batch, for windows of 5, 10 and 15 batches, given the change that led to the batch."""
    grid = [(win, name, float(T.slack(spec.name, win, spec.v, 1.0))) for win in (5, 10, 15) for name, spec in (variants.line_up(win) | {"exact_depth": VariantSpec("exact_depth")}).items()]
    per = F.explode(F.array(*[F.struct(F.lit(win).cast("long").alias("m"), F.lit(name).alias("variant"), F.lit(unit).alias("unit")) for win, name, unit in grid]))
    out = theory.delta_exact(m, lo, hi).join(window.kth_frequency(m, K), "batch_id").withColumn("x", per).select("batch_id", "fk", F.col("x.m").alias("m"), F.col("x.variant").alias("variant"), (F.col("x.unit") * F.col("delta")).alias("theta"))
    return out.select("batch_id", "m", "variant", "theta", F.greatest(F.lit(1).cast("long"), F.ceil(F.col("fk") - F.col("theta") - 1e-9)).alias("f_min"))


def q46(spark, d):
    m, (lo, hi) = counts(spark, d), days(spark, d)
    out = None
    for win in (5, 10, 15):
        one = metrics.summarize(q30(m, lo, hi, win=win)).select(F.lit(win).cast("long").alias("m"), "variant", "windows", "precision", "recall")
        out = one if out is None else out.unionByName(one)
    return out


#: Batches of 43 minutes to 3 days: a factor of 100.
SPANS = (3 * DAY // 100, 3 * DAY // 10, 3 * DAY)


def q47(spark, d):
    out = None
    for span in SPANS:
        m, (lo, hi) = counts(spark, d, span), days(spark, d, span)
        one = metrics.summarize(q30(m, lo, hi)).select(F.lit(span // 1_000_000).cast("long").alias("batch_seconds"), "variant", "windows", "precision", "recall")
        out = one if out is None else out.unionByName(one)
    return out


def q48(spark, d):
    m, (lo, hi) = counts(spark, d), days(spark, d)
    out = None
    for k in (5, 10, 25, 50):
        one = metrics.summarize(q30(m, lo, hi, k=k)).select(F.lit(k).cast("long").alias("k"), "variant", "windows", "precision", "recall")
        out = one if out is None else out.unionByName(one)
    return out


def q49(spark, d):
    """The events table arrives as a stream of files and is mined batch by batch as batches close."""
    from driftlattice.streaming.miner import StreamMiner, file_stream, run_available

    miner = StreamMiner(spark, VariantSpec("lookahead"), MineParams(delta=DELTA))
    run_available(file_stream(spark, f"{d}/events.parquet*"), lambda df, epoch: miner(adapters.adapt(df, F.col("ts"), F.col("event_type"), place=F.col("event_id")), epoch), f"{miner.ledger.folder}/checkpoint")
    miner.finish()
    return miner.ledger.reports()


def q50(spark, d):
    df = spark.read.parquet(f"{d}/events.parquet")
    frame = df.select(F.col("user_id").cast("string").alias("stream_key"), adapters.micros(F.col("ts")).alias("tick"), ((F.col("event_id") * 7919) % 10007 * 1_000_000 + F.col("event_id")).alias("arrival"))
    late = batching.late_split(frame, 5 * DAY)
    return late.groupBy("stream_key").agg(F.count(F.lit(1)).alias("n_events"), F.sum(F.col("late").cast("long")).alias("n_late"))


def q51(spark, d):
    from driftlattice.queries.episodes import incremental

    stats = incremental(spark, d).stats
    rows = [(s.batch_id, s.fk_seed, s.fk, float(s.delta), float(s.theta), s.f_min, s.passes, s.n_counted, s.n_frequent, s.n_border, s.n_new, s.depth_exhausted, s.capped, metrics.state_bytes(s.n_frequent + s.n_border, ELL)) for s in stats]
    return spark.createDataFrame(rows, "batch_id long, fk_seed long, fk long, delta double, theta double, f_min long, passes long, n_counted long, n_frequent long, n_border long, n_new long, depth_exhausted boolean, capped boolean, state_bytes long")


TOPK = "window_end long, key string, wfreq long, rank long"
#: The algorithms themselves, beside their closed forms above: each has to give the same rows.
RUNS = {
    "q90_recount_run": "q20_window_truth", "q91_batch_union_run": "q21_batch_union", "q92_sticky_union_run": "q22_sticky_union", "q93_lookahead_run": "q23_lookahead",
    "q94_persist_half_run": "q24_persist_half", "q95_persist_34_run": "q25_persist_34", "q96_heur_half_run": "q26_heur_half", "q97_heur_34_run": "q27_heur_34",
}


def _run(spec):
    def run(spark, d):
        counters, symbols = event_counters(spark, d)
        params = MineParams(m=M, k=K, ell=ELL, delta=DELTA)
        if spec.name == "window_recount":
            out = lattice.window_recount(counters, symbols, params)
        elif spec.name in ("batch_union", "sticky_union"):
            out = lattice.union_variants(counters, symbols, params, spec.name == "sticky_union")
        else:
            out = lattice.run_variant(counters, symbols, spec, params)
        return spark.createDataFrame(out.topk, TOPK)

    return run


def q98(spark, d):
    """The exact two-stage algorithm, begun anew with every window, at the largest change that occurs."""
    counters, symbols = event_counters(spark, d)
    m, (lo, hi) = counts(spark, d), days(spark, d)
    delta = theory.delta_exact(m, lo, hi).agg(F.max("delta")).first()[0] or 1
    return spark.createDataFrame(lattice.exact_window_topk(counters, symbols, MineParams(m=M, k=K, ell=ELL, delta=float(delta)), float(delta)).topk, TOPK)


def q99(spark, d):
    """All incremental methods with the drift estimated from the tracked patterns, batch by batch."""
    counters, symbols = event_counters(spark, d)
    rows = []
    for name, spec in variants.line_up(M).items():
        if name not in ("batch_union", "sticky_union"):
            out = lattice.run_variant(counters, symbols, spec, MineParams(m=M, k=K, ell=ELL, delta="estimate", missing="interval"))
            delta = {st.batch_id: float(st.delta) for st in out.stats}
            rows += [(name, w, delta[w], key, low, high) for w, key, low, high in out.bounds]
    return spark.createDataFrame(rows, "variant string, window_end long, delta double, key string, wfreq long, wfreq_hi long")


def q87(m, lo, hi):
    """The corollary's three cases: persistence of one batch, of all, and of half of them."""
    eps = window.spread(theory.separation(m, K, DELTA, [PHI]), M, lo, hi).groupBy("window_end").agg(F.max("eps").alias("eps"))
    cases = F.explode(F.array(*[F.struct(F.lit(case).alias("case"), F.lit(v).cast("long").alias("v"), F.lit(T.error_bound_special(case, 1.0, K, M)).alias("factor")) for case, v in (("one", 1), ("all", M), ("half", (M + 1) // 2))]))
    return eps.withColumn("x", cases).select("window_end", F.col("x.case").alias("case"), F.col("x.v").alias("v"), "eps", F.round(F.col("eps") * F.col("x.factor"), 6).alias("bound"))


QUERIES = {
    "q16_delta_exact": _matrix(theory.delta_exact),
    "q17_delta_p75": _matrix(lambda m, lo, hi: theory.delta_estimate(m, lo, hi).join(theory.delta_estimate(m, lo, hi, population="topk_common", k=K).withColumnRenamed("delta", "delta_topk"), "batch_id", "left")),
    "q18_fk_drift": _matrix(lambda m, lo, hi: theory.fk_drift(m, K, lo, hi)),
    "q19_rank_drift": _matrix(lambda m, lo, hi: theory.rank_drift(m, K, lo, hi)),
    **{name: _variant(spec) for name, spec in SPECS.items()},
    "q28_exact": q28,
    "q29_prev_window": _variant(VariantSpec("previous_window")),
    "q30_precision_recall": _matrix(q30),
    "q31_accuracy_summary": _matrix(lambda m, lo, hi: metrics.summarize(q30(m, lo, hi))),
    "q32_persistent": _matrix(lambda m, lo, hi: theory.persistent_sizes(m, K, M, lo, hi)),
    "q33_bounds": _matrix(lambda m, lo, hi: theory.bounds(m, K, M, lo, hi)),
    "q34_separation": _matrix(lambda m, lo, hi: theory.separation(m, K, DELTA, PHIS)),
    "q35_band_gap": _matrix(lambda m, lo, hi: theory.band_gap(m, K, M, DELTA, 2.0, lo, hi)),
    "q36_error_bound": _matrix(lambda m, lo, hi: theory.error_bounds(m, K, M, DELTA, PHI, lo, hi, VS)),
    "q37_thresholds": _matrix(q37), "q46_m_sweep": q46, "q47_tb_sweep": q47, "q48_k_sweep": q48,
    "q49_stream_replay": q49, "q50_late_events": q50, "q51_cost_counters": q51,
    "q52_mixing": _matrix(lambda m, lo, hi: theory.mixing(m, K, M, VS, DELTA, PHI, lo, hi)),
    "q87_special_cases": _matrix(q87),
    **{name: _run(SPECS[closed]) for name, closed in RUNS.items()},
    "q98_exact_run": q98, "q99_estimated_runs": q99,
}

# ---------------------------------------------------------------- SQL

_CHANGE = """lim AS (SELECT min(batch_id) AS lo, max(batch_id) AS hi FROM ev),
chg AS (SELECT batch_id, key, abs(coalesce(c.freq, 0) - coalesce(p.freq, 0)) AS change FROM (SELECT batch_id, key, freq FROM m) c
  FULL JOIN (SELECT batch_id + 1 AS batch_id, key, freq FROM m) p USING (batch_id, key), lim WHERE batch_id BETWEEN lo + 1 AND hi)"""


def _variant_cte(name: str, theta: float | str, k: int = K, m: int = M, matrix: str = "m") -> str:
    """CTE `name`(window_end, key, wfreq, rank) of a lattice variant in closed form: seeded counts, current candidates."""
    return f"""{name}_f AS (SELECT batch_id, key, freq, freq >= greatest(1, ceil(fk - {theta} - 1e-9)) AS tr FROM {matrix} JOIN fk USING (batch_id)),
{name}_h AS (SELECT *, tr OR coalesce((SELECT p.tr FROM {name}_f p WHERE p.key = f.key AND p.batch_id = f.batch_id - 1), false) AS have FROM {name}_f f),
{name}_s AS (SELECT window_end, key, CAST(sum(CASE WHEN have THEN freq ELSE 0 END) AS BIGINT) AS wfreq FROM {name}_h JOIN ends ON batch_id BETWEEN window_end - {m - 1} AND window_end GROUP BY 1, 2 HAVING bool_or(tr AND batch_id = window_end)),
{name} AS ({top_sql(name + '_s', k)})"""


def _union_cte(name: str, sticky: bool, k: int = K, m: int = M, matrix: str = "m") -> str:
    have = f"max(CAST(hit AS INT)) OVER (PARTITION BY key ORDER BY batch_id RANGE BETWEEN {m} PRECEDING AND CURRENT ROW) = 1" if sticky else "hit"
    return f"""{name}_f AS (SELECT batch_id, key, freq, freq >= fk AS hit FROM {matrix} JOIN fk USING (batch_id)),
{name}_h AS (SELECT *, {have} AS have FROM {name}_f),
{name}_s AS (SELECT window_end, key, CAST(sum(CASE WHEN have THEN freq ELSE 0 END) AS BIGINT) AS wfreq FROM {name}_h JOIN ends ON batch_id BETWEEN window_end - {m - 1} AND window_end GROUP BY 1, 2 HAVING bool_or(hit)),
{name} AS ({top_sql(name + '_s', k)})"""


def _truth_cte(k: int = K, m: int = M, matrix: str = "m") -> str:
    return f"tr_s AS (SELECT window_end, key, CAST(sum(freq) AS BIGINT) AS wfreq FROM {matrix} JOIN ends ON batch_id BETWEEN window_end - {m - 1} AND window_end GROUP BY 1, 2), truth AS ({top_sql('tr_s', k)})"


def _slack(name: str, m: int, delta: float) -> float:
    spec = variants.line_up(m)[name]
    return T.slack(spec.name, m, spec.v, delta)


_LATTICE = ("lookahead", "persist_34", "heur_34", "persist_half", "heur_half")


def _quality_ctes(k: int = K, m: int = M, delta: float = DELTA, matrix: str = "m", ev: str = "ev") -> str:
    parts = [fk_sql(k, matrix), ends_sql(m, ev), _truth_cte(k, m, matrix), _union_cte("batch_union", False, k, m, matrix), _union_cte("sticky_union", True, k, m, matrix)]
    parts += [_variant_cte(n, _slack(n, m, delta), k, m, matrix) for n in _LATTICE]
    parts.append("previous_window AS (SELECT window_end + 1 AS window_end, key, wfreq, rank FROM truth WHERE window_end + 1 <= (SELECT max(window_end) FROM ends))")
    names = ("batch_union", "sticky_union", *_LATTICE, "previous_window")
    parts.append("rep AS (" + " UNION ALL ".join(f"SELECT '{n}' AS variant, * FROM {n}" for n in names) + ")")
    parts.append("""qual AS (SELECT variant, window_end, n_pred, n_true, round(n_common / n_pred, 6) AS precision, round(n_common / n_true, 6) AS recall FROM
  (SELECT r.variant, r.window_end, count(*) AS n_pred, count(t.key) AS n_common FROM rep r LEFT JOIN truth t USING (window_end, key) GROUP BY 1, 2) JOIN (SELECT window_end, count(*) AS n_true FROM truth GROUP BY 1) USING (window_end))""")
    parts.append("summ AS (SELECT variant, count(*) AS windows, round(avg(precision), 4) AS precision, round(avg(recall), 4) AS recall FROM qual GROUP BY variant)")
    return ",\n".join(parts)


_BASE = f"{m_sql()}, {fk_sql()}, {ends_sql()}"
_HITS = f"hits AS (SELECT window_end, key, count(*) AS hits FROM m JOIN fk USING (batch_id) JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end WHERE freq >= fk GROUP BY 1, 2)"
_EPS = f"SELECT batch_id, phi, round(greatest(0.0, sum(CASE WHEN freq >= fk - phi * {DELTA} THEN 1 ELSE 0 END) / {K} - 1), 6) AS eps FROM m JOIN fk USING (batch_id), (SELECT unnest([{', '.join(f'CAST({p} AS DOUBLE)' for p in PHIS)}]) AS phi) GROUP BY 1, 2"
def _sweep(column: str, parts: list[tuple[int, str]]) -> str:
    return " UNION ALL ".join(f"SELECT CAST({value} AS BIGINT) AS {column}, * FROM ({query})" for value, query in parts)


ORACLES = {
    "q16_delta_exact": f"WITH {m_sql()}, {_CHANGE} SELECT batch_id, max(change) AS delta FROM chg GROUP BY 1",
    "q17_delta_p75": f"""WITH {m_sql()}, {fk_sql()}, {_CHANGE}, h AS (SELECT batch_id, key FROM m JOIN fk USING (batch_id) WHERE freq >= fk),
a AS (SELECT batch_id, round(quantile_cont(change, 0.75), 6) AS delta FROM chg GROUP BY 1),
b AS (SELECT c.batch_id, round(quantile_cont(change, 0.75), 6) AS delta_topk FROM chg c JOIN h x ON x.batch_id = c.batch_id AND x.key = c.key JOIN h y ON y.batch_id = c.batch_id - 1 AND y.key = c.key GROUP BY 1)
SELECT a.batch_id, delta, delta_topk FROM a LEFT JOIN b USING (batch_id)""",
    "q18_fk_drift": f"WITH {m_sql()}, {fk_sql()}, {_CHANGE}, d AS (SELECT batch_id, max(change) AS delta FROM chg GROUP BY 1) SELECT a.batch_id, a.fk, b.fk AS fk_before, delta, delta - abs(a.fk - b.fk) AS residual FROM fk a JOIN fk b ON b.batch_id = a.batch_id - 1 JOIN d ON d.batch_id = a.batch_id",
    "q19_rank_drift": f"""WITH {m_sql()}, {fk_sql()}, {_CHANGE}, d AS (SELECT max(change) AS delta FROM chg),
rows_ AS (SELECT r, freq >= n.fk AS hit, coalesce((SELECT x.freq FROM m x WHERE x.key = m.key AND x.batch_id = m.batch_id + r), 0) - t.fk AS gap, 2 * r * delta AS room
  FROM m JOIN fk n USING (batch_id), (SELECT unnest([1, 2, 3]) AS r), d, fk t WHERE t.batch_id = m.batch_id + r)
SELECT CAST(r AS BIGINT) AS r, CAST(min(CASE WHEN hit THEN gap + room END) AS BIGINT) AS residual_in, CAST(min(CASE WHEN NOT hit THEN room - gap END) AS BIGINT) AS residual_out FROM rows_ GROUP BY r""",
    "q20_window_truth": f"WITH {m_sql()}, {ends_sql()}, {_truth_cte()} SELECT * FROM truth",
    "q21_batch_union": f"WITH {_BASE}, {_union_cte('x', False)} SELECT * FROM x",
    "q22_sticky_union": f"WITH {_BASE}, {_union_cte('x', True)} SELECT * FROM x",
    **{q: f"WITH {_BASE}, {_variant_cte('x', T.slack(SPECS[q].name, M, SPECS[q].v, DELTA))} SELECT * FROM x" for q in ("q23_lookahead", "q24_persist_half", "q25_persist_34", "q26_heur_half", "q27_heur_34")},
    "q28_exact": f"WITH {_BASE}, {_CHANGE}, {_variant_cte('x', f'{2 * (M - 1)} * (SELECT max(change) FROM chg)')} SELECT * FROM x",
    "q29_prev_window": f"WITH {m_sql()}, {ends_sql()}, {_truth_cte()} SELECT window_end + 1 AS window_end, key, wfreq, rank FROM truth WHERE window_end + 1 <= (SELECT max(window_end) FROM ends)",
    "q30_precision_recall": f"WITH {m_sql()}, {_quality_ctes()} SELECT * FROM qual",
    "q31_accuracy_summary": f"WITH {m_sql()}, {_quality_ctes()} SELECT * FROM summ",
    "q32_persistent": f"WITH {_BASE}, {_HITS} SELECT window_end, CAST(v AS BIGINT) AS v, count(*) AS n_persistent FROM hits, (SELECT unnest(range(1, {M + 1})) AS v) WHERE hits >= v GROUP BY 1, 2",
    "q33_bounds": f"""WITH {_BASE}, {_HITS}, {_CHANGE}, d AS (SELECT max(change) AS delta FROM chg), {_truth_cte()},
sf AS (SELECT window_end, CAST(sum(fk) AS BIGINT) AS sum_fk FROM fk JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end GROUP BY 1),
vs AS (SELECT window_end, v, min(CASE WHEN coalesce(hits, 0) >= v THEN wfreq END) AS seen_min, max(CASE WHEN coalesce(hits, 0) < v THEN wfreq END) AS seen_max FROM tr_s LEFT JOIN hits USING (window_end, key), (SELECT unnest(range(1, {M + 1})) AS v) GROUP BY 1, 2)
SELECT window_end, v, sum_fk - ({M} - v) * ({M} - v + 1) * delta AS lower, sum_fk + v * (v + 1) * delta AS upper_printed, sum_fk + v * (v - 1) * delta AS upper_tight, seen_min, seen_max FROM vs JOIN sf USING (window_end), d""",
    "q34_separation": f"WITH {m_sql()}, {fk_sql()} {_EPS}",
    "q35_band_gap": f"WITH {_BASE} SELECT DISTINCT window_end, key FROM m JOIN fk USING (batch_id) JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end WHERE freq < fk AND freq >= fk - 2.0 * {DELTA}",
    "q36_error_bound": f"""WITH {_BASE}, {_HITS}, {_truth_cte()}, se AS ({_EPS}),
e AS (SELECT window_end, max(eps) AS eps FROM se JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end WHERE phi = {PHI} GROUP BY 1),
g AS (SELECT * FROM (VALUES {', '.join(f'({v}, CAST({T.mu(M, v, PHI)!r} AS DOUBLE))' for v in VS)}) AS t(v, mu)),
mi AS (SELECT window_end, v, mu, CAST(sum(CASE WHEN coalesce(hits, 0) < v THEN 1 ELSE 0 END) AS BIGINT) AS missed FROM truth LEFT JOIN hits USING (window_end, key), g GROUP BY 1, 2, 3),
np AS (SELECT window_end, v, CAST(sum(CASE WHEN hits >= v THEN 1 ELSE 0 END) AS BIGINT) AS n_persistent FROM hits, g GROUP BY 1, 2)
SELECT window_end, CAST(v AS BIGINT) AS v, eps, round(mu, 6) AS mu, round(eps * {K} * {M} / mu, 6) AS bound, n_persistent, missed FROM mi JOIN e USING (window_end) JOIN np USING (window_end, v)""",
    "q37_thresholds": f"""WITH {m_sql()}, {fk_sql()}, {_CHANGE}, d AS (SELECT batch_id, max(change) AS delta FROM chg GROUP BY 1),
g AS (SELECT m, unnest(['batch_union', 'sticky_union', 'lookahead', 'persist_34', 'heur_34', 'persist_half', 'heur_half', 'exact_depth']) AS variant,
  unnest([0.0, 0.0, 2.0, 2 * (m - .75 * m), m * (2 - .75 - .5625), 2 * (m - .5 * m), m * (2 - .5 - .25), 2.0 * (m - 1)]::DOUBLE[]) AS unit FROM (SELECT unnest([5, 10, 15]) AS m))
SELECT batch_id, CAST(m AS BIGINT) AS m, variant, unit * delta AS theta, CAST(greatest(1, ceil(fk - unit * delta - 1e-9)) AS BIGINT) AS f_min FROM d JOIN fk USING (batch_id), g""",
    "q46_m_sweep": _sweep("m", [(win, f"WITH {m_sql()}, {_quality_ctes(K, win)} SELECT * FROM summ") for win in (5, 10, 15)]),
    "q47_tb_sweep": _sweep("batch_seconds", [(span // 1_000_000, f"WITH {m_sql(ELL, span)}, {_quality_ctes()} SELECT * FROM summ") for span in SPANS]),
    "q48_k_sweep": _sweep("k", [(k, f"WITH {m_sql()}, {_quality_ctes(k)} SELECT * FROM summ") for k in (5, 10, 25, 50)]),
    "q50_late_events": f"""WITH {ev_sql()}, a AS (SELECT user_id, tick, max(tick) OVER (PARTITION BY user_id ORDER BY (event_id * 7919) % 10007 * 1000000 + event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM ev)
SELECT CAST(user_id AS VARCHAR) AS stream_key, count(*) AS n_events, CAST(sum(CASE WHEN tick < seen - {5 * DAY} THEN 1 ELSE 0 END) AS BIGINT) AS n_late FROM a GROUP BY 1""",
    "q52_mixing": f"""WITH {_BASE}, {_HITS}, {_truth_cte()}, sf AS (SELECT window_end, sum(fk) AS sum_fk FROM fk JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end GROUP BY 1),
g AS (SELECT unnest([{', '.join(map(str, VS))}]) AS v),
gap AS (SELECT DISTINCT window_end, key FROM m JOIN fk USING (batch_id) JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end WHERE freq < fk AND freq >= fk - {PHI} * {DELTA}),
r AS (SELECT t.window_end, v, t.key, p.key IS NULL AS outside FROM tr_s t JOIN sf USING (window_end) CROSS JOIN g LEFT JOIN hits h USING (window_end, key) LEFT JOIN gap p USING (window_end, key)
  WHERE coalesce(h.hits, 0) < v AND t.wfreq >= sum_fk - ({M} - v) * ({M} - v + 1) * {DELTA})
SELECT sf.window_end, CAST(g.v AS BIGINT) AS v, {PHI} / 2 > greatest(1, (1 - g.v / {M}.0) * ({M} - g.v + 1)) AS phi_ok, count(r.key) AS n_mixing, CAST(sum(CASE WHEN outside THEN 1 ELSE 0 END) AS BIGINT) AS n_outside
FROM sf CROSS JOIN g LEFT JOIN r ON r.window_end = sf.window_end AND r.v = g.v GROUP BY 1, 2, 3""",
    "q87_special_cases": f"""WITH {_BASE}, se AS ({_EPS}), e AS (SELECT window_end, max(eps) AS eps FROM se JOIN ends ON batch_id BETWEEN window_end - {M - 1} AND window_end WHERE phi = {PHI} GROUP BY 1),
c AS (SELECT * FROM (VALUES ('one', 1, {K} * {M} / ({M} - 1.0)), ('all', {M}, {K} * {M}.0), ('half', {(M + 1) // 2}, 4.0 * {K} * {M} * {M} / ({M} * {M} - 1.0))) AS t("case", v, factor))
SELECT window_end, "case", CAST(v AS BIGINT) AS v, eps, round(eps * CAST(factor AS DOUBLE), 6) AS bound FROM e, c""",
}
ORACLES["q49_stream_replay"] = ORACLES["q23_lookahead"]
ORACLES |= {name: ORACLES[closed] for name, closed in RUNS.items()} | {"q98_exact_run": ORACLES["q20_window_truth"]}
