"""Drift, separation, band gaps and the bounds beside what is observed."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftlattice.functions import thresholds as T
from driftlattice.plans.window import kth_frequency, persistent_hits, spread, window_sums, window_truth, with_flags


def changes(counts: DataFrame, first: int, last: int) -> DataFrame:
    """(batch_id, key, change): absolute change of each pattern against the batch before; absent counts as 0."""
    cur = counts.select("batch_id", "key", F.col("freq").alias("cur"))
    prev = counts.select((F.col("batch_id") + 1).alias("batch_id"), "key", F.col("freq").alias("prev"))
    both = cur.join(prev, ["batch_id", "key"], "full_outer").where(F.col("batch_id").between(first + 1, last))
    return both.select("batch_id", "key", F.abs(F.coalesce("cur", F.lit(0)) - F.coalesce("prev", F.lit(0))).alias("change"))


def delta_exact(counts: DataFrame, first: int, last: int) -> DataFrame:
    return changes(counts, first, last).groupBy("batch_id").agg(F.max("change").alias("delta"))


def delta_estimate(counts: DataFrame, first: int, last: int, q: float = 0.75, population: str = "all", k: int = 25, tracked_slack: float = 0.0, approximate: bool = False) -> DataFrame:
    """(batch_id, delta): q-quantile of the changes of 'all' patterns, of those in both top k ('topk_common'), or of those tracked in both."""
    change = changes(counts, first, last)
    if population != "all":
        flag = "hit" if population == "topk_common" else "tracked"
        flags = with_flags(counts, k, tracked_slack).where(flag).select("batch_id", "key")
        change = change.join(flags, ["batch_id", "key"], "left_semi").join(flags.select((F.col("batch_id") + 1).alias("batch_id"), "key"), ["batch_id", "key"], "left_semi")
    value = F.percentile_approx("change", q, 10_000).cast("double") if approximate else F.percentile("change", q)
    return change.groupBy("batch_id").agg(F.round(value, 6).alias("delta"))


def fk_drift(counts: DataFrame, k: int, first: int, last: int) -> DataFrame:
    """(batch_id, fk, fk_before, delta, residual): the k-th frequency moves by delta at most, so no residual is negative."""
    fk = kth_frequency(counts, k)
    before = fk.select((F.col("batch_id") + 1).alias("batch_id"), F.col("fk").alias("fk_before"))
    out = fk.join(before, "batch_id").join(delta_exact(counts, first, last), "batch_id")
    return out.withColumn("residual", F.col("delta") - F.abs(F.col("fk") - F.col("fk_before")))


def rank_drift(counts: DataFrame, k: int, first: int, last: int, steps=(1, 2, 3)) -> DataFrame:
    """(r, residual_in, residual_out) over all batches and patterns: distance from the bounds of patterns in and out of the top k r batches ago."""
    bound = delta_exact(counts, first, last).agg(F.max("delta").alias("delta"))
    flags = with_flags(counts, k, 0)
    fk = kth_frequency(counts, k).select(F.col("batch_id").alias("then_id"), F.col("fk").alias("fk_then"))
    then = counts.select(F.col("batch_id").alias("then_id"), "key", F.col("freq").alias("freq_then"))
    now = flags.select((F.col("batch_id")).alias("now_id"), "key", "hit").withColumn("r", F.explode(F.array(*[F.lit(r) for r in steps]))).withColumn("then_id", F.col("now_id") + F.col("r")).where(F.col("then_id") <= last)
    rows = now.join(then, ["then_id", "key"], "left").join(F.broadcast(fk), "then_id").crossJoin(F.broadcast(bound))
    gap = F.coalesce("freq_then", F.lit(0)) - F.col("fk_then")
    room = 2 * F.col("r") * F.col("delta")
    return rows.groupBy("r").agg(F.min(F.when(F.col("hit"), gap + room)).alias("residual_in"), F.min(F.when(~F.col("hit"), room - gap)).alias("residual_out")).withColumn("r", F.col("r").cast("long"))


def persistent_sizes(counts: DataFrame, k: int, m: int, first: int, last: int) -> DataFrame:
    """(window_end, v, n_persistent) for v = 1 .. m."""
    hits = persistent_hits(with_flags(counts, k, 0), m, first, last)
    return hits.withColumn("v", F.explode(F.sequence(F.lit(1), F.col("hits").cast("int")))).groupBy("window_end", "v").agg(F.count(F.lit(1)).alias("n_persistent")).withColumn("v", F.col("v").cast("long"))


def window_fk(counts: DataFrame, k: int, m: int, first: int, last: int) -> DataFrame:
    return spread(kth_frequency(counts, k), m, first, last).groupBy("window_end").agg(F.sum("fk").alias("sum_fk"))


def bounds(counts: DataFrame, k: int, m: int, first: int, last: int) -> DataFrame:
    """(window_end, v, lower, upper_printed, upper_tight, seen_min, seen_max): bounds beside the least persistent and the largest other sum."""
    delta = delta_exact(counts, first, last).agg(F.max("delta").alias("delta"))
    hits = persistent_hits(with_flags(counts, k, 0), m, first, last)
    sums = window_sums(counts, m, first, last).join(hits, ["window_end", "key"], "left").withColumn("hits", F.coalesce("hits", F.lit(0)))
    vs = sums.withColumn("v", F.explode(F.sequence(F.lit(1), F.lit(m))))
    seen = vs.groupBy("window_end", "v").agg(F.min(F.when(F.col("hits") >= F.col("v"), F.col("wfreq"))).alias("seen_min"), F.max(F.when(F.col("hits") < F.col("v"), F.col("wfreq"))).alias("seen_max"))
    out = seen.join(F.broadcast(window_fk(counts, k, m, first, last)), "window_end").crossJoin(F.broadcast(delta))
    v, d = F.col("v"), F.col("delta")
    return out.select("window_end", v.cast("long").alias("v"), (F.col("sum_fk") - (m - v) * (m - v + 1) * d).alias("lower"), (F.col("sum_fk") + v * (v + 1) * d).alias("upper_printed"), (F.col("sum_fk") + v * (v - 1) * d).alias("upper_tight"), "seen_min", "seen_max")


def separation(counts: DataFrame, k: int, delta: float, phis) -> DataFrame:
    """(batch_id, phi, eps): patterns within phi * delta below the k-th frequency, beyond k, as a share of k."""
    fk = kth_frequency(counts, k)
    rows = counts.join(F.broadcast(fk), "batch_id").withColumn("phi", F.explode(F.array(*[F.lit(float(p)) for p in phis])))
    near = F.sum(F.when(F.col("freq") >= F.col("fk") - F.col("phi") * delta, 1).otherwise(0))
    return rows.groupBy("batch_id", "phi").agg(F.round(F.greatest(F.lit(0.0), near / k - 1), 6).alias("eps"))


def band_gap(counts: DataFrame, k: int, m: int, delta: float, phi: float, first: int, last: int) -> DataFrame:
    """(window_end, key): patterns in [fk - phi * delta, fk) in at least one batch of the window."""
    fk = kth_frequency(counts, k)
    inside = counts.join(F.broadcast(fk), "batch_id").where((F.col("freq") < F.col("fk")) & (F.col("freq") >= F.col("fk") - phi * delta))
    return spread(inside, m, first, last).select("window_end", "key").distinct()


def mixing(counts: DataFrame, k: int, m: int, vs, delta: float, phi: float, first: int, last: int) -> DataFrame:
    """(window_end, v, phi_ok, n_mixing, n_outside): non-persistent patterns that reach the lower bound, and how many of them lie
    outside the band gap (0 where the condition on phi holds); a row for every window and v."""
    hits = persistent_hits(with_flags(counts, k, 0), m, first, last)
    grid = F.explode(F.array(*[F.struct(F.lit(int(v)).cast("long").alias("v"), F.lit(float((m - v) * (m - v + 1) * delta)).alias("room"), F.lit(T.phi_ok(phi, m, v)).alias("phi_ok")) for v in vs]))
    fk = window_fk(counts, k, m, first, last).withColumn("g", grid).select("window_end", "g.v", "g.phi_ok", (F.col("sum_fk") - F.col("g.room")).alias("low"))
    rows = window_sums(counts, m, first, last).join(hits, ["window_end", "key"], "left").join(F.broadcast(fk), "window_end").where((F.coalesce("hits", F.lit(0)) < F.col("v")) & (F.col("wfreq") >= F.col("low")))
    gap = band_gap(counts, k, m, delta, phi, first, last).withColumn("inside", F.lit(1))
    found = rows.join(gap, ["window_end", "key"], "left").groupBy("window_end", "v").agg(F.count(F.lit(1)).alias("n_mixing"), F.sum(F.when(F.col("inside").isNull(), 1).otherwise(0)).alias("n_outside"))
    return fk.join(found, ["window_end", "v"], "left").select("window_end", "v", "phi_ok", F.coalesce("n_mixing", F.lit(0)).alias("n_mixing"), F.coalesce("n_outside", F.lit(0)).alias("n_outside"))


def error_bounds(counts: DataFrame, k: int, m: int, delta: float, phi: float, first: int, last: int, vs=(1, 5, 8, 10)) -> DataFrame:
    """(window_end, v, eps, mu, bound, n_persistent, missed): the bound on errors beside the true top-k patterns that are not persistent."""
    flags = with_flags(counts, k, 0)
    hits = persistent_hits(flags, m, first, last)
    eps = spread(separation(counts, k, delta, [phi]), m, first, last).groupBy("window_end").agg(F.max("eps").alias("eps"))
    truth = window_truth(counts, m, k, first, last).select("window_end", "key").join(hits, ["window_end", "key"], "left").withColumn("hits", F.coalesce("hits", F.lit(0)))
    grid = F.explode(F.array(*[F.struct(F.lit(int(v)).cast("long").alias("v"), F.lit(T.mu(m, v, phi)).alias("mu")) for v in vs]))
    missed = truth.withColumn("g", grid).groupBy("window_end", "g").agg(F.sum(F.when(F.col("hits") < F.col("g.v"), 1).otherwise(0)).alias("missed"))
    size = hits.withColumn("g", grid).groupBy("window_end", F.col("g.v").alias("v")).agg(F.sum(F.when(F.col("hits") >= F.col("g.v"), 1).otherwise(0)).alias("n_persistent"))
    out = missed.select("window_end", F.col("g.v").alias("v"), F.col("g.mu").alias("mu"), "missed").join(eps, "window_end").join(size, ["window_end", "v"])
    return out.select("window_end", "v", "eps", F.round("mu", 6).alias("mu"), F.round(F.col("eps") * k * m / F.col("mu"), 6).alias("bound"), "n_persistent", "missed")


def special_cases(eps: float, k: int, m: int) -> dict[str, float]:
    half = math.floor((m + 1) / 2)
    return {"one": T.error_bound_special("one", eps, k, m), "all": T.error_bound_special("all", eps, k, m), "half": T.error_bound_special("half", eps, k, m), "v_half": half}
