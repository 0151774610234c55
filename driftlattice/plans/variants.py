"""The window answers compared with each other, as declarative plans over stored batch counts.

Given the counts of all patterns per batch, what each variant would have tracked, known and reported
has a closed form; one plan per variant answers all windows at once, without a loop over batches.
The same answers come out of the incremental lattice (plans.lattice.run_variant), which needs no
counts of patterns that it does not track.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftlattice.functions.thresholds import slack
from driftlattice.operators import pairs
from driftlattice.params import VariantSpec
from driftlattice.plans import metrics
from driftlattice.plans.window import persistent_hits, spread, topk_with_ties, window_truth, with_flags
from driftlattice.sources.ledger import written

#: The published line-up with m = 10: slack variants at v = m / 2 and 3 m / 4.
LINE_UP = {
    "batch_union": VariantSpec("batch_union"), "sticky_union": VariantSpec("sticky_union"), "lookahead": VariantSpec("lookahead"),
    "persist_34": VariantSpec("persistent_depth", 0.75), "heur_34": VariantSpec("heuristic_depth", 0.75),
    "persist_half": VariantSpec("persistent_depth", 0.5), "heur_half": VariantSpec("heuristic_depth", 0.5),
}


def line_up(m: int) -> dict[str, VariantSpec]:
    """The variants compared, with v as a share of m made a number of batches."""
    return {name: spec if spec.v is None else VariantSpec(spec.name, max(1.0, spec.v * m)) for name, spec in LINE_UP.items() } if m > 1 else {n: s if s.v is None else VariantSpec(s.name, 1.0) for n, s in LINE_UP.items()}


def report(counts: DataFrame, spec: VariantSpec, m: int, k: int, delta: float, first: int, last: int, known: str = "seeded", candidates: str = "current", reported: str = "tracked") -> DataFrame:
    """(window_end, key, wfreq, rank) that a variant reports.

    known: batches whose count of a pattern the variant has ('frequent': tracked there; 'seeded': or
    in the batch before, as the next batch's seed counts it). candidates: patterns tracked in the
    newest batch ('current') or in any of the window ('window').
    """
    if spec.name == "window_recount":
        return window_truth(counts, m, k, first, last)
    if spec.name == "previous_window":
        return window_truth(counts, m, k, first, last).withColumn("window_end", F.col("window_end") + 1).where(F.col("window_end") <= last)
    theta = slack(spec.name, m, spec.v, delta)
    flags = with_flags(counts, k, theta)
    if spec.name == "batch_union":
        rows = spread(flags.where("hit"), m, first, last)
        return topk_with_ties(rows.groupBy("window_end", "key").agg(F.sum("freq").alias("wfreq")), k, "window_end", "wfreq")
    if spec.name == "sticky_union":
        held = F.max(F.col("hit").cast("int")).over(Window.partitionBy("key").orderBy("batch_id").rangeBetween(-m, 0)) == 1
        rows = spread(flags.withColumn("have", held), m, first, last)
        sums = rows.groupBy("window_end", "key").agg(F.sum(F.when(F.col("have"), F.col("freq")).otherwise(0)).alias("wfreq"), F.max("hit").alias("in"))
        return topk_with_ties(sums.where("in").drop("in"), k, "window_end", "wfreq")
    by_key = Window.partitionBy("key").orderBy("batch_id")
    before = F.coalesce(F.when(F.lag("batch_id").over(by_key) == F.col("batch_id") - 1, F.lag("tracked").over(by_key)), F.lit(False))
    have = F.col("tracked") | before if known == "seeded" else F.col("tracked")
    rows = spread(flags.withColumn("have", have), m, first, last)
    now = F.col("tracked") & (F.col("batch_id") == F.col("window_end")) if candidates == "current" else F.col("tracked")
    sums = rows.groupBy("window_end", "key").agg(F.sum(F.when(F.col("have"), F.col("freq")).otherwise(0)).alias("wfreq"), F.max(now).alias("in")).where("in").drop("in")
    if reported == "persistent":
        sums = sums.join(persistent_hits(flags, m, first, last).where(F.col("hits") >= spec.hits()), ["window_end", "key"], "left_semi")
    return topk_with_ties(sums, k, "window_end", "wfreq")


def all_reports(counts: DataFrame, m: int, k: int, delta: float, first: int, last: int) -> DataFrame:
    """(variant, window_end, key, wfreq, rank) of the whole line-up and the reference curve."""
    specs = {**line_up(m), "previous_window": VariantSpec("previous_window")}
    out = None
    for name, spec in specs.items():
        one = report(counts, spec, m, k, delta, first, last).select(F.lit(name).alias("variant"), "window_end", "key", "wfreq", "rank")
        out = one if out is None else out.unionByName(one)
    return out


def pair_quality(frame: DataFrame, m: int, k: int, delta: float, block: int | None = None) -> DataFrame | None:
    """metrics.quality of the whole line-up over all pairs of symbols of frame(batch_id, tick, symbol), without a table of their counts.

    Two rounds over all pairs (operators.pairs): the first gives the truth and, as it counts how many pairs have a frequency, every batch's
    k-th one; then each report's candidates are looked at as far as their sum over the window could be among its k best. What it has to reach is
    known from some of the best pairs of the truth, whatever these are. None where pairs.tick_bits gives none.
    """
    grid = pairs.tick_bits(frame)
    if grid is None:
        return None
    spark, nb = frame.sparkSession, grid.batches()
    first = written(pairs.each_block(spark, grid, block, pairs.window_rows, pairs.ROWS, m, k, pairs.pilot(grid, m, k), pairs.pilot(grid, 1, k)))
    fk, have = np.full(nb, np.iinfo(np.int64).max // 2), {}
    for r in first.where("name = 'spectrum'").groupBy("end", "wfreq").agg(F.sum("n").alias("n")).orderBy("end", F.desc("wfreq")).collect():
        if have.get(r.end, 0) < k:  # down to the k-th best pair, or the last one
            fk[r.end], have[r.end] = r.wfreq, have.get(r.end, 0) + r.n
    reports = {}
    for name, spec in line_up(m).items():
        floors = np.maximum(1, np.ceil(fk - slack(spec.name, m, spec.v, delta) - 1e-9)).astype(np.int64)
        unions = spec.name in ("batch_union", "sticky_union")
        reports[name] = pairs.Report(floors, m if spec.name == "sticky_union" else 0 if unions else 1, unions)
    truth = written(topk_with_ties(first.where("name = ''").select("end", "a", "b", "wfreq"), k, "end", "wfreq"))
    some = truth.withColumn("r", F.row_number().over(Window.partitionBy("end").orderBy(F.desc("wfreq"), "a", "b"))).where(F.col("r") <= 4 * k).select("a", "b").distinct().toArrow()
    often = pairs.common_pairs(grid)
    bounds = pairs.report_bounds(grid, m, k, reports, *(np.concatenate([some.column(c).to_numpy(), x]) for c, x in zip("ab", often)))
    rows = pairs.each_block(spark, grid, block, pairs.report_rows, pairs.ROWS, m, k, reports, bounds)
    said = rows.withColumn("rank", F.rank().over(Window.partitionBy("name", "end").orderBy(F.desc("wfreq")))).where(F.col("rank") <= k)
    named = lambda df, name: df.select(name.alias("variant"), (F.col("end") + grid.lo).alias("window_end"), (F.col("a") * len(grid.names) + F.col("b")).alias("key"))
    before = named(truth.withColumn("end", F.col("end") + 1).where(F.col("end") < nb), F.lit("previous_window"))
    return metrics.quality(named(said, F.col("name")).unionByName(before), named(truth, F.lit(""))).drop("n_common")
