"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def quality(reports: DataFrame, truth: DataFrame, by=()) -> DataFrame:
    """(variant, window_end, n_pred, n_true, n_common, precision, recall); set sizes are real, ties included. by: further columns of both, of which each group is taken apart."""
    both = reports.select(*by, "variant", "window_end", "key").join(truth.select(*by, "window_end", "key", F.lit(1).alias("true")), [*by, "window_end", "key"], "left")
    pred = both.groupBy(*by, "variant", "window_end").agg(F.count(F.lit(1)).alias("n_pred"), F.count("true").alias("n_common"))
    out = pred.join(truth.groupBy(*by, "window_end").agg(F.count(F.lit(1)).alias("n_true")), [*by, "window_end"])
    return out.select(*by, "variant", "window_end", "n_pred", "n_true", "n_common", F.round(F.col("n_common") / F.col("n_pred"), 6).alias("precision"), F.round(F.col("n_common") / F.col("n_true"), 6).alias("recall"))


def summarize(quality_df: DataFrame, by=("variant",)) -> DataFrame:
    return quality_df.groupBy(*by).agg(F.count(F.lit(1)).alias("windows"), F.round(F.avg("precision"), 4).alias("precision"), F.round(F.avg("recall"), 4).alias("recall"))


def timeline(quality_df: DataFrame, drift=((15, 20), (35, 42))) -> DataFrame:
    """The same with the region of each window: drifting or steady."""
    inside = F.lit(False)
    for low, high in drift:
        inside = inside | F.col("window_end").between(low, high)
    return quality_df.withColumn("region", F.when(inside, "drifting").otherwise("steady"))


class StopWatch:
    """Wall-clock seconds of named parts, and counters beside them."""

    def __init__(self):
        self.rows: list[dict] = []

    def __call__(self, **names):
        watch, row = self, dict(names)

        class _Part:
            def __enter__(self):
                row["began"] = time.perf_counter()
                return row

            def __exit__(self, *_):
                row["seconds"] = time.perf_counter() - row.pop("began")
                watch.rows.append(row)

        return _Part()


def state_bytes(lattice_rows: int, ell: int, events: int = 0) -> int:
    """Bytes a method keeps between batches: 8 a count, 4 a node, 12 an event it must hold."""
    return lattice_rows * (8 + 4 * ell) + 12 * events
