"""Batches, ticks and slices of an event frame."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def batch_ledger(frame: DataFrame) -> DataFrame:
    """(batch_id, n_events, n_symbols, first_tick, last_tick) per batch."""
    return frame.groupBy("batch_id").agg(
        F.count(F.lit(1)).alias("n_events"), F.countDistinct("symbol").alias("n_symbols"), F.min("tick").alias("first_tick"), F.max("tick").alias("last_tick")
    )


def alphabet(frame: DataFrame) -> DataFrame:
    """(symbol, etype): dense ids in symbol order. The ranking runs over distinct symbols only."""
    return frame.select("symbol").distinct().select("symbol", (F.row_number().over(Window.orderBy("symbol")) - 1).alias("etype"))


def new_symbols(batch: DataFrame, known: DataFrame) -> DataFrame:
    """Symbols of a batch that the dictionary does not hold."""
    return batch.select("symbol").distinct().join(known.select("symbol"), "symbol", "left_anti")


def frequent_symbols_only(frame: DataFrame, f_min: int, per=("batch_id",)) -> DataFrame:
    """Drops events whose symbol is below the threshold on its own: no longer pattern can hold it."""
    ticks = frame.select(*per, "symbol", "tick").distinct().groupBy(*per, "symbol").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= f_min)
    return frame.join(ticks.select(*per, "symbol"), [*per, "symbol"], "left_semi")


def to_ticks(frame: DataFrame, per=("batch_id",)) -> DataFrame:
    """(*per, tick, symbols): events of one time are one tick with a set of symbols."""
    return frame.groupBy(*per, "tick").agg(F.sort_array(F.collect_set("symbol")).alias("symbols"))


def cuts(frame: DataFrame, slices: int, per=("batch_id",)) -> DataFrame:
    """(*per, cut array<long>): ticks that part each batch into slices of about equal numbers of events.

    Approximate percentiles, so no task sorts a batch, and bursts do not make large slices.
    """
    shares = [k / slices for k in range(1, slices)]
    return frame.groupBy(*per).agg(F.percentile_approx("tick", shares, 1000).alias("cut"))


def sequences(frame: DataFrame, per=("batch_id",), slices: int = 1, ties: bool = True) -> DataFrame:
    """(*per, seg, seq): the ticks of each slice in order, as arrays of symbols (ties), or every event in the order of tick, place (where the frame has it) and symbol.

    Slices are cut at tick borders only. A slice is the largest thing a task holds; choose `slices`
    so that it stays near a hundred thousand ticks.
    """
    rows = to_ticks(frame, per) if ties else frame
    if slices > 1:
        rows = rows.join(cuts(frame, slices, per), list(per)).withColumn("seg", F.size(F.filter("cut", lambda c: c < F.col("tick"))).cast("int"))
    else:
        rows = rows.withColumn("seg", F.lit(0))
    order = ["tick"] if ties else [c for c in ("tick", "place") if c in frame.columns]
    ordered = F.array_sort(F.collect_list(F.struct(*order, F.col("symbols" if ties else "symbol").alias("y"))))
    return rows.groupBy(*per, "seg").agg(F.transform(ordered, lambda x: x["y"]).alias("seq"))


def late_split(frame: DataFrame, lateness: int) -> DataFrame:
    """Marks events as late against a running watermark in arrival order (arrival long, tick long).

    An event is late when the largest tick that arrived before it is more than `lateness` ahead.
    """
    seen = F.max("tick").over(Window.partitionBy("stream_key").orderBy("arrival").rowsBetween(Window.unboundedPreceding, -1))
    return frame.withColumn("late", F.coalesce(F.col("tick") < seen - lateness, F.lit(False)))
