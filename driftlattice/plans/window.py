"""Top-k with ties, window sums, persistence: plans over the count matrix (batch_id, key, freq)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def topk_with_ties(df: DataFrame, k: int, by: str, value: str = "freq") -> DataFrame:
    """Rows whose value is at least the k-th best of their group, with rank. The filter on the rank reaches the scan side of the shuffle."""
    return df.withColumn("rank", F.rank().over(Window.partitionBy(by).orderBy(F.desc(value))).cast("long")).where(F.col("rank") <= k)


def kth_frequency(counts: DataFrame, k: int) -> DataFrame:
    """(batch_id, fk): the k-th best frequency, or the smallest where fewer patterns occur."""
    best = counts.withColumn("r", F.row_number().over(Window.partitionBy("batch_id").orderBy(F.desc("freq")))).where(F.col("r") <= k)
    return best.groupBy("batch_id").agg(F.min("freq").alias("fk"))


def batch_range(counts: DataFrame) -> tuple[int, int] | None:
    low, high = counts.agg(F.min("batch_id"), F.max("batch_id")).first()
    return None if low is None else (low, high)


def spread(df: DataFrame, m: int, first: int, last: int) -> DataFrame:
    """Every row beside each full window (window_end) that holds its batch."""
    ends = F.sequence(F.greatest(F.col("batch_id"), F.lit(first + m - 1)), F.least(F.col("batch_id") + m - 1, F.lit(last)))
    alive = df.where((F.lit(first + m - 1) <= last) & (F.greatest(F.col("batch_id"), F.lit(first + m - 1)) <= F.least(F.col("batch_id") + m - 1, F.lit(last))))
    return alive.withColumn("window_end", F.explode(ends))


def window_sums(counts: DataFrame, m: int, first: int, last: int) -> DataFrame:
    """(window_end, key, wfreq): sums of batch frequencies; partial sums come before the shuffle."""
    return spread(counts, m, first, last).groupBy("window_end", "key").agg(F.sum("freq").alias("wfreq"))


def window_truth(counts: DataFrame, m: int, k: int, first: int, last: int) -> DataFrame:
    return topk_with_ties(window_sums(counts, m, first, last), k, "window_end", "wfreq")


def with_flags(counts: DataFrame, k: int, theta: float) -> DataFrame:
    """counts with fk, hit (in the batch's top k) and tracked (at least fk - theta, and 1)."""
    fk = kth_frequency(counts, k)
    return counts.join(F.broadcast(fk), "batch_id").withColumn("hit", F.col("freq") >= F.col("fk")).withColumn("tracked", F.col("freq") >= F.greatest(F.lit(1), F.ceil(F.col("fk") - F.lit(theta) - 1e-9)))


def persistent_hits(flags: DataFrame, m: int, first: int, last: int) -> DataFrame:
    """(window_end, key, hits): batches of the window in whose top k a pattern is."""
    return spread(flags.where("hit"), m, first, last).groupBy("window_end", "key").agg(F.count(F.lit(1)).alias("hits"))
