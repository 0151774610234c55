"""SQL front: views over a stream's batches, counts and reports, and a table function that mines a partition."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from driftlattice.functions.aggregates import nonoverlap_count
from driftlattice.params import MineParams, VariantSpec
from driftlattice.plans import variants, window


def register_views(counts: DataFrame, m: int, k: int, delta: float, variant: str = "lookahead", v: float | None = None) -> None:
    """Temp views batch_topk(batch_id, key, freq, rank), window_topk(window_end, key, wfreq, rank) and window_truth of stored counts."""
    low, high = window.batch_range(counts) or (0, -1)
    window.topk_with_ties(counts, k, "batch_id").createOrReplaceTempView("batch_topk")
    variants.report(counts, VariantSpec(variant, v), m, k, delta, low, high).createOrReplaceTempView("window_topk")
    window.window_truth(counts, m, k, low, high).createOrReplaceTempView("window_truth")


@udtf(returnType="batch_id bigint, key string, freq bigint")
class MineEpisodes:
    """SELECT * FROM mine_episodes(25, 4, TABLE(SELECT batch_id, tick, symbol ...) PARTITION BY batch_id ORDER BY tick)

    The top k serial episodes of size ell of each partition, with ties. A partition is one batch and
    is held in memory; for batches beyond that use operators.counting with slices.
    """

    def __init__(self):
        self.ticks: list[tuple[int, set]] = []
        self.batch, self.k, self.ell = None, 1, 1

    def eval(self, k: int, ell: int, row):
        self.batch, self.k, self.ell = row["batch_id"], k, ell
        if self.ticks and self.ticks[-1][0] == row["tick"]:
            self.ticks[-1][1].add(row["symbol"])
        else:
            self.ticks.append((row["tick"], {row["symbol"]}))

    def terminate(self):
        from driftlattice.plans import lattice

        if not self.ticks:
            return

        def count(patterns):
            out = {}
            for p in patterns:
                n = 0
                for _, here in self.ticks:
                    n += p[n % len(p)] in here
                out[p] = n // len(p)
            return out

        symbols = {(x,) for _, here in self.ticks for x in here}
        found, _ = lattice.mine_topk(lattice.Memo(count), symbols, self.k, self.ell, MineParams(k=self.k, ell=self.ell))
        for key, freq, _ in lattice.ranked({">".join(p): c for p, c in found.top().items()}, self.k):
            yield self.batch, key, freq


def register_functions(spark: SparkSession) -> None:
    """mine_episodes (table function) and nonoverlap_count (aggregate) for SQL."""
    spark.udtf.register("mine_episodes", MineEpisodes)
    spark.udf.register("nonoverlap_count", nonoverlap_count)
