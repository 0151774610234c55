"""Episode mining on Structured Streaming.

One global stream: micro-batches are appended to an event ledger (a partition per micro-batch, so a
replayed micro-batch overwrites itself), batches whose end the watermark has passed are closed and
mined, and every result is a ledger partition named by its batch: exactly once, whatever restarts.

Many key streams: the state of a key's automata lives in Spark's state store, per key.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, types as T
from pyspark.sql import functions as F

from driftlattice.operators import batching, counting
from driftlattice.params import MineParams, VariantSpec
from driftlattice.plans import lattice
from driftlattice.functions.thresholds import slack
from driftlattice.sources import adapters
from driftlattice.sources.ledger import shared_folder, written

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def file_stream(spark: SparkSession, path: str, schema: str = EVENT_SCHEMA, files_per_trigger: int = 1, kind: str = "parquet") -> DataFrame:
    """A stream of files (parquet, csv, json ...); `path` is a folder or a pattern."""
    return spark.readStream.format(kind).schema(schema).option("maxFilesPerTrigger", files_per_trigger).load(path)


def rate_stream(spark: SparkSession, rows_per_second: int, symbols: int) -> DataFrame:
    """A synthetic live stream as an event frame, for trials."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rate.select(F.lit("all").alias("stream_key"), F.col("timestamp").cast("timestamp_ntz").alias("ts"), F.unix_micros("timestamp").alias("tick"), F.concat(F.lit("s"), (F.pmod(F.xxhash64("value"), F.lit(symbols))).cast("string")).alias("symbol"))


def message_frame(messages: DataFrame, origin: str = adapters.ORIGIN) -> DataFrame:
    """Messages with a JSON value {key, ts, symbol}, the shape a message queue delivers, as an event frame."""
    parsed = messages.select(F.from_json(F.col("value").cast("string"), "key string, ts timestamp_ntz, symbol string").alias("x"))
    return adapters.adapt(parsed.select("x.*"), F.col("ts"), F.col("symbol"), F.col("key"), origin=origin)


class EventLedger:
    """Event log and results under a folder all executors share: events by micro-batch and time batch, reports by window."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        import uuid

        self.spark, self.folder = spark, folder or f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def append(self, frame: DataFrame, epoch: int) -> None:
        """A replayed micro-batch overwrites itself."""
        frame.write.mode("overwrite").partitionBy("batch_id").parquet(f"{self.folder}/events/epoch={epoch}")

    def read(self, first: int | None = None, last: int | None = None) -> DataFrame:
        """Events of some time batches; only their partitions are read."""
        log = self.spark.read.option("basePath", f"{self.folder}/events").parquet(f"{self.folder}/events/*").withColumn("batch_id", F.col("batch_id").cast("long"))
        if first is not None:
            log = log.where(F.col("batch_id") >= first)
        return log if last is None else log.where(F.col("batch_id") <= last)

    def keep_report(self, window_end: int, rows: list[tuple]) -> None:
        self.spark.createDataFrame([(key, n, rank) for _, key, n, rank in rows], "key string, wfreq long, rank long").write.mode("overwrite").parquet(f"{self.folder}/topk/window_end={window_end}")

    def reports(self) -> DataFrame:
        """(window_end, key, wfreq, rank) of all windows so far."""
        out = self.spark.read.option("basePath", f"{self.folder}/topk").parquet(f"{self.folder}/topk/*")
        return out.select(F.col("window_end").cast("long").alias("window_end"), "key", "wfreq", "rank")


def run_available(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Runs a stream over all that is available now, micro-batch by micro-batch."""
    query = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


def replay_counts(spark: SparkSession, sf_dir: str, span: int, ell: int) -> DataFrame:
    """The count matrix of the events table, arrived as a stream of files."""
    ledger = EventLedger(spark)

    def each(df: DataFrame, epoch: int) -> None:
        ledger.append(adapters.with_batches(adapters.adapt(df, F.col("ts"), F.col("event_type"), place=F.col("event_id")), span), epoch)

    run_available(file_stream(spark, f"{sf_dir}/events.parquet*"), each, f"{ledger.folder}/checkpoint")
    frame = ledger.read()
    symbols = frame.select("symbol").distinct()
    return counting.count(batching.sequences(frame, ties=False), counting.enumerate_all(symbols, ell), ell, ties=False).select("batch_id", "key", "freq")


@dataclass
class StreamMiner:
    """foreachBatch handler that mines each batch once, after the watermark has passed its end.

    policy 'drop': events of closed batches go to the late side table; 'reopen': the lattice is redone
    from the reopened batch on, which corrects at most m windows.
    """

    spark: SparkSession
    spec: VariantSpec
    params: MineParams
    lateness: int = 0
    policy: str = "drop"
    ledger: EventLedger | None = None
    closed: int | None = None
    high: int | None = None
    result: lattice.RunResult = field(default_factory=lambda: lattice.RunResult([], {}, []))
    symbols: set = field(default_factory=set)
    late_events: int = 0

    def __post_init__(self):
        if self.policy not in ("drop", "reopen"):
            raise ValueError("policy is 'drop' or 'reopen'")
        self.spec.checked(self.params.m)
        self.ledger = self.ledger or EventLedger(self.spark)

    def __call__(self, frame: DataFrame, epoch: int) -> None:
        rows = adapters.with_batches(frame, self.params.span)
        low, top = rows.agg(F.min("batch_id"), F.max("tick")).first()
        if top is None:
            return
        if self.closed is not None and low <= self.closed:
            if self.policy == "drop":
                late = rows.where(F.col("batch_id") <= self.closed)
                late.write.mode("overwrite").parquet(f"{self.ledger.folder}/late/epoch={epoch}")
                self.late_events += late.count()
                rows = rows.where(F.col("batch_id") > self.closed)
            else:
                self.closed = low - 1
        self.ledger.append(rows, epoch)
        self.high = max(top, self.high if self.high is not None else top)
        self.close((self.high - self.lateness) // self.params.span - 1)

    def finish(self) -> lattice.RunResult:
        """Closes everything that has arrived."""
        if self.high is not None:
            self.close(self.high // self.params.span)
        return self.result

    def close(self, last: int) -> None:
        """Mines the batches up to `last` that are not closed yet; batches before them are not read again."""
        if self.closed is not None and last <= self.closed:
            return
        frame = self.ledger.read(None if self.closed is None else self.closed + 1, last)
        first = frame.agg(F.min("batch_id")).first()[0] if self.closed is None else self.closed + 1
        if first is None:
            return
        # a frame with places (adapters.adapt) holds events that are steps of their own, also within a tick
        seqs = written(batching.sequences(frame, slices=self.params.slices, ties="place" not in frame.columns), "batch_id")
        known = self.spark.createDataFrame([(x,) for (x,) in self.symbols], "symbol string")
        self.symbols |= {(r.symbol,) for r in batching.new_symbols(frame, known).collect()}
        for s in [j for j in self.result.lattices if j >= first]:
            del self.result.lattices[s], self.result.known[s]
        self.result.stats = [st for st in self.result.stats if st.batch_id < first]
        self.result.topk = [r for r in self.result.topk if r[0] < first]
        theta_of = lambda delta: slack(self.spec.name, self.params.m, self.spec.v, delta)
        for s in range(first, last + 1):
            prev, seen = self.result.lattices.get(s - 1), {}
            counter = lattice.spark_counter(seqs, s, self.params.klass)

            def count(patterns, counter=counter, seen=seen):
                got = counter(patterns)
                seen.update({p: got.get(p, 0) for p in patterns})
                return got

            lat, stats = lattice.advance(prev, count, self.symbols, self.params, theta_of, lattice.delta_rule(self.params), s)
            lattice.take_in(self.result, lat, stats, prev, seen, self.params)
            rows = lattice.report(self.result, s, self.spec, self.params)
            if rows:
                self.result.topk += rows
                self.ledger.keep_report(s, rows)
        self.closed = last
        # a reopened batch redoes its windows from lattices of the m batches before; older ones are never used again
        for s in [j for j in self.result.lattices if j <= last - 2 * self.params.m]:
            del self.result.lattices[s], self.result.known[s]


def keyed_counts(frame: DataFrame, nodes: list[tuple[str, ...]]) -> DataFrame:
    """Per stream key, running frequencies of given serial episodes over an unbounded stream (update mode).

    The state of a key is one move counter per episode and the tick reached; events of one call are
    ordered by tick, and events at or before the tick reached are ignored as late.
    """
    import pandas as pd

    out = T.StructType([T.StructField("stream_key", T.StringType()), T.StructField("key", T.StringType()), T.StructField("freq", T.LongType())])
    state_type = T.StructType([T.StructField("moves", T.ArrayType(T.LongType())), T.StructField("tick", T.LongType())])

    def run(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        moves, reached = (list(state.get[0]), state.get[1]) if state.exists else ([0] * len(nodes), -(2**62))
        rows = pd.concat(list(frames)).sort_values("tick")
        for tick, group in rows.groupby("tick"):
            if tick <= reached:
                continue
            reached, here = tick, set(group["symbol"])
            for i, p in enumerate(nodes):
                moves[i] += p[moves[i] % len(p)] in here
        state.update((moves, int(reached)))
        yield pd.DataFrame({"stream_key": key[0], "key": [">".join(p) for p in nodes], "freq": [m // len(p) for m, p in zip(moves, nodes)]})

    return frame.groupBy("stream_key").applyInPandasWithState(run, out, state_type, "update", "NoTimeout")


def session_batches(frame: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Sessions of each key stream as an alternative to equal time batches."""
    return frame.groupBy("stream_key", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n_events")).select("stream_key", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n_events")
