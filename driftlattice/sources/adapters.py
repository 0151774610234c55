"""Tables as event frames, and the synthetic streams.

An event frame has (stream_key string, ts timestamp_ntz, tick long, symbol string); tick counts
microseconds from a fixed origin in wall-clock time, never through a session's time zone.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

ORIGIN = "2024-01-01 00:00:00"
DAY = 86_400_000_000

EVENT_FRAME = T.StructType([
    T.StructField("stream_key", T.StringType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("tick", T.LongType()), T.StructField("symbol", T.StringType()),
])


def micros(ts: Column, origin: str = ORIGIN) -> Column:
    """Microseconds of a timestamp_ntz since the origin."""
    return F.timestamp_diff("MICROSECOND", F.lit(origin).cast("timestamp_ntz"), ts.cast("timestamp_ntz"))


def adapt(df: DataFrame, ts: Column | None, symbol: Column, key: Column | None = None, tick: Column | None = None, origin: str = ORIGIN, place: Column | None = None) -> DataFrame:
    """Any table as an event frame; `tick` replaces time where order is given by a number. Rows without time or symbol are refused by validate_events, dropped here.

    place: orders events of one tick where each of them counts as a step of its own (sequences with ties=False); a further column then.
    """
    when = ts.cast("timestamp_ntz") if ts is not None else F.lit(None).cast("timestamp_ntz")
    at = tick.cast("long") if tick is not None else micros(ts, origin)
    out = df.select((key.cast("string") if key is not None else F.lit("all")).alias("stream_key"), when.alias("ts"), at.alias("tick"), symbol.cast("string").alias("symbol"), *([place.alias("place")] if place is not None else []))
    return out.where(F.col("tick").isNotNull() & F.col("symbol").isNotNull())


def validate_events(df: DataFrame) -> DataFrame:
    """The same frame; raises on a wrong schema, and at run time on a null tick or symbol."""
    have = {f.name: f.dataType for f in df.schema}
    for f in EVENT_FRAME:
        if have.get(f.name) != f.dataType:
            raise ValueError(f"an event frame needs {f.name} {f.dataType.simpleString()}, not {have.get(f.name)}")
    bad = F.col("tick").isNull() | F.col("symbol").isNull()
    return df.withColumn("tick", F.when(bad, F.raise_error(F.lit("an event needs a tick and a symbol")).cast("long")).otherwise(F.col("tick")))


def events(spark: SparkSession, sf_dir: str, symbol: Column | None = None, key: Column | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/events.parquet")
    return adapt(df, F.col("ts"), F.col("event_type") if symbol is None else symbol, key, place=F.col("event_id"))


def event_files(spark: SparkSession, path: str, kind: str = "parquet", schema: str = "ts timestamp_ntz, symbol string, key string", ts: str = "ts", symbol: str = "symbol", key: str | None = None, **options) -> DataFrame:
    """Files of events (parquet, orc, csv, json) as an event frame; rows without time or symbol raise when they are read.

    The schema is given, never inferred, so that no pass over the files is spent on it.
    """
    if kind not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"no reader for {kind!r}")
    rows = spark.read.format(kind).schema(schema).options(**options).load(path)
    frame = rows.select((F.col(key).cast("string") if key else F.lit("all")).alias("stream_key"), F.col(ts).cast("timestamp_ntz").alias("ts"), micros(F.col(ts)).alias("tick"), F.col(symbol).cast("string").alias("symbol"))
    return validate_events(frame)


def with_batches(frame: DataFrame, span: int) -> DataFrame:
    """Adds batch_id = floor(tick / span): batches are half-open and equal in time."""
    return frame.withColumn("batch_id", F.floor(F.col("tick") / F.lit(span)).cast("long"))


def composite(props: Column, name: str = "k") -> Column:
    """A JSON property as a part of a symbol."""
    return F.get_json_object(props, f"$.{name}")


def tag_symbols(html: Column) -> Column:
    return F.regexp_extract_all(F.lower(html), F.lit(r"<([a-z][a-z0-9]*)"), 1)


#: Microseconds between the base events of a planted stream.
STEP = 1000


def planted_span(events_df: DataFrame, batches: int) -> int:
    """Batch span that parts the base events of a planted stream into at most so many batches, each of the same whole hundreds of events."""
    n = (events_df.agg(F.max("event_id")).first()[0] or 0) + 1
    return -(-n // (100 * batches)) * 100 * STEP


def planted_stream(events_df: DataFrame, alphabet: int, n_patterns: int, noise_copies: int = 1, span: int = 400 * STEP, drift: tuple[tuple[int, int], ...] = (), ell: int = 4) -> DataFrame:
    """Noise of a power law plus planted serial episodes whose rates drift from batch to batch.

    Arithmetic over event_id = 0, 1, ... only, so that any engine rebuilds the same stream. Base event e
    is at e * STEP; it yields noise symbols (the share of the r most frequent of A symbols is the root
    of r / A), and each pattern p emits its nodes in a burst of its own when its test holds: in every ten
    base events about rate / 100 times, at scattered places, rate in parts of a thousand. Rates are close
    to each other, rise and fall slowly in different phases, and drift in opposite directions, for even
    and odd p, within the drift intervals (of batches of `span`).
    """
    e = F.col("event_id")
    batch = F.floor(e * STEP / F.lit(span))
    ramp = F.lit(0)
    for lo, hi in drift:
        ramp = ramp + (F.greatest(F.lit(lo - 1), F.least(batch, F.lit(hi))) - (lo - 1))
    noise = []
    for c in range(noise_copies):
        noise.append(F.struct((e * STEP + c).alias("tick"), F.concat(F.lit("n"), F.expr(f"({alphabet}L * (event_id * {7919 + 2 * c} % 10007) * (event_id * {7919 + 2 * c} % 10007)) div (10007L * 10007)").cast("string")).alias("symbol")))
    block = F.floor(e / 10)

    def emitted(p):
        rate = 350 + 7 * p % 20 + F.abs((5 * p + batch) % 24 - 12) + F.when(p % 2 == 0, 3).otherwise(-3) * ramp
        shift = (block * block * 31 + block * p * 17 + p * 613) % 1009 % 10
        times = (block * 17 + block * block * p * 7 + p * 31) % 1013 % 10 + 1
        place = ((e % 10 + shift) % 10 + 1) * times % 11 - 1  # a permutation of each ten events
        fires = place * 100 + (block * 37 + p * 11) % 100 < rate
        nodes = F.array(*[F.struct((e * STEP + 100 + 8 * p + i).alias("tick"), F.concat(F.lit("p"), p.cast("string"), F.lit(f"_{i}")).alias("symbol")) for i in range(ell)])
        return F.when(fires, nodes).otherwise(F.array().cast("array<struct<tick:bigint,symbol:string>>"))

    bursts = F.flatten(F.transform(F.sequence(F.lit(0).cast("long"), F.lit(n_patterns - 1).cast("long")), emitted))
    rows = events_df.select("event_id").select(F.explode(F.concat(F.array(*noise), bursts)).alias("x"))
    out = rows.select(F.lit("all").alias("stream_key"), F.col("x.tick").cast("long").alias("tick"), F.col("x.symbol").alias("symbol"))
    return out.withColumn("ts", F.timestamp_add("MICROSECOND", F.col("tick"), F.lit(ORIGIN).cast("timestamp_ntz"))).select("stream_key", "ts", "tick", "symbol")


def planted_places(ids: np.ndarray, alphabet: int, n_patterns: int, noise_copies: int = 1, span: int = 400 * STEP, drift: tuple[tuple[int, int], ...] = (), ell: int = 4) -> dict[str, np.ndarray]:
    """What planted_stream makes of some base events (ids from 0 on), as the sorted ticks of each symbol; no tick holds two symbols."""
    e = np.unique(ids)
    out: dict[str, np.ndarray] = {}
    if not len(e):
        return out
    at = np.concatenate([e * STEP + c for c in range(noise_copies)])
    roots = np.concatenate([e * (7919 + 2 * c) % 10007 for c in range(noise_copies)])
    noise = alphabet * roots * roots // (10007 * 10007)
    low, width = at.min(), np.ptp(at) + 1
    noise, at = np.divmod(np.sort(noise * width + (at - low)), width)
    edges = np.flatnonzero(np.diff(noise, prepend=-1))
    out.update((f"n{noise[first]}", ticks) for first, ticks in zip(edges, np.split(at + low, edges[1:])))
    batch, (blocks, of) = e * STEP // span, np.unique(e // 10, return_inverse=True)
    ramp = sum((np.maximum(lo - 1, np.minimum(batch, hi)) - (lo - 1) for lo, hi in drift), np.zeros_like(batch))
    for p in range(n_patterns):
        rate = 350 + 7 * p % 20 + np.abs((5 * p + batch) % 24 - 12) + (3 if p % 2 == 0 else -3) * ramp
        shift = (blocks * blocks * 31 + blocks * p * 17 + p * 613) % 1009 % 10
        times = (blocks * 17 + blocks * blocks * p * 7 + p * 31) % 1013 % 10 + 1
        place = ((e % 10 + shift[of]) % 10 + 1) * times[of] % 11 - 1
        first = e[place * 100 + ((blocks * 37 + p * 11) % 100)[of] < rate] * STEP + 100 + 8 * p
        if len(first):
            out.update((f"p{p}_{i}", first + i) for i in range(ell))
    return out


def poisson_stream(spark: SparkSession, alphabet: int, rest_hz: float, patterns: list[list[int]], batches: int, batch_seconds: float, strength_hz: float = 1.0, seed: int = 42) -> DataFrame:
    """Poisson noise with power-law rates and planted episodes whose rates walk at random from batch to batch.

    Seeded and made in parallel: one row per batch and source, events by exponential gaps.
    """
    harmonic = sum(1.0 / (r + 1) for r in range(alphabet))
    total = rest_hz * min(alphabet, 50)
    sources = spark.range(batches * (alphabet + len(patterns))).select((F.col("id") % batches).alias("batch"), F.floor(F.col("id") / batches).alias("source"))
    walk = 1 + 0.5 * F.sin(F.col("batch") * (0.3 + 0.07 * F.col("source")) + F.col("source"))
    rate = F.when(F.col("source") < alphabet, F.lit(total / harmonic) / (F.col("source") + 1)).otherwise(F.lit(strength_hz) * walk)
    n = F.greatest(F.lit(0), F.round(rate * batch_seconds + F.sqrt(rate * batch_seconds) * F.randn(seed))).cast("int")
    made = sources.withColumn("n", n).where("n > 0").select("batch", "source", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i"))
    span = int(batch_seconds * 1_000_000)
    made = made.withColumn("tick", (F.col("batch") * span + F.floor(F.rand(seed + 1) * span)).cast("long"))
    lists = F.array(*[F.array(*[F.lit(f"s{x}") for x in p]) for p in patterns]) if patterns else F.array(F.array(F.lit("")))
    symbols = F.when(F.col("source") < alphabet, F.array(F.concat(F.lit("s"), F.col("source").cast("string")))).otherwise(F.element_at(lists, (F.greatest(F.col("source") - alphabet, F.lit(0)) + 1).cast("int")))
    out = made.select("tick", F.posexplode(symbols).alias("i", "symbol")).withColumn("tick", F.col("tick") + 1000 * F.col("i"))
    return out.select(F.lit("all").alias("stream_key"), F.timestamp_add("MICROSECOND", F.col("tick"), F.lit(ORIGIN).cast("timestamp_ntz")).alias("ts"), "tick", "symbol")
