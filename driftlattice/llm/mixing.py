"""Mixing sources to target weights by capped water-filling (native: DataFrame functions only).

A source's target is its weight's share of the total size, but at most `epochs` times its own
size; what a clamped source cannot take is dealt to the others in proportion to their weights
until no target is above its cap. The fixed point of that redistribution is one water level L
with target = min(cap, weight * L): sorting the sources by cap / weight and taking running sums
finds it in one pass, without a loop.

A target is met by whole repetitions of every document plus one more repetition of some of them:
documents are ordered by a seeded digest of their id and taken until the rest is used up; the one
that the cut falls into is taken if that ends nearer to the target. The order is cut in two steps, first over digest buckets (sums per source and bucket), then over the
documents of the one bucket where the cut falls, so no task ever holds a source.

Defined cases: null or blank text has size 0 and takes nothing; a null source is a source of its
own, ranked last; an empty table gives an empty result; repeated ids share their digest, so their
order among each other does not change any sum; other columns of the table are ignored, or carried
along where `keep` names them, whatever their names but those of the result.

Sources are ranked in one task (a row each, cycling weights need their order); everything else is per
source and digest bucket.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftlattice.llm.shared import field, word_count, written

EPOCHS = 3
WEIGHTS = (1, 2, 3)
SEED = "mix-1"
#: Hex digits of the digest that name a bucket: 4096 buckets a source.
PREFIX = 3


def source_sizes(sized: DataFrame) -> DataFrame:
    return sized.groupBy("source").agg(F.sum("size").alias("source_size"))


def water_fill(sources: DataFrame, total=None, epochs: int = EPOCHS) -> DataFrame:
    """(source, source_size, weight) -> the same with `target` double.

    total: size of the whole mix (default: the sum of all sizes). Rows are one per source.
    """
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    by_level = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    onward = by_level.rowsBetween(0, Window.unboundedFollowing)
    out = (
        sources.withColumn("cap", epochs * F.col("source_size"))
        .withColumn("all_sizes", F.sum("source_size").over(everything) if total is None else F.lit(total))
        .withColumn("rest", F.col("all_sizes") - F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("rest_weight", F.sum("weight").over(onward))
        # the level if this source and all later ones are not clamped
        .withColumn("free", F.col("cap") * F.col("rest_weight") >= F.col("rest") * F.col("weight"))
    )
    level = F.first(F.when(F.col("free"), F.struct("rest", "rest_weight")), True).over(by_level.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return out.withColumn("level", level).select(
        "source", "source_size", "weight",
        F.when(F.col("cap") * F.col("level.rest_weight") <= F.col("level.rest") * F.col("weight"), F.col("cap").cast("double"))
        .when(F.col("level").isNull(), F.col("cap").cast("double"))
        .otherwise(F.col("weight") * F.col("level.rest").cast("double") / F.col("level.rest_weight"))
        .alias("target"),
    )


def cycling_weights(sizes: DataFrame, weights=WEIGHTS) -> DataFrame:
    """Weights dealt to the sources in code point order, null last, over and over."""
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    return sizes.withColumn("weight", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(place, F.lit(len(weights))) + 1).cast("int")).cast("long"))


def mix(docs: DataFrame, epochs: int = EPOCHS, weights=WEIGHTS, seed: str = SEED, keep=()) -> DataFrame:
    """documents -> (doc_id, *keep, size, source_size, target, taken).

    taken = size * (whole repetitions of its source) + size once more for documents whose place
    in the seeded order lies within the fractional part. `keep` names columns to carry along.
    """
    digest = F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))))
    own = {"doc_id", "size", "source_size", "target", "taken"}
    if clash := [c for c in keep if c.lower() in own]:
        raise ValueError(f"a kept column is called {clash[0]}, like one of the result")
    # kept columns travel in one struct, so none of their names meets ours
    carried = [F.struct(*[field(c) for c in keep]).alias("carried")] if keep else []
    sized = written(docs.select("doc_id", "source", *carried, word_count(F.col("text").cast("string")).alias("size"), digest.alias("digest")))
    sized = sized.withColumn("bucket", F.substring("digest", 1, PREFIX))
    buckets = sized.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size"))
    targets = water_fill(cycling_weights(buckets.groupBy("source").agg(F.sum("bucket_size").alias("source_size"))), None, epochs)
    targets = targets.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)))
    targets = targets.withColumn("extra", F.round(F.col("target") - F.col("whole") * F.col("source_size")).cast("long"))
    run = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    targets = targets.withColumnRenamed("source", "of")
    cuts = buckets.join(targets, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    cuts = written(cuts.withColumn("before", F.coalesce(F.sum("bucket_size").over(run), F.lit(0))))
    cuts = cuts.select(F.col("source").alias("s"), F.col("bucket").alias("k"), "bucket_size", "source_size", "target", "whole", "extra", "before")
    # one row per source and bucket: at most 4096 a source, whatever the number of documents
    placed = sized.join(F.broadcast(cuts) if _small(cuts) else cuts, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("k")))
    in_cut = (F.col("before") < F.col("extra")) & (F.col("before") + F.col("bucket_size") > F.col("extra"))
    order = Window.partitionBy("s", "k").orderBy("digest", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = ["doc_id", *[F.col("carried")[c].alias(c) for c in keep], "size", "source_size", "target"]
    settled = placed.where(~in_cut).select(*out, (F.col("size") * (F.col("whole") + (F.col("before") + F.col("bucket_size") <= F.col("extra")).cast("long"))).alias("taken"))
    split = placed.where(in_cut).withColumn("upto", F.col("before") + F.sum("size").over(order))
    # the document that the cut falls into has extra between upto - size and upto
    more = (F.col("upto") - F.col("size") < F.col("extra")) & (2 * F.col("upto") - F.col("size") < 2 * F.col("extra"))
    split = split.select(*out, (F.col("size") * (F.col("whole") + ((F.col("upto") <= F.col("extra")) | more).cast("long"))).alias("taken"))
    return settled.unionByName(split)


def _small(cuts: DataFrame, most: int = 200_000) -> bool:
    """Whether the cuts may be broadcast: their count is checked, never assumed."""
    return cuts.limit(most + 1).count() <= most


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "size", "source_size", "target", "taken")


_SIZE = r"len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> ''))"

#: Rows of mix() over a relation with doc_id, source and text.
MIX_SQL = """
sized AS MATERIALIZED (SELECT *, {size} AS size, md5('mix-1:' || coalesce(CAST(doc_id AS VARCHAR), 'null')) AS digest FROM {table}),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
weighed AS (SELECT *, 1 + (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 AS weight, 3 * source_size AS cap FROM sources),
levels AS (
  SELECT *, (SELECT CAST(sum(source_size) AS BIGINT) FROM sources) - coalesce(CAST(sum(cap) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS rest,
    CAST(sum(weight) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS rest_weight
  FROM weighed),
lvl AS (SELECT rest AS r, rest_weight AS rw FROM levels WHERE cap * rest_weight >= rest * weight ORDER BY cap / weight, source ASC NULLS LAST LIMIT 1),
targets AS (
  SELECT source, source_size, CASE WHEN cap * rw <= r * weight THEN CAST(cap AS DOUBLE) ELSE weight * CAST(r AS DOUBLE) / rw END AS target FROM levels, lvl),
parts AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM targets),
mixed AS (
  SELECT d.*, p.source_size, p.target, p.whole, CAST(round(p.target - p.whole * p.source_size) AS BIGINT) AS extra,
    CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.digest, d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS upto
  FROM sized d JOIN parts p ON d.source IS NOT DISTINCT FROM p.source)
"""
SQL = "WITH " + MIX_SQL.format(table="documents", size=_SIZE) + "SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target, CAST(size * (whole + CASE WHEN upto <= extra OR upto - size < extra AND 2 * upto - size < 2 * extra THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM mixed"
