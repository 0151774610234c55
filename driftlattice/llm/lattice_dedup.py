"""Embedding near-dedup by lattice hashing on E8.

Unit vectors are projected to 8 dimensions by seeded orthonormal maps, scaled, shifted and decoded
to the nearest point of the E8 lattice. A table's cell is named by the points of several such blocks
of 8 dimensions, and a vector also probes the PROBES neighbouring cells it is closest to, so a pair
split by a cell wall is still met. Pairs met in any table are verified by cosine in double precision.

Blocks and tables follow the number n of vectors (plan_of): one block lets about 1 in SELECTIVITY of
unrelated pairs meet, so ln n / ln SELECTIVITY blocks keep the unrelated vectors that a vector meets
in a table below a constant; every block more loses a part of the pairs at the threshold, which twice
the tables make up for. The chance that a pair of cosine 0.98 meets is 0.984, 0.65, 0.37 and 0.19 a
table of one to four blocks, in 16 to 768 dimensions alike, so at most about 1 in 1,000 such pairs is
missed at any n up to 2.5e10; tests measure both rates.

Only vectors of one label and one dimension meet. Bitwise equal vectors of a label are one class
and are never expanded into pairs.

Defined cases: null labels, and vectors that are null, empty, zero or hold null or non-finite
components, link with nothing and are their own component; a null id is returned with a null
component and links with nothing; repeated rows of an id are one vector; ties in cosine are all linked; other
columns are ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import components, mix, written

COSINE = 0.98
TABLES = 4
SELECTIVITY = 400
PROBES = 6
SCALE = 6.0


def plan_of(n: int) -> tuple[int, int]:
    """Blocks a cell and number of tables for n vectors."""
    blocks = max(1, math.ceil(math.log(max(2, n)) / math.log(SELECTIVITY)))
    return blocks, TABLES << (blocks - 1)


def shortest_vectors() -> np.ndarray:
    """The 240 shortest vectors of E8: two entries of +-1, or eight of +-1/2 with an even number of minus signs."""
    out = []
    for i in range(8):
        for j in range(i):
            for a in (-1, 1):
                for b in (-1, 1):
                    v = np.zeros(8)
                    v[i], v[j] = a, b
                    out.append(v)
    signs = np.array([[1 - 2 * (k >> b & 1) for b in range(8)] for k in range(256)])
    return np.concatenate([np.array(out), signs[signs.prod(1) > 0] / 2])


def nearest_even(x: np.ndarray) -> np.ndarray:
    """Nearest whole point with an even coordinate sum."""
    point = np.rint(x)
    odd = np.flatnonzero(point.sum(1) % 2 != 0)
    gap = x[odd] - point[odd]
    worst = np.abs(gap).argmax(1)
    rows = np.arange(len(odd))
    point[odd, worst] += np.where(gap[rows, worst] >= 0, 1, -1)
    return point


def decode(x: np.ndarray) -> np.ndarray:
    """Nearest E8 point of each row: the better of the even whole points and their half-shifted copy."""
    whole, half = nearest_even(x), nearest_even(x - 0.5) + 0.5
    closer = ((x - half) ** 2).sum(1) < ((x - whole) ** 2).sum(1)
    return np.where(closer[:, None], half, whole)


def projections(dim: int, table: int, blocks: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng([seed, dim, table])
    wide = max(dim, 8 * blocks)
    q, _ = np.linalg.qr(rng.standard_normal((wide, 8 * blocks)))
    return q[:dim] * np.sqrt(wide / 64), rng.random(8 * blocks)


def cells(unit: np.ndarray, table: int, blocks: int, probes: int, scale: float) -> np.ndarray:
    """Cell names of each vector: its own, then the closest neighbours' (shifts of one block)."""
    rng = np.random.default_rng([7, table])
    weights = rng.integers(1, 2**62, 8 * blocks, dtype=np.int64).astype(np.uint64)
    maps, shift = projections(unit.shape[1], table, blocks)
    x = unit @ maps * scale + shift
    near = shortest_vectors()
    home = np.concatenate([decode(x[:, 8 * k : 8 * k + 8]) for k in range(blocks)], 1)
    name = ((2 * home).astype(np.int64).astype(np.uint64) * weights).sum(1, dtype=np.uint64)
    pull = np.concatenate([(x - home)[:, 8 * k : 8 * k + 8] @ near.T for k in range(blocks)], 1)
    best = np.argpartition(-pull, probes, 1)[:, :probes]
    step = np.concatenate([((2 * near).astype(np.int64).astype(np.uint64) * weights[None, 8 * k : 8 * k + 8]).sum(1, dtype=np.uint64) for k in range(blocks)])
    return np.concatenate([name[:, None], name[:, None] + step[best]], 1)


def lattice_keys(vectors: DataFrame, tables: int, blocks: int, probes: int, scale: float) -> DataFrame:
    """vectors(id long, tag long, unit array<double>) -> (cell long, id long, home boolean)."""

    def run(batches):
        for batch in batches:
            ids, tags = batch.column("id").to_numpy(), batch.column("tag").to_numpy().astype(np.int64).view(np.uint64)
            column = batch.column("unit")
            size = np.diff(column.offsets.to_numpy())
            flat, ends = column.flatten().to_numpy(), np.cumsum(size)
            for dim in np.unique(size):
                rows = np.flatnonzero(size == dim)
                unit = flat[(ends[rows] - dim)[:, None] + np.arange(dim)]
                for t in range(tables):
                    name = mix(cells(unit, t, blocks, probes, scale) ^ mix(tags[rows] + np.uint64(t * 1_000_003 + int(dim)))[:, None])
                    home = np.zeros(name.shape, bool)
                    home[:, 0] = True
                    yield pa.RecordBatch.from_arrays([pa.array(name.ravel().view(np.int64)), pa.array(np.repeat(ids[rows], name.shape[1])), pa.array(home.ravel())], ["cell", "id", "home"])

    return vectors.mapInArrow(run, "cell long, id long, home boolean")


def linked_vectors(table: DataFrame, cosine: float = COSINE, plan: tuple[int, int] | None = None, probes: int = PROBES, scale: float = SCALE) -> DataFrame:
    """table(vec_id, embedding, label) -> (vec_id, n_links, component_id, kept). plan: blocks and tables other than plan_of() has."""
    raw = table.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"), F.col("label").cast("string").alias("label"))
    sound = F.col("label").isNotNull() & F.col("vec_id").isNotNull() & F.coalesce(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))), F.lit(False)) & F.coalesce(F.exists("v", lambda x: x != 0), F.lit(False))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    # divided by the largest component first, so that neither tiny nor huge vectors lose their norm
    top = F.array_max(F.transform("v", F.abs))
    rows = raw.where(sound).withColumn("v", F.transform("v", lambda x: x / top))
    classes = rows.groupBy("label", "v").agg(F.min("vec_id").alias("id"), F.countDistinct("vec_id").alias("copies"))
    classes = written(classes.select("id", "copies", F.xxhash64("label").alias("tag"), "label", "v", F.transform("v", lambda x: x / norm).alias("unit")))
    blocks, tables = plan or plan_of(classes.count())
    keys = written(lattice_keys(classes.select("id", "tag", "unit"), tables, blocks, probes, scale))
    home = keys.where("home").select("cell", F.col("id").alias("a"))
    probe = keys.select("cell", F.col("id").alias("b"))
    pairs = home.join(probe, "cell").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    one = classes.select(F.col("id").alias("a"), F.col("unit").alias("u"), F.col("label").alias("la"), F.col("copies").alias("ma"))
    two = classes.select(F.col("id").alias("b"), F.col("unit").alias("w"), F.col("label").alias("lb"), F.col("copies").alias("mb"))
    product = F.aggregate(F.zip_with("u", "w", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    links = written(pairs.join(one, "a").join(two, "b").where((F.col("la") == F.col("lb")) & (F.size("u") == F.size("w")) & (product >= cosine)).select("a", "b", "ma", "mb"))
    degree = links.select(F.col("a").alias("id"), F.col("mb").alias("m")).unionByName(links.select(F.col("b").alias("id"), F.col("ma").alias("m"))).groupBy("id").agg(F.sum("m").alias("others"))
    placed = components(classes.select("id"), links)
    label = classes.join(degree, "id", "left").join(placed, "id").select("label", "v", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.col("component").alias("component_id"))
    linked = rows.select("vec_id", "label", "v").distinct().join(label, ["label", "v"]).select("vec_id", "n_links", "component_id")
    alone = raw.where(~sound).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionByName(alone).select("vec_id", "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linked_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
