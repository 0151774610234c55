"""Tools that several operators share: Arrow text buffers, rolling hashes, components.

The hash tools work on whole Arrow batches: all texts of a slice lie in one byte
buffer, word borders come from a mask, and every hash of a span is a difference
of two prefix sums, so no Python code runs per word.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from driftlattice.sources.ledger import dropped, written  # noqa: F401

#: Text bytes handled at once by the numpy kernels; a longer single text is still handled whole.
SLICE_BYTES = 2 << 20

WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def table_bytes(df: DataFrame) -> int:
    """Size of a table with doc_id and text: the optimizer's (from file sizes, no job), or the sum of its text bytes where the optimizer has none."""
    known = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if known < 1 << 60:
        return known
    return int(df.agg(F.coalesce(F.sum(F.octet_length(F.col("text").cast("string"))), F.lit(0))).first()[0])


def released() -> None:
    """Gives memory that is free in this process back to the system. Python workers live on from stage to stage, and what they hold adds to an executor's need."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError, TypeError):  # a C library without it
        pass


def lean(run):
    """A function of mapInArrow that gives its memory back when a task is done."""

    def mapped(batches):
        try:
            yield from run(batches)
        finally:
            released()

    return mapped


def word_count(text):
    """Column: number of whitespace-separated words of a text, 0 for null."""
    parts = F.split(F.coalesce(text, F.lit("")), GAP)
    empty = lambda c: F.when(c == "", 1).otherwise(0)
    return (F.size(parts) - empty(F.element_at(parts, 1)) - F.when(F.size(parts) > 1, empty(F.element_at(parts, -1))).otherwise(0)).cast("long")


def let(value, fn):
    """Column: fn(value) with the value computed once, where fn's expression would compute it at each use."""
    return F.element_at(F.transform(F.array(value), fn), 1)


def fresh(columns, name: str) -> str:
    """`name`, or with leading underscores until no column is called so (Spark's names ignore case)."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def field(name: str):
    """The column of exactly this name, dots and all."""
    return F.col("`" + name.replace("`", "``") + "`")


# ---------------------------------------------------------------- maps over whole texts


def text_map(docs: DataFrame, keep, added: str, run) -> DataFrame:
    """docs(text, *keep) -> (*keep, columns of the DDL `added`): run() makes the added columns of a batch's texts, an iterator of them over batches' texts.

    Kept columns pass through untouched, whatever their names; an added name that is among them is refused.
    """
    new = T._parse_datatype_string(added) if isinstance(added, str) else added
    clash = [f.name for f in new if fresh(keep, f.name) != f.name]
    if clash:
        raise ValueError(f"a kept column is called {clash[0]}, like a new one")
    source = docs.select(*[field(c) for c in keep], F.col("text").cast("string"))
    names, plain = [*keep, *new.names], [f"c{k}" for k in range(len(keep) + len(new))]
    schema = T.StructType([T.StructField(c, f.dataType) for c, f in zip(plain, [*source.schema.fields[:-1], *new.fields])])

    def mapped(batches):
        work = run()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *work(batch.columns[-1])], plain)

    return source.toDF(*plain[: len(keep)], "text").mapInArrow(lean(mapped), schema).toDF(*names)


def text_filter(docs: DataFrame, run) -> DataFrame:
    """The rows of docs whose texts run() says to keep (a function from a batch's texts to a mask); only these rows travel back, once."""
    at = docs.columns.index("text")
    plain = docs.toDF(*[f"c{k}" for k in range(len(docs.columns))])  # any name will do outside

    def filtered(batches):
        keep = run()
        for batch in batches:
            yield batch.filter(pa.array(keep(batch.columns[at].cast(pa.string()))))

    return plain.mapInArrow(lean(filtered), plain.schema).toDF(*docs.columns)


# ---------------------------------------------------------------- Arrow text buffers


def text_buffer(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All texts of a column as one uint8 buffer and its n + 1 offsets; null is the empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    column = column.cast(pa.large_string())
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def row_slices(column: pa.Array | pa.ChunkedArray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts hold at most `most` bytes together (or one row)."""
    n = len(column)
    if not n:
        return
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False) if isinstance(column, pa.Array) else pc.fill_null(pc.binary_length(column), 0).to_numpy()
    end = np.cumsum(size.astype(np.int64))
    first, base = 0, 0
    while first < n:
        last = max(first + 1, int(np.searchsorted(end, base + most, "right")))
        yield first, last
        base, first = int(end[last - 1]), last


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: each bit of the input moves about half of the output's bits."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(32))


class Hasher:
    """Polynomial prefix hashes mod 2^64 over bytes (for words) and over word hashes (for windows)."""

    def __init__(self, seed: int, lower: bool = False):
        rng = np.random.default_rng(seed)
        self.table = rng.integers(1, 2**63, 256, dtype=np.uint64)
        if lower:
            self.table[65:91] = self.table[97:123]
        base = rng.integers(1, 2**62, 2, dtype=np.uint64) * np.uint64(4) + np.uint64(3)
        self.bases = [int(x) for x in base]
        self.inverses = [pow(x, -1, 2**64) for x in self.bases]
        self.kept: dict[tuple[int, bool], np.ndarray] = {}

    def powers(self, which: int, n: int, inverse: bool = False) -> np.ndarray:
        have = self.kept.get((which, inverse))
        if have is None or len(have) < n:
            steps = np.full(max(n, 1 << 16), (self.inverses if inverse else self.bases)[which], np.uint64)
            steps[0] = 1
            have = self.kept[which, inverse] = np.cumprod(steps, dtype=np.uint64)
        return have[:n]

    def words(self, raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of each span [start, end) of the buffer."""
        sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(self.table[raw] * self.powers(0, len(raw)), out=sums[1:])
        return mix((sums[end] - sums[start]) * self.powers(0, len(raw), True)[start] + (end - start).astype(np.uint64))

    def windows(self, words: np.ndarray, width: int) -> np.ndarray:
        """Hash of each run of `width` words (also of those across texts, which the caller skips)."""
        n = len(words)
        if n < width:
            return np.zeros(0, np.uint64)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(words * self.powers(1, n), out=sums[1:])
        return mix((sums[width:] - sums[:-width]) * self.powers(1, n - width + 1, True))

    def runs(self, words: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of each run [start, end) of words."""
        sums = np.zeros(len(words) + 1, np.uint64)
        np.cumsum(words * self.powers(1, len(words)), out=sums[1:])
        return mix((sums[end] - sums[start]) * self.powers(1, len(words) + 1, True)[start] + (end - start).astype(np.uint64))


#: Bytes of a word: all but the six whitespace bytes.
WORD_BYTE = np.ones(256, bool)
WORD_BYTE[[0x20, *range(0x09, 0x0E)]] = False
#: Bytes of a token: ASCII letters and digits, and all bytes of other characters.
TOKEN_BYTE = np.array([b > 127 or chr(b).isalnum() for b in range(256)])


def spans(raw: np.ndarray, offsets: np.ndarray, kind: np.ndarray = WORD_BYTE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all runs of bytes of a kind, and each text's first run (n + 1 entries)."""
    inside = kind[raw]
    before = np.zeros(len(raw), bool)
    before[1:] = inside[:-1]
    borders = offsets[offsets < len(raw)]
    before[borders] = False
    start = np.flatnonzero(inside & ~before)
    after = np.zeros(len(raw), bool)
    after[:-1] = inside[1:]
    after[borders[borders > 0] - 1] = False
    end = np.flatnonzero(inside & ~after) + 1
    return start, end, np.searchsorted(start, offsets)


def window_starts(first: np.ndarray, width: int, n: int) -> np.ndarray:
    """Mask over the n - width + 1 window places: those that lie in one text."""
    inside = np.zeros(max(0, n - width + 1), bool)
    for a, b in zip(first[:-1], first[1:]):
        if b - a >= width:
            inside[a : b - width + 1] = True
    return inside


def member(values: np.ndarray, sorted_set: np.ndarray) -> np.ndarray:
    """Mask: which values occur in a sorted array."""
    if not len(sorted_set) or not len(values):
        return np.zeros(len(values), bool)
    at = np.searchsorted(sorted_set, values)
    at[at == len(sorted_set)] = 0
    return sorted_set[at] == values


# ---------------------------------------------------------------- chunks


def chunk_count(docs: DataFrame, per_chunk_bytes: int = 4 << 20) -> int:
    return max(16, 2 * table_bytes(docs.select("doc_id", "text")) // per_chunk_bytes)


def chunk_of(column: str, chunks: int):
    return F.pmod(F.xxhash64(F.coalesce(F.col(column).cast("long"), F.lit(-1))), F.lit(int(chunks)))


def chunked(docs: DataFrame, per_chunk_bytes: int = 4 << 20) -> DataFrame:
    """(chunk, doc_id, text): rows dealt by a hash of their id into chunks of a few MB.

    The number of chunks follows the size of the input, so a chunk's texts always fit a task.
    """
    return docs.select(
        chunk_of("doc_id", chunk_count(docs, per_chunk_bytes)).alias("chunk"),
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("text").cast("string").alias("text"),
    )


# ---------------------------------------------------------------- components


def components(nodes: DataFrame, links: DataFrame, rounds: int = 60) -> DataFrame:
    """Smallest reachable id per node, by hooking onto the smallest neighbour and pointer jumping.

    nodes: (id long); links: (a long, b long), undirected, repeats allowed. Returns (id, component).
    Every round is one aggregation over the links, which are re-pointed at the roots and
    deduplicated, so a hub with many links shrinks fast; the labels stay in written tables.
    Nodes without links are never shuffled more than once (at the last join).
    """
    both = links.select("a", "b").where("a <> b")
    both = written(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    label = None
    live = both
    for _ in range(rounds):
        if live.isEmpty():
            break
        # hook: every root joins the smallest root next to it, if that is smaller
        hook = live.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("root"))
        hook = written(hook)
        while True:  # jump until every pointer ends at a root
            up = hook.select(F.col("a").alias("root"), F.col("root").alias("upper"))
            nxt = written(hook.join(up, "root").select("a", F.col("upper").alias("root"), (F.col("upper") != F.col("root")).alias("moved")))
            moved = not nxt.where("moved").isEmpty()
            hook = nxt.select("a", "root")
            if not moved:
                break
        if label is None:
            label = hook
        else:
            label = written(label.join(hook.select(F.col("a").alias("root"), F.col("root").alias("top")), "root", "left").select("a", F.coalesce("top", "root").alias("root")))
        one = hook.select("a", F.col("root").alias("ra"))
        two = hook.select(F.col("a").alias("b"), F.col("root").alias("rb"))
        live = written(live.join(one, "a").join(two, "b").where("ra <> rb").select(F.col("ra").alias("a"), F.col("rb").alias("b")).distinct())
    else:
        raise RuntimeError("the components did not settle")
    if label is None:
        return nodes.select("id", F.col("id").alias("component"))
    return nodes.join(label.withColumnRenamed("a", "id"), "id", "left").select("id", F.coalesce("root", "id").alias("component"))
