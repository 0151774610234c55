"""Benchmark decontamination by spaced-seed hashing.

Fixed masks of SPAN word positions look at some positions and ignore the others, so a window still
hashes alike when words at ignored positions were substituted. The seeds of all benchmark items
form a small index; every window of every document probes it under every mask. A hit fixes an
item and a diagonal (document place minus item place); there the two word sequences are compared
word by word and the best-scoring run (match +1, substitution -2; of runs that score alike the one
with most equal words) decides: a document is contaminated by an item when that run holds MIN_WORDS
equal words. An item of fewer than SPAN words
has to occur whole; from TOLERANT words on one of its words may be another one, for which a mask
for each position ignores that position.

The benchmark is the stated query set: it is taken in blocks of BLOCK_BYTES of text, one broadcast
index per block with that proven bound, and each task walks the blocks one after another over its
rows, so a task holds one block. All blocks together grow with the benchmark only, never with the
documents, which are never shuffled.

Defined cases: null or empty document text has no hits; null or empty items, items without an id and
those of fewer than SHORTEST words match nothing, as so few words occur in clean text; repeated items
report each id once; repeated document rows give repeated result rows; very long texts are probed
whole; an empty benchmark leaves every document clean, an empty table gives an empty result; ties in
the best item go to the smaller id; other columns pass through stage() whatever their names, and
contamination() refuses kept columns that are called like its new ones.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import TOKEN_BYTE, Hasher, member, mix, row_slices, spans, text_buffer, text_filter, text_map

#: Positions looked at (1) and ignored (0); fixed values, a mask reaches from its first to its last 1. Each accepted run begins with one of the 143
#: placements of ten equal words and up to four substitutions whose scores stay positive, and each of those holds a seed of some mask.
MASKS = ("00011101101", "11110001100", "11101100100", "11110101000")
SPAN = 11
MIN_WORDS = 10
SHORTEST, TOLERANT = 5, 8
MISS = 2
BLOCK_BYTES = 8 << 20
FILTER_BITS = 20

_HASHER = Hasher(10)


def word_hashes(column) -> tuple[np.ndarray, np.ndarray]:
    raw, offsets = text_buffer(pc.utf8_lower(column))
    start, end, first = spans(raw, offsets, TOKEN_BYTE)
    return _HASHER.words(raw, start, end), first


def seeds(words: np.ndarray, mask: str) -> np.ndarray:
    """Hash of each window of len(mask) words under a mask."""
    n = len(words) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    for k, bit in enumerate(mask):
        if bit == "1":
            total += words[k : k + n] * np.uint64((2 * k + 1) * 0x9E3779B97F4A7C15 % 2**64)
    return mix(total)


def masks_of(length: int) -> list[str]:
    """Masks for items of a length (SPAN: of this and all greater ones)."""
    if length >= SPAN:
        return [m.strip("0") for m in MASKS]
    if length < TOLERANT:
        return ["1" * length]
    return ["1" * k + "0" + "1" * (length - k - 1) for k in range(length)]


def accepted(size: int, min_words: int = MIN_WORDS) -> int:
    """Equal words that an item of a size asks for."""
    return min_words if size >= SPAN else size - (size >= TOLERANT)


def build_index(ids: list[int], texts: list[str]) -> dict:
    """Seed index of some items: per mask the sorted hashes with item and place, and all items' words."""
    words, first = word_hashes(pa.array(texts, pa.string()))
    sizes = np.diff(first)
    tables = []
    for length in sorted({int(min(n, SPAN)) for n in sizes if n >= SHORTEST}):
        for mask in masks_of(length):
            value = seeds(words, mask)
            item = np.searchsorted(first, np.arange(len(value)), "right") - 1
            fits = np.arange(len(value)) + len(mask) <= first[item + 1]
            fits &= sizes[item] >= SPAN if length == SPAN else sizes[item] == length
            at = np.flatnonzero(fits)
            order = np.argsort(value[at], kind="stable")
            at = at[order]
            bits = np.zeros(1 << FILTER_BITS, bool)
            bits[(value[at] & np.uint64((1 << FILTER_BITS) - 1)).astype(np.int64)] = True
            tables.append((mask, value[at], item[at], at, bits))
    return {"ids": np.array(ids, np.int64), "words": words, "first": first, "tables": tables}


def best_run(same: np.ndarray) -> int:
    """Equal words in the best-scoring run of a diagonal; of runs that score alike the most, none with a start that scores nothing."""
    score = np.concatenate([[0], np.cumsum(np.where(same, 1, -MISS))])
    low = np.minimum.accumulate(score)
    gain = score - low
    if not len(same) or gain.max() <= 0:
        return 0
    equal = np.concatenate([[0], np.cumsum(same)])
    begin = np.maximum.accumulate(np.where(score == low, np.arange(len(score)), 0))  # the last place of the least score so far
    stops = np.flatnonzero(gain == gain.max())
    return int((equal[stops] - equal[begin[stops]]).max())


def matches(index: dict, words: np.ndarray, first: np.ndarray) -> dict[tuple[int, int], tuple[int, int, float]]:
    """(text, item) -> seed hits, equal words in the best run, their share of the item."""
    found: dict[tuple[int, int, int], int] = {}
    for mask, keys, item, place, bits in index["tables"]:
        value = seeds(words, mask)
        maybe = np.flatnonzero(bits[(value & np.uint64((1 << FILTER_BITS) - 1)).astype(np.int64)])
        maybe = maybe[member(value[maybe], keys)]
        if not len(maybe):
            continue
        text = np.searchsorted(first, maybe, "right") - 1
        inside = maybe + len(mask) <= first[text + 1]
        maybe, text = maybe[inside], text[inside]
        low, high = np.searchsorted(keys, value[maybe], "left"), np.searchsorted(keys, value[maybe], "right")
        count = high - low
        slot = np.repeat(low, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        hit = np.stack([np.repeat(text, count), item[slot], np.repeat(maybe, count) - place[slot]], 1)
        for (t, i, d), n in zip(*(lambda u: (u[0].tolist(), u[1].tolist()))(np.unique(hit, axis=0, return_counts=True))):
            found[t, i, d] = found.get((t, i, d), 0) + n
    out: dict[tuple[int, int], tuple[int, int, float]] = {}
    for (t, i, d), hits in found.items():
        a, b = max(index["first"][i], first[t] - d), min(index["first"][i + 1], first[t + 1] - d)
        same = index["words"][a:b] == words[a + d : b + d]
        size = int(index["first"][i + 1] - index["first"][i])
        run = best_run(same) if size >= SPAN else int(same.sum())
        old = out.get((t, i), (0, 0, 0.0))
        out[t, i] = (old[0] + hits, max(old[1], run), max(old[2], run / size))
    return out


def index_blocks(spark: SparkSession, benchmark: DataFrame) -> list:
    """One broadcast index per block of the benchmark; a block holds at most about BLOCK_BYTES of text."""
    items = benchmark.where("item_id IS NOT NULL AND text IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = -(-int(size) // BLOCK_BYTES)
    out = []
    for k in range(blocks):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).orderBy("item_id", "text").collect()
        if rows:
            out.append(spark.sparkContext.broadcast(build_index([r[0] for r in rows], [r[1] for r in rows])))
    return out


def prober(blocks: list, min_words: int):
    """texts -> per text: seed hits, contaminating items, best item, its equal words and their share of the item."""

    def probe(texts: pa.Array) -> list[list]:
        rows: list[list] = [[0, [], None, 0, 0.0] for _ in range(len(texts))]
        for shared in blocks:
            index = shared.value
            for a, b in row_slices(texts):
                words, first = word_hashes(texts.slice(a, b - a))
                for (t, i), (hits, equal, share) in sorted(matches(index, words, first).items()):
                    row, item = rows[a + t], int(index["ids"][i])
                    if equal >= accepted(int(index["first"][i + 1] - index["first"][i]), min_words):
                        row[0] += hits
                        row[1].append(item)
                        if (equal, share, -item) > (row[3], row[4], -(row[2] if row[2] is not None else 2**62)):
                            row[2:] = [item, equal, share]
            if len(blocks) > 1:
                shared._value = None  # one block in memory at a time
                del shared._value
        return rows

    return probe


def contamination(docs: DataFrame, benchmark: DataFrame, keep=("doc_id",), min_words: int = MIN_WORDS) -> DataFrame:
    """docs(text, *keep) -> (*keep, contaminated, n_hits, n_items, items, best_item, best_words, best_share)."""
    blocks = index_blocks(docs.sparkSession, benchmark)

    def run():
        probe = prober(blocks, min_words)

        def columns(texts):
            rows = probe(texts)
            items = [sorted(set(r[1])) for r in rows]
            of = lambda k, kind: pa.array([r[k] for r in rows], kind)
            return pa.array([bool(x) for x in items], pa.bool_()), of(0, pa.int64()), pa.array([len(x) for x in items], pa.int64()), pa.array(items, pa.list_(pa.int64())), of(2, pa.int64()), of(3, pa.int64()), of(4, pa.float64())

        return columns

    return text_map(docs, keep, "contaminated boolean, n_hits long, n_items long, items array<long>, best_item long, best_words long, best_share double", run)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: contaminated documents go."""
    blocks = index_blocks(spark, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))

    def run():
        probe = prober(blocks, MIN_WORDS)
        return lambda texts: np.array([not r[1] for r in probe(texts)], bool)

    return text_filter(docs, run)
