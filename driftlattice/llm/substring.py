"""Exact-substring deduplication by fixed-block anchors.

A repeat is a window of WINDOW consecutive words that also starts in a document with a smaller id.
Every document is cut into non-overlapping reference blocks of BLOCK words; a window of WINDOW >=
2 * BLOCK - 1 words of the reference holds a whole block, so a document that repeats the window
holds that block at some place. All rolling windows of BLOCK words probe the index of blocks; a
place that hits a block of another chunk of documents is an anchor. Around anchors the hits are
extended: every WINDOW-word window over an anchor is compared by its own hash, and the windows
that repeat, joined, are the maximal exact repeats, whose words go.

Physical plan: documents are dealt into chunks of a few MB (one shuffle of the texts, reused).
Chunks send sorted distinct hashes, packed, to hash buckets, and buckets answer each chunk with
the entries that matter, first for anchors, then for windows. Repeats inside a chunk are settled
there. Neither step makes pairs of documents: a passage in a million documents is one entry per
chunk and one answer per chunk.

Defined cases: null text has no words; texts shorter than the window keep all words; equal ids
do not remove each other's words; a null id counts as larger than all others; an empty table gives
an empty result. Hashes are 64 bits, of the anchor and independently of the whole window; both
have to agree.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from driftlattice.llm.shared import Hasher, chunked, member, row_slices, spans, table_bytes, text_buffer

WINDOW = 50
BLOCK = 25
LAST = np.iinfo(np.int64).max

_ANCHOR, _FULL = Hasher(4), Hasher(44)


def texts_of(group: pa.Table) -> tuple[pa.Array, np.ndarray]:
    texts = group.column("text").combine_chunks()
    ids = group.column("doc_id").to_numpy(zero_copy_only=False) if group.column("doc_id").null_count == 0 else np.array([LAST if x is None else x for x in group.column("doc_id").to_pylist()], np.int64)
    return texts, ids.astype(np.int64)


def hashed_slices(texts: pa.Array, hasher: Hasher):
    for a, b in row_slices(texts):
        raw, offsets = text_buffer(texts.slice(a, b - a))
        start, end, first = spans(raw, offsets)
        yield a, b, hasher.words(raw, start, end), first


def whole_windows(words: np.ndarray, first: np.ndarray, width: int, hasher: Hasher) -> tuple[np.ndarray, np.ndarray]:
    """Places of the windows that lie in one text, and their hashes."""
    size = np.maximum(0, np.diff(first) - width + 1)
    at = np.arange(size.sum()) + np.repeat(first[:-1] - (np.cumsum(size) - size), size)
    return at, hasher.windows(words, width)[at]


def deal(keys: np.ndarray, bits: int) -> list[tuple[int, int, int]]:
    """(bucket, from, to) of the non-empty buckets of sorted hashes; a bucket is the leading bits."""
    edge = np.concatenate([[0], np.searchsorted(keys, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)), [len(keys)]])
    return [(int(k), int(edge[k]), int(edge[k + 1])) for k in np.flatnonzero(np.diff(edge))]


def low32(keys: np.ndarray, bits: int) -> np.ndarray:
    """32 bits behind the bucket's bits: enough within a bucket, as anchors only propose windows."""
    return ((keys << np.uint64(bits)) >> np.uint64(32)).astype(np.uint32)


def chunk_id(group: pa.Table) -> int:
    return group.column("chunk")[0].as_py()


def anchor_requests(bits: int, block: int):
    def ask(group: pa.Table) -> pa.Table:
        rolling, fixed = [], []
        for _, _, words, first in hashed_slices(texts_of(group)[0], _ANCHOR):
            at, value = whole_windows(words, first, block, _ANCHOR)
            rolling.append(np.unique(value))
            text = np.searchsorted(first, at, "right") - 1
            fixed.append(value[(at - first[text]) % block == 0])
        keys, blocks = np.unique(np.concatenate(rolling)), np.unique(np.concatenate(fixed))
        parts = deal(keys, bits)
        edge = {k: (a, b) for k, a, b in deal(blocks, bits)}
        return pa.table({
            "bucket": pa.array([k for k, _, _ in parts], pa.int32()), "chunk": pa.array([chunk_id(group)] * len(parts), pa.int64()),
            "probes": pa.array([low32(keys[a:b], bits).tobytes() for _, a, b in parts], pa.binary()),
            "blocks": pa.array([low32(blocks[slice(*edge.get(k, (0, 0)))], bits).tobytes() for k, _, _ in parts], pa.binary()),
        })

    return ask


def anchor_answers(group: pa.Table) -> pa.Table:
    """Entries that two or more chunks hold and at least one holds as a reference block."""
    probes = [np.frombuffer(x, np.uint32) for x in group.column("probes").to_pylist()]
    blocks = np.unique(np.concatenate([np.frombuffer(x, np.uint32) for x in group.column("blocks").to_pylist()]))
    every = np.sort(np.concatenate([x[member(x, blocks)] for x in probes]))
    twice = np.unique(every[1:][every[1:] == every[:-1]])
    chunks, bucket = group.column("chunk").to_pylist(), group.column("bucket")[0].as_py()
    rows = [(c, x[member(x, twice)]) for c, x in zip(chunks, probes)]
    rows = [(c, x.tobytes()) for c, x in rows if len(x)]
    return pa.table({"chunk": pa.array([c for c, _ in rows], pa.int64()), "bucket": pa.array([bucket] * len(rows), pa.int32()), "hits": pa.array([x for _, x in rows], pa.binary())})


def window_requests(bits: int, block: int, window: int):
    def ask(group: pa.Table, reply: pa.Table) -> pa.Table:
        empty = pa.table({"bucket": pa.array([], pa.int32()), "chunk": pa.array([], pa.int64()), "keys": pa.array([], pa.binary()), "docs": pa.array([], pa.binary())})
        if not group.num_rows or not reply.num_rows:
            return empty
        hits = np.sort(np.concatenate([(np.uint64(k) << np.uint64(32)) | np.frombuffer(x, np.uint32).astype(np.uint64) for k, x in zip(reply.column("bucket").to_pylist(), reply.column("hits").to_pylist())]))
        texts, ids = texts_of(group)
        keys, docs = [], []
        other = hashed_slices(texts, _FULL)
        for (a, _, words, first), (_, _, full, _) in zip(hashed_slices(texts, _ANCHOR), other):
            at, value = whole_windows(words, first, block, _ANCHOR)
            anchor = np.zeros(len(words) + 1, np.int64)
            anchor[at + 1] = member((value >> np.uint64(64 - bits) << np.uint64(32)) | low32(value, bits), hits)
            anchor = np.cumsum(anchor)
            at, value = whole_windows(full, first, window, _FULL)
            near = anchor[at + window - block + 1] > anchor[at]
            keys.append(value[near])
            docs.append(ids[a + np.searchsorted(first, at[near], "right") - 1])
        keys, docs = np.concatenate(keys), np.concatenate(docs)
        order = np.lexsort((docs, keys))
        keys, docs = keys[order], docs[order]
        lead = np.ones(len(keys), bool)
        lead[1:] = keys[1:] != keys[:-1]
        keys, docs = keys[lead], docs[lead]  # the smallest id of the chunk
        parts = deal(keys, bits)
        return pa.table({
            "bucket": pa.array([k for k, _, _ in parts], pa.int32()), "chunk": pa.array([chunk_id(group)] * len(parts), pa.int64()),
            "keys": pa.array([keys[a:b].tobytes() for _, a, b in parts], pa.binary()), "docs": pa.array([docs[a:b].tobytes() for _, a, b in parts], pa.binary()),
        })

    return ask


def window_answers(group: pa.Table) -> pa.Table:
    """For each chunk the windows that start in a smaller document of another chunk."""
    keys = [np.frombuffer(x, np.uint64) for x in group.column("keys").to_pylist()]
    docs = [np.frombuffer(x, np.int64) for x in group.column("docs").to_pylist()]
    every, own = np.concatenate(keys), np.concatenate(docs)
    order = np.lexsort((own, every))
    lead = np.ones(len(every), bool)
    lead[1:] = every[order][1:] != every[order][:-1]
    unique, least = every[order][lead], own[order][lead]
    rows = [(c, k[least[np.searchsorted(unique, k)] < d]) for c, k, d in zip(group.column("chunk").to_pylist(), keys, docs)]
    rows = [(c, k.tobytes()) for c, k in rows if len(k)]
    return pa.table({"chunk": pa.array([c for c, _ in rows], pa.int64()), "repeated": pa.array([k for _, k in rows], pa.binary())})


def removal(window: int):
    def finish(group: pa.Table, reply: pa.Table) -> pa.Table:
        n_words, n_removed, digest, kept_texts = [], [], [], []
        if group.num_rows:
            texts, ids = texts_of(group)
            repeated = np.sort(np.concatenate([np.zeros(0, np.uint64), *[np.frombuffer(x, np.uint64) for x in reply.column("repeated").to_pylist()]]))
            parts, keys, docs = [], [], []
            for a, b, words, first in hashed_slices(texts, _FULL):
                at, value = whole_windows(words, first, window, _FULL)
                doc = ids[a + np.searchsorted(first, at, "right") - 1]
                parts.append((a, b, first, at, value, doc))
                keys.append(value)
                docs.append(doc)
            every, own = np.concatenate(keys), np.concatenate(docs)
            # windows that occur once in the chunk need no look at ids
            ordered = np.sort(every)
            twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
            some = member(every, twice)
            least = np.full(len(twice), LAST)
            np.minimum.at(least, np.searchsorted(twice, every[some]), own[some])
            for a, b, first, at, value, doc in parts:
                gone = member(value, repeated)
                inside = np.flatnonzero(member(value, twice) & ~gone)
                gone[inside] = least[np.searchsorted(twice, value[inside])] < doc[inside]
                step = np.zeros(first[-1] + 1, np.int64)
                np.add.at(step, at[gone], 1)
                np.add.at(step, at[gone] + window, -1)
                drop = np.cumsum(step)[:-1] > 0
                lost = np.concatenate([[0], np.cumsum(drop)])
                lost = lost[first[1:]] - lost[first[:-1]]
                for k in range(b - a):
                    words = (texts[a + k].as_py() or "").encode().split()
                    if lost[k]:
                        words = [w for w, d in zip(words, drop[first[k] : first[k + 1]].tolist()) if not d]
                    kept = b" ".join(words)
                    n_words.append(int(first[k + 1] - first[k]))
                    n_removed.append(int(lost[k]))
                    digest.append(hashlib.sha256(kept).hexdigest())
                    kept_texts.append(kept)
        doc_id = group.column("doc_id") if group.num_rows else pa.array([], pa.int64())
        return pa.table({"doc_id": doc_id, "n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "kept_sha256": pa.array(digest, pa.string()), "kept": pa.array(kept_texts, pa.binary()).cast(pa.string())})

    return finish


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_words, n_removed, kept_sha256, kept): one row per document, `kept` the remaining words."""
    block = max(1, (window + 1) // 2)
    bits = max(3, math.ceil(math.log2(max(1, table_bytes(docs.select("doc_id", "text")) / (4 << 20)))))
    chunks = chunked(docs)
    asks = chunks.groupBy("chunk").applyInArrow(anchor_requests(bits, block), "bucket int, chunk long, probes binary, blocks binary")
    hits = asks.groupBy("bucket").applyInArrow(anchor_answers, "chunk long, bucket int, hits binary")
    wide = chunks.groupBy("chunk").cogroup(hits.groupBy("chunk")).applyInArrow(window_requests(bits, block, window), "bucket int, chunk long, keys binary, docs binary")
    repeated = wide.groupBy("bucket").applyInArrow(window_answers, "chunk long, repeated binary")
    return chunks.groupBy("chunk").cogroup(repeated.groupBy("chunk")).applyInArrow(removal(window), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("kept")
