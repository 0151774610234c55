"""Language-model scoring by context-tree weighting over bytes.

Every next byte is coded as eight binary decisions. For each decision and each context of 0 to
DEPTH preceding bytes there is a Krichevsky-Trofimov estimator; the weighted probability of a
context mixes its own estimator and the product over its one byte longer contexts, half and half,
at all depths. After learning, the chance of a byte is the mixture along its context path with the
posterior weights that this recursion gives; its negative log2 is its code length.

All counts derive from the counts of (DEPTH + 1)-byte grams of the learning texts. A chunk of
documents sends its distinct grams and words, packed and with their counts, to hash buckets. A
bucket of grams holds whole subtrees below contexts of TOP bytes, so it sums and weighs them
bottom-up and hands on only what contexts of TOP - 1 bytes have to know: at most 2^24 decisions,
whatever the corpus, which the driver weighs up to the root. Then every bucket answers each chunk
with the log10 probability of the grams that it asked for (words: with their counts), in the order
of asking. No task holds the model, and what travels follows the number of distinct grams a chunk.

Texts are coded as their lower-cased words (A-Z only), one space after each and one end byte, so
the model and the base score predict the same tokens; the context before a text is end bytes.

Defined cases: null and empty texts consist of the end alone; unseen bytes and contexts have the
estimators' prior of one half; repeated rows are learned and scored each; a null id counts as the
empty string for the hold-out; other columns are ignored, whatever their names; an empty table gives
an empty result; with no learning row every count is zero and the model codes eight bits a byte.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import WORD_BYTE, Hasher, chunk_count, dropped, mix, row_slices, spans, table_bytes, text_buffer, written

DEPTH = 5
#: Grams are dealt by their nearest TOP context bytes.
TOP = 3
#: Input bytes per chunk of documents (two chunks each) and per hash bucket of grams and words.
CHUNK_BYTES, BUCKET_BYTES = 8 << 20, 8 << 20
FOLDS, HELD = 5, 1
SPACE, END = 0x20, 0x0A

_WORDS = Hasher(2, lower=True)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def fold(folds: int = FOLDS):
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(folds))


# ---------------------------------------------------------------- the coded stream


def coded(raw: np.ndarray, offsets: np.ndarray, depth: int = DEPTH):
    """Coded bytes of all texts, each behind `depth` end bytes; first scored place of each text; words' spans."""
    start, end, first = spans(raw, offsets)
    n = len(offsets) - 1
    kept = np.flatnonzero(WORD_BYTE[raw])
    letters = np.concatenate([[0], np.cumsum(end - start)])  # word bytes before each word
    text_at = letters[first[:-1]] + first[:-1] + np.arange(n) * (depth + 1) + depth
    out = np.full(len(kept) + len(start) + n * (depth + 1), SPACE, np.uint8)
    text = np.repeat(np.arange(n), np.diff(first))  # of each word
    shift = np.arange(len(start)) + (text + 1) * depth + text
    out[np.arange(len(kept)) + np.repeat(shift, end - start)] = _LOWER[raw[kept]]
    stop = letters[first[1:]] + first[1:] + np.arange(n) * (depth + 1) + depth
    out[stop] = END
    for k in range(depth):
        out[text_at - 1 - k] = END
    return out, text_at, stop, (start, end, first)


def grams(stream: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """At each place from `depth` on: the last `depth` bytes and the byte itself, nearest context byte first.

    Packed as context 1, 2, ... depth (from the top) and the byte lowest, so that a context of d
    bytes is a prefix.
    """
    n = len(stream) - depth
    if n <= 0:
        return np.zeros(0, np.int64)
    value = stream[depth:].astype(np.int64)
    for d in range(1, depth + 1):
        value |= stream[depth - d : depth - d + n].astype(np.int64) << (8 * (depth - d + 1))
    return value


def scored_places(text_at: np.ndarray, stop: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """Places in grams() that belong to texts, in order."""
    size = stop - text_at + 1
    return np.arange(size.sum()) + np.repeat(text_at - depth - (np.cumsum(size) - size), size)


# ---------------------------------------------------------------- weighting


def log_gamma_half(n: np.ndarray) -> np.ndarray:
    """ln Gamma(n + 1/2) for whole n."""
    x = n + 0.5
    small = np.concatenate([[0.0], np.cumsum(np.log(np.arange(256) + 0.5))]) + math.lgamma(0.5)
    big = np.maximum(x, 200.0)
    series = (big - 0.5) * np.log(big) - big + 0.5 * math.log(2 * math.pi) + 1 / (12 * big) - 1 / (360 * big**3)
    return np.where(n <= 256, small[np.minimum(n, 256).astype(np.int64)], series)


def log_gamma_one(n: np.ndarray) -> np.ndarray:
    """ln Gamma(n + 1) for whole n."""
    small = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, 257)))])
    big = np.maximum(n + 1.0, 200.0)
    series = (big - 0.5) * np.log(big) - big + 0.5 * math.log(2 * math.pi) + 1 / (12 * big) - 1 / (360 * big**3)
    return np.where(n <= 256, small[np.minimum(n, 256).astype(np.int64)], series)


def log_kt(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """ln of the Krichevsky-Trofimov block probability."""
    return log_gamma_half(n0) + log_gamma_half(n1) - log_gamma_one(n0 + n1) - math.log(math.pi)


def stop_weight(kt: np.ndarray, below: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Posterior weight of a context's own estimator, and ln of its weighted probability."""
    weighted = np.logaddexp(kt, below) - math.log(2)
    return np.exp(kt - math.log(2) - weighted), weighted


def weigh_levels(gram: np.ndarray, n: np.ndarray, depth: int = DEPTH, top: int = 1):
    """All grams below some contexts of `top` bytes -> chance of each of the eight bits, mixed over depths top .. depth.

    Also returns the decisions at depth `top`: (context << 8 | node), n0, n1, ln weighted probability.
    """
    byte = gram & 255
    bits = np.arange(8)
    node = ((1 << bits)[None, :] | (byte[:, None] >> (8 - bits)[None, :])).astype(np.int64)
    one = (byte[:, None] >> (7 - bits)[None, :]) & 1
    weight = np.repeat(n.astype(np.float64), 8)
    chance = below = None
    levels = []
    for d in range(depth, top - 1, -1):
        key = ((gram >> (8 * (depth - d + 1)))[:, None] << 8 | node).ravel()
        unique, at = np.unique(key, return_inverse=True)
        n1 = np.bincount(at, weight * one.ravel(), len(unique))
        n0 = np.bincount(at, weight, len(unique)) - n1
        kt = log_kt(n0, n1)
        if d == depth:
            weighted, own = kt, np.ones(len(unique))
        else:
            own, weighted = stop_weight(kt, below(unique))
        levels.append((at, own, n0, n1))

        def below(parent, unique=unique, weighted=weighted):
            up = (unique >> 16 << 8) | (unique & 255)
            place = np.searchsorted(parent, up)
            return np.bincount(place, weighted, len(parent))

    for at, own, n0, n1 in levels:
        p = ((np.where(one.ravel(), n1[at], n0[at]) + 0.5) / (n0[at] + n1[at] + 1)).reshape(one.shape)
        w = own[at].reshape(one.shape)
        chance = p if chance is None else w * p + (1 - w) * chance
    return chance, (unique, n0, n1, weighted)


def weigh_subtree(gram: np.ndarray, n: np.ndarray, depth: int = DEPTH):
    """weigh_levels() for the grams of one nearest context byte, up to depth 1; decisions by node."""
    chance, (key, n0, n1, weighted) = weigh_levels(gram, n, depth)
    return chance, (key & 255, n0, n1, weighted)


class Upper:
    """The tree's part above depth TOP: chance of a bit = near + rest * (chance mixed from depth TOP on)."""

    def __init__(self, key: np.ndarray, n0: np.ndarray, n1: np.ndarray, below: np.ndarray):
        """Decisions of the contexts of TOP - 1 bytes (sorted keys), and the summed ln weighted probability of their children."""
        near, rest = np.zeros(len(key)), np.ones(len(key))
        parts, place, k = [], np.arange(len(key)), key
        for _ in range(TOP):  # contexts of TOP - 1 bytes, ..., of none
            own, weighted = stop_weight(log_kt(n0, n1), below)
            parts.append((own[place], ((n1 + 0.5) / (n0 + n1 + 1))[place]))
            shorter, up = np.unique((k >> 16 << 8) | (k & 255), return_inverse=True)
            n0, n1, below = (np.bincount(up, x, len(shorter)) for x in (n0, n1, weighted))
            place, k = up[place], shorter
        for own, p in reversed(parts):  # from the root down
            near += rest * own * p
            rest = rest * (1 - own)
        self.key, self.near, self.rest = key, near, rest

    def log10(self, gram: np.ndarray, deep: np.ndarray, depth: int = DEPTH) -> np.ndarray:
        """log10 probability of the last byte of each gram."""
        byte, bits = gram & 255, np.arange(8)
        node = (1 << bits)[None, :] | (byte[:, None] >> (8 - bits)[None, :])
        one = ((byte[:, None] >> (7 - bits)[None, :]) & 1).astype(bool)
        at = np.searchsorted(self.key, (gram >> (8 * (depth - TOP + 2)))[:, None] << 8 | node)
        near, rest = self.near[at], self.rest[at]
        return np.log10(np.where(one, near, 1 - rest - near) + rest * deep).sum(1)


class GramTable:
    """Scores of a chunk's distinct grams in an open hash table; every lookup is of a gram that is there."""

    def __init__(self, gram: np.ndarray, logp: np.ndarray):
        self.bits = max(4, math.ceil(math.log2(max(1, 3 * len(gram)))))
        self.key, self.logp = np.full(1 << self.bits, -1, np.int64), np.zeros(1 << self.bits)
        slot = self.home(gram)
        while len(gram):
            free = self.key[slot] < 0
            self.key[slot[free]] = gram[free]
            placed = self.key[slot] == gram
            self.logp[slot[placed]] = logp[placed]
            gram, logp, slot = gram[~placed], logp[~placed], (slot[~placed] + 1) & ((1 << self.bits) - 1)

    def home(self, gram: np.ndarray) -> np.ndarray:
        return ((gram.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def scores(self, gram: np.ndarray) -> np.ndarray:
        slot = self.home(gram)
        far = np.flatnonzero(self.key[slot] != gram)
        while len(far):
            slot[far] = (slot[far] + 1) & ((1 << self.bits) - 1)
            far = far[self.key[slot[far]] != gram[far]]
        return self.logp[slot]


# ---------------------------------------------------------------- chunks and buckets


def chunk_words(table: pa.Table, depth: int = DEPTH):
    """Per slice of a chunk: rows, coded stream, word hashes."""
    texts = table.column("text").combine_chunks()
    texts = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
    for a, b in row_slices(texts):
        raw, offsets = text_buffer(texts.slice(a, b - a))
        stream, text_at, stop, (start, end, first) = coded(raw, offsets, depth)
        yield a, b, stream, text_at, stop, _WORDS.words(raw, start, end), first


def summed(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, sorted, and the sums of their counts."""
    key, n = np.concatenate(keys), np.concatenate(counts)
    if not len(key):
        return key, n
    order = np.argsort(key)
    key, n = key[order], n[order]
    start = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return key[start], np.add.reduceat(n, start)


def by_bucket(gram: np.ndarray, bits: int, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """Order of sorted grams by their bucket, then by gram, and where each bucket starts. Grams of one context of TOP bytes share a bucket."""
    bucket = (mix((gram >> (8 * (depth - TOP + 1))).view(np.uint64)) >> np.uint64(64 - bits)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    return order, np.searchsorted(bucket[order], np.arange((1 << bits) + 1))


def asks(chunks: DataFrame, bits: int, depth: int = DEPTH) -> DataFrame:
    """chunks(chunk, text, learn) -> (bucket, chunk, keys binary, n binary): each chunk's distinct words (buckets 0 ..) and grams
    (buckets 2^bits ..) with their counts in learning texts."""

    def ask(table: pa.Table) -> pa.Table:
        learn = table.column("learn").to_numpy().astype(np.int64)
        words, word_n, found, gram_n = [], [], [], []
        for a, b, stream, text_at, stop, word, first in chunk_words(table, depth):
            for value, n, to, to_n in (
                (word >> np.uint64(1), np.diff(first), words, word_n),
                (grams(stream, depth)[scored_places(text_at, stop, depth)].view(np.uint64), stop - text_at + 1, found, gram_n),
            ):
                value, n = np.unique(value * np.uint64(2) + np.repeat(learn[a:b], n).astype(np.uint64), return_counts=True)
                to.append(value >> np.uint64(1))
                to_n.append(np.where(value & np.uint64(1), n, 0))
        (key, n), (gram, m) = summed(words, word_n), summed(found, gram_n)
        edge = np.searchsorted(key, np.arange((1 << bits) + 1, dtype=np.uint64) << np.uint64(63 - bits))
        order, border = by_bucket(gram.view(np.int64), bits, depth)
        gram, m = gram[order], m[order]
        rows = [(k, key[x:y], n[x:y]) for k, (x, y) in enumerate(zip(edge, edge[1:])) if y > x]
        rows += [(k + (1 << bits), gram[x:y], m[x:y]) for k, (x, y) in enumerate(zip(border, border[1:])) if y > x]
        return pa.table({
            "bucket": pa.array([r[0] for r in rows], pa.int32()), "chunk": pa.array([table.column("chunk")[0].as_py()] * len(rows), pa.int64()),
            "keys": pa.array([r[1].tobytes() for r in rows], pa.binary()), "n": pa.array([r[2].astype(np.uint32).tobytes() for r in rows], pa.binary()),
        })

    return chunks.groupBy("chunk").applyInArrow(ask, "bucket int, chunk long, keys binary, n binary")


def bucket_totals(table: pa.Table) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """What each chunk asked, the distinct keys of a bucket, and their summed counts."""
    asked = [np.frombuffer(x, np.int64) for x in table.column("keys").to_pylist()]
    key, total = summed(asked, [np.frombuffer(x, np.uint32).astype(np.int64) for x in table.column("n").to_pylist()])
    return asked, key, total


def upper_tree(asked: DataFrame, bits: int, depth: int = DEPTH) -> Upper:
    """The part of the tree above depth TOP, from the gram buckets' sums: at most 2^24 decisions, a bound of the model's shape."""

    def run(table: pa.Table) -> pa.Table:
        _, gram, n = bucket_totals(table)
        _, (key, n0, n1, weighted) = weigh_levels(gram, n, depth, TOP)
        up, at = np.unique((key >> 16 << 8) | (key & 255), return_inverse=True)
        return pa.table({"key": pa.array(up), **{c: pa.array(np.bincount(at, x, len(up))) for c, x in (("n0", n0), ("n1", n1), ("below", weighted))}})

    parts = asked.where(F.col("bucket") >= 1 << bits).groupBy("bucket").applyInArrow(run, "key long, n0 double, n1 double, below double")
    rows = parts.groupBy("key").agg(*[F.sum(c).alias(c) for c in ("n0", "n1", "below")]).orderBy("key").toArrow()
    return Upper(*[rows.column(c).to_numpy() for c in ("key", "n0", "n1", "below")])


def answered(asked: DataFrame, upper: Upper, bits: int, depth: int = DEPTH) -> DataFrame:
    """(chunk, bucket, reply binary, tokens, kinds): to each chunk the totals of its words, the scores of its grams, as it asked.

    Rows with chunk -1 carry each word bucket's sum and number of learned words.
    """
    shared = asked.sparkSession.sparkContext.broadcast(upper)

    def run(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        asked, key, total = bucket_totals(table)
        chunk = table.column("chunk").to_pylist()
        if bucket >= 1 << bits:
            deep, _ = weigh_levels(key, total, depth, TOP)
            value, tokens, kinds = shared.value.log10(key, deep, depth).astype(np.float32), None, None
        else:
            value, tokens, kinds = total, [0] * len(asked) + [int(total.sum())], [0] * len(asked) + [int((total > 0).sum())]
        reply = [value[np.searchsorted(key, x)].tobytes() for x in asked]
        if tokens:
            chunk, reply = [*chunk, -1], [*reply, b""]
        return pa.table({
            "chunk": pa.array(chunk, pa.int64()), "bucket": pa.array([bucket] * len(reply), pa.int32()), "reply": pa.array(reply, pa.binary()),
            "tokens": pa.array(tokens or [0] * len(reply), pa.int64()), "kinds": pa.array(kinds or [0] * len(reply), pa.int64()),
        })

    return asked.groupBy("bucket").applyInArrow(run, "chunk long, bucket int, reply binary, tokens long, kinds long")


def score(docs: DataFrame, held, depth: int = DEPTH) -> DataFrame:
    """docs(doc_id, text), held: boolean column of the rows not learned from ->
    (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_bytes, bits_per_byte)."""
    if depth < TOP:
        raise ValueError(f"contexts have {TOP} bytes or more, not {depth}")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), (~held).alias("learn"))
    size = table_bytes(rows)
    bits = max(3, math.ceil(math.log2(max(1, size / BUCKET_BYTES))))
    chunks = rows.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunk_count(rows, CHUNK_BYTES))))
    asked = written(asks(chunks.select("chunk", "text", "learn"), bits, depth))
    answers = written(answered(asked, upper_tree(asked, bits, depth), bits, depth))
    dropped(asked)
    texts = rows.agg(F.count(F.when(F.col("learn"), 1))).first()[0]
    learned = answers.where("chunk = -1").agg(F.coalesce(F.sum("tokens"), F.lit(0)), F.coalesce(F.sum("kinds"), F.lit(0))).first()
    tokens, kinds = learned[0] + texts, learned[1] + (texts > 0)
    scale = math.log10(tokens + 0.5 * (kinds + 1))
    end_known, end_part = int(texts > 0), math.log10(texts + 0.5) - scale
    schema = "doc_id long, learn boolean, n_tokens long, n_known long, base_score double, score double, n_bytes long"
    nothing = pa.schema([("doc_id", pa.int64()), ("learn", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()), ("n_bytes", pa.int64())]).empty_table()

    def finish(group: pa.Table, reply: pa.Table) -> pa.Table:
        m = group.num_rows
        if not m:
            return nothing
        got = sorted(zip(reply.column("bucket").to_pylist(), reply.column("reply").to_pylist()))
        counts = np.concatenate([np.zeros(0, np.int64), *[np.frombuffer(x, np.int64) for k, x in got if k < 1 << bits]])
        logp = np.concatenate([np.frombuffer(x, np.float32) for k, x in got if k >= 1 << bits])
        parts, values = [], []
        for a, b, stream, text_at, stop, words, first in chunk_words(group, depth):
            parts.append((a, b, text_at, stop, words, first))
            values.append(grams(stream, depth)[scored_places(text_at, stop, depth)])
        key = np.unique(np.concatenate([p[4] for p in parts]) >> np.uint64(1))
        gram, _ = summed(*zip(*(np.unique(v, return_counts=True) for v in values)))
        table = GramTable(gram[by_bucket(gram, bits, depth)[0]], logp)
        n_tokens, n_known, n_bytes = (np.zeros(m, np.int64) for _ in range(3))
        base, model = np.zeros(m), np.zeros(m)
        for (a, b, text_at, stop, words, first), value in zip(parts, values):
            c = counts[np.searchsorted(key, words >> np.uint64(1))] if len(words) else np.zeros(0, np.int64)
            text = np.repeat(np.arange(b - a), np.diff(first))
            n_tokens[a:b] = np.diff(first) + 1
            n_known[a:b] = np.bincount(text, c > 0, b - a).astype(np.int64) + end_known
            base[a:b] = np.bincount(text, np.log10(c + 0.5) - scale, b - a) + end_part
            size = stop - text_at + 1
            model[a:b], n_bytes[a:b] = np.add.reduceat(table.scores(value), np.cumsum(size) - size), size
        return pa.table({"doc_id": group.column("doc_id"), "learn": group.column("learn"), "n_tokens": pa.array(n_tokens), "n_known": pa.array(n_known), "base_score": pa.array(base), "score": pa.array(model), "n_bytes": pa.array(n_bytes)})

    replies = answers.where("chunk >= 0").select("chunk", "bucket", "reply")
    out = chunks.groupBy("chunk").cogroup(replies.groupBy("chunk")).applyInArrow(finish, schema)
    return out.select(
        "doc_id", (~F.col("learn")).alias("held_out"), "n_tokens", "n_known", F.lit(int(tokens)).cast("long").alias("train_tokens"), "base_score", "score", "n_bytes",
        (-F.col("score") / math.log10(2) / F.col("n_bytes")).alias("bits_per_byte"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), fold() == HELD)
