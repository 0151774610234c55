"""N-gram Jaccard join by PartEnum signatures.

Sets of word shingles fall into bands of nearly equal size. Two sets with Jaccard similarity of at
least THRESHOLD percent differ in at most k elements, k fixed by the band; so the shingle domain is
hash-partitioned and

* for k of 8 or more, into n1 > k parts: two such sets agree on at least n1 - k of them. A set's
  signatures are its parts' contents; empty parts are left out as long as the set has fewer than
  n1 - k of them, for then an agreeing part with content remains. Shingles that very many documents
  hold (shared passages) are set apart first, as they make parts agree by chance: a set signs with
  its other shingles, and only if too many of its parts are then empty also with all of them;
* for smaller k, into (k + 1) / 2 parts of three second-level parts each: one first-level part
  differs in at most one element, so the sets share the content of two of its three second-level
  parts, and the three subsets of two are enumerated;
* for k = 0 the whole set is the signature.

A set signs for its own band and the next, so sets of neighbouring bands meet. Shared signatures
only propose; every link is verified on the shingle sets (100 * common >= THRESHOLD * union).

Equal sets are one class from the start. Classes that share a signature are a group, and groups are
verified by stars, never by all pairs: each class with one partner first, then in rounds the members
of a group that are not in its largest component with a few hubs inside it, twice as many a round;
links contract to components. When rounds find little more, the pairs of a group that are still in
different components are verified, so no link that joins components is lost. Before a set travels to
a partner, parity sketches are compared, inside the join that makes the pairs: each set as SKETCH
bits, a bit the parity of the number of its elements in a hash part. Sets that differ in d elements
differ in at most d of these bits, so no link is ruled out, and few others are let through.

Defined cases: null, empty or blank texts have no shingles, link with nothing and are their own
component; texts of fewer than five words have their whole word sequence as single shingle; equal
ids are one node; a null id is returned with its set size and a null component; other columns are
ignored (stage() keeps them), whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import Hasher, chunk_count, chunk_of, components, dropped, field, lean, member, mix, released, row_slices, spans, table_bytes, text_buffer, written

WIDTH = 5
THRESHOLD = 80
ENUMERATE_BELOW = 8
#: Common shingles set apart: at most so many (a bounded broadcast), each in so many documents of a block of so many shingles.
COMMON, COMMON_FROM, COMMON_BLOCK = 1_000_000, 6, 4_000_000
#: Input bytes per hash bucket of signatures: large buckets name a document once for many of its signatures.
BUCKET_BYTES = 16 << 20
#: Ids that may be broadcast to pick the documents to verify; beyond it the join shuffles.
BROADCAST_IDS = 2_000_000
#: Sketches (of SKETCH bits) that may be broadcast.
BROADCAST_SKETCHES = 100_000
#: Rounds of stars (by their hubs a group) end early when a round links less than LINKING of what it compares with hubs.
ROUNDS, LINKING = (1, 2, 4, 8, 16), 0.01
#: Bits of a parity sketch; about as many as a set has elements make a sharp one, fewer a weaker one that lets more pairs through.
SKETCH = 2048

_HASHER = Hasher(7, lower=True)
_U = np.uint64


def shingle_sets(texts: pa.Array, width: int = WIDTH):
    """Per slice: (first row, distinct shingle hashes sorted within each text, each text's first entry)."""
    for a, b in row_slices(texts):
        raw, offsets = text_buffer(texts.slice(a, b - a))
        start, end, first = spans(raw, offsets)
        words = _HASHER.words(raw, start, end)
        size = np.diff(first)
        many = np.maximum(0, size - width + 1)
        at = np.arange(many.sum()) + np.repeat(first[:-1] - (np.cumsum(many) - many), many)
        value, text = _HASHER.windows(words, width)[at], np.repeat(np.arange(b - a), many)
        short = np.flatnonzero((size > 0) & (size < width))
        value = np.concatenate([value, _HASHER.runs(words, first[:-1][short], first[1:][short])])
        text = np.concatenate([text, short])
        order = np.lexsort((value, text))
        value, text = value[order], text[order]
        fresh = np.ones(len(value), bool)
        fresh[1:] = (value[1:] != value[:-1]) | (text[1:] != text[:-1])
        value, text = value[fresh], text[fresh]
        yield a, value, np.searchsorted(text, np.arange(b - a + 1))


def wide_sum(slot: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
    """Sums mod 2^64 per slot (each half exact in a double for up to 2^20 entries a slot)."""
    low = np.bincount(slot, (value & _U(0xFFFFFFFF)).astype(np.float64), n).astype(np.uint64)
    high = np.bincount(slot, (value >> _U(32)).astype(np.float64), n).astype(np.uint64)
    return low + (high << _U(32))


def set_class(value: np.ndarray, first: np.ndarray) -> np.ndarray:
    """One 64-bit name per set; equal sets have equal names (two independent sums and the size go in)."""
    text = np.repeat(np.arange(len(first) - 1), np.diff(first))
    one, two = wide_sum(text, mix(value), len(first) - 1), wide_sum(text, mix(value ^ _U(0x5851F42D4C957F2D)), len(first) - 1)
    return mix(one ^ mix(two + np.diff(first).astype(np.uint64)))


def bands(most: int, threshold: int = THRESHOLD) -> tuple[np.ndarray, np.ndarray]:
    """Smallest sizes of the bands up to `most` and one beyond, and each band's k."""
    low, k = [1], []
    while True:
        high = low[-1] * 100 // threshold
        k.append(2 * high * (100 - threshold) // (100 + threshold))
        if low[-1] > most:
            return np.array(low), np.array(k)
        low.append(high + 1)


class Heavy:
    """A fixed set of common shingles; any set keeps the join exact, a good one keeps chance candidates few."""

    def __init__(self, values: np.ndarray):
        self.values = np.sort(values)
        self.bits = np.zeros(1 << 22, bool)
        self.bits[(self.values & _U((1 << 22) - 1)).astype(np.int64)] = True

    def mask(self, value: np.ndarray) -> np.ndarray:
        out = self.bits[(value & _U((1 << 22) - 1)).astype(np.int64)]
        at = np.flatnonzero(out)
        out[at] = member(value[at], self.values)
        return out


NOTHING = Heavy(np.zeros(0, np.uint64))


def signatures(value: np.ndarray, first: np.ndarray, threshold: int = THRESHOLD, heavy: Heavy = NOTHING) -> tuple[np.ndarray, np.ndarray]:
    """All signatures of all sets: (64-bit signature, set number)."""
    size = np.diff(first)
    low, ks = bands(int(size.max(initial=1)), threshold)
    band = np.searchsorted(low, size, "right") - 1
    common = np.flatnonzero(heavy.mask(value))
    spread, element = mix(value ^ _U(0x2545F4914F6CDD1D)) >> _U(32), mix(value ^ _U(0x1F123BB5159A55E5))
    out_sig, out_set = [], []
    for step in (0, 1):
        live = np.flatnonzero(size > 0)
        instance = band[live] + step
        k = ks[np.minimum(instance, len(ks) - 1)]
        fine, large = (k > 0) & (k < ENUMERATE_BELOW), k >= ENUMERATE_BELOW
        parts = np.where(k == 0, 1, np.where(fine, 3 * ((k + 2) // 2), (k + 1) * 6 // 5 + 2))
        base = np.concatenate([[0], np.cumsum(parts)])
        which = np.zeros(len(size), np.int64)
        which[live] = np.arange(len(live))
        owner = which[np.repeat(np.arange(len(size)), size)]  # of each element, among the live
        slot = base[owner] + ((spread * parts[owner].astype(np.uint64)) >> _U(32)).astype(np.int64)
        content, count = wide_sum(slot, element, base[-1]), np.bincount(slot, minlength=base[-1])
        of = np.repeat(np.arange(len(live)), parts)
        place = np.arange(base[-1]) - base[of]
        tag = mix((instance[of].astype(np.uint64) << _U(40)) | place.astype(np.uint64))
        # large k: first by the shingles that are not common
        light = content - wide_sum(slot[common], element[common], base[-1])
        light_count = count - np.bincount(slot[common], minlength=base[-1])
        able = large & (np.bincount(of, light_count == 0, len(live)).astype(np.int64) < parts - k)
        keep = large[of] & (light_count > 0)
        out_sig.append(mix(light ^ mix(tag + _U(1)))[keep])
        out_set.append(live[of[keep]])
        # second-level parts: what the other two of each three hold
        at = np.flatnonzero(fine[of])
        content[at] = np.repeat(content[at].reshape(-1, 3).sum(1, dtype=np.uint64), 3) - content[at]
        empty = np.bincount(of, count == 0, len(live)).astype(np.int64)
        keep = ~able[of] & ((count > 0) | fine[of] | (empty >= parts - k)[of])
        out_sig.append(mix(content ^ tag)[keep])
        out_set.append(live[of[keep]])
    return np.concatenate(out_sig), np.concatenate(out_set)


def frequent(kept: list[np.ndarray], least: int = COMMON_FROM) -> tuple[np.ndarray, np.ndarray]:
    """The values that are there so often at least, and how often; takes what `kept` holds out of it, and needs little more than that."""
    value = np.concatenate(kept)
    kept.clear()
    if len(value) < least:
        return value[:0], np.zeros(0, np.int64)
    value.sort()
    # where equal values begin and are already so many
    full = value[: len(value) - least + 1] == value[least - 1 :]
    full[1:] &= value[1 : len(full)] != value[: len(full) - 1]
    first = np.flatnonzero(full)
    found = value[first]
    return found, np.searchsorted(value, found, "right") - first


def scanned(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_shingles, class, value, n) of two kinds, from one pass over the texts:
    a row for each document (n null), and one for each shingle that COMMON_FROM documents of a block of COMMON_BLOCK shingles hold."""

    def run(batches):
        kept, room = [], 0

        def flush():
            value, n = frequent(kept)
            none = pa.nulls(len(n), pa.int64())
            return pa.RecordBatch.from_arrays([none, none, none, pa.array(value.view(np.int64)), pa.array(n)], ["doc_id", "n_shingles", "class", "value", "n"])

        for batch in batches:
            n, name = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for _, value, first in shingle_sets(batch.column("text"), width):
                n.append(np.diff(first))
                name.append(set_class(value, first).view(np.int64))
                kept.append(value)
                room += len(value)
                if room > COMMON_BLOCK:
                    yield flush()
                    room = 0
            none = pa.nulls(batch.num_rows, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.concatenate(n)), pa.array(np.concatenate(name)), none, none], ["doc_id", "n_shingles", "class", "value", "n"])
        if kept:
            yield flush()

    return docs.select("doc_id", "text").mapInArrow(lean(run), "doc_id long, n_shingles long, class long, value long, n long")


def common_shingles(counts: DataFrame) -> Heavy:
    """(value, n) -> the most frequent COMMON shingles. The bound is on the helper set only: whatever it holds, every link is found."""
    counts = written(counts.groupBy("value").agg(F.sum("n").alias("n")))
    found = counts.count()
    if found > COMMON:
        floor = counts.agg(F.percentile_approx("n", 1 - 0.9 * COMMON / found, 10_000)).first()[0]
        counts = counts.where(F.col("n") > floor).limit(COMMON)
    return Heavy(counts.select("value").toArrow().column("value").to_numpy().astype(np.int64).view(np.uint64))


def signature_groups(docs: DataFrame, bits: int, threshold: int, heavy: Heavy) -> DataFrame:
    """docs(text) -> distinct (grp long, class long, hub long): classes that share a signature, groups of two or more; hub: one of the group.

    Signatures travel packed: per task slice and hash bucket 32 more bits of each and the number of
    its class in a small list, equal sets of a slice once.
    """

    shared = docs.sparkSession.sparkContext.broadcast(heavy.values)

    def ask(batches):
        heavy = Heavy(shared.value)
        for batch in batches:
            for _, value, first in shingle_sets(batch.column("text")):
                name = set_class(value, first)
                names, lead = np.unique(name, return_index=True)
                keep = np.zeros(len(name), bool)
                keep[lead] = True
                sig, which = signatures(value, first, threshold, heavy)
                mine = keep[which]
                sig, which = sig[mine], np.searchsorted(names, name[which[mine]]).astype(np.uint32)
                order = np.argsort(sig)
                sig, which = sig[order], which[order]
                edge = np.concatenate([[0], np.searchsorted(sig, np.arange(1, 1 << bits, dtype=np.uint64) << _U(64 - bits)), [len(sig)]])
                used = np.flatnonzero(np.diff(edge))
                short = ((sig << _U(bits)) >> _U(32)).astype(np.uint32)
                rows = [(int(k), short[edge[k] : edge[k + 1]], which[edge[k] : edge[k + 1]]) for k in used]
                out_names, out_which = [], []
                for _, _, w in rows:
                    own, at = np.unique(w, return_inverse=True)
                    out_names.append(names[own].tobytes())
                    out_which.append(at.astype(np.uint16 if len(own) < 1 << 16 else np.uint32).tobytes())
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1].tobytes() for r in rows], pa.binary()), pa.array(out_which, pa.binary()), pa.array(out_names, pa.binary())], ["bucket", "sig", "which", "names"])

    def meet(group: pa.Table) -> pa.Table:
        sig, name = [], []
        for s, w, n in zip(*(group.column(c).to_pylist() for c in ("sig", "which", "names"))):
            s, n = np.frombuffer(s, np.uint32), np.frombuffer(n, np.uint64)
            sig.append(s)
            name.append(n[np.frombuffer(w, np.uint16 if len(w) == 2 * len(s) else np.uint32)])
        sig, name = np.concatenate(sig), np.concatenate(name)
        order = np.argsort(sig, kind="stable")
        sig, name = sig[order], name[order]
        same = np.zeros(len(sig), bool)
        same[1:] = sig[1:] == sig[:-1]
        near = same.copy()
        near[:-1] |= same[1:]
        sig, name = sig[near], name[near]
        order = np.lexsort((name, sig))
        sig, name = sig[order], name[order]
        fresh = np.ones(len(sig), bool)
        fresh[1:] = (sig[1:] != sig[:-1]) | (name[1:] != name[:-1])
        sig, name = sig[fresh], name[fresh]
        lead = np.ones(len(sig), bool)
        lead[1:] = sig[1:] != sig[:-1]
        start = np.flatnonzero(lead)
        size = np.diff(np.append(start, len(sig)))
        start, size = start[size > 1], size[size > 1]
        # groups with the same members are one group, named by them
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(name))]) if len(name) else np.zeros(1, np.uint64)
        label = mix(total[start + size] - total[start] + size.astype(np.uint64))
        label, at = np.unique(label, return_index=True)
        start, size = start[at], size[at]
        place = np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())
        return pa.table({"grp": pa.array(np.repeat(label, size).view(np.int64)), "class": pa.array(name[place].view(np.int64)), "hub": pa.array(np.repeat(name[start], size).view(np.int64))})

    asks = docs.select("text").mapInArrow(lean(ask), "bucket int, sig binary, which binary, names binary")
    return asks.groupBy("bucket").applyInArrow(meet, "grp long, class long, hub long").distinct()


def parity(value: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Per set the parities of its elements' numbers in SKETCH hash parts, as rows of 64-bit words."""
    part = (mix(value ^ _U(0x632BE59BD9B4E019)) >> _U(64 - SKETCH.bit_length() + 1)).astype(np.int64)
    out = [np.zeros((0, SKETCH // 64), np.int64)]
    for a in range(0, len(first) - 1, 2000):  # so many sets at once, as each takes SKETCH counters
        edge = first[a : a + 2001]
        owner = np.repeat(np.arange(len(edge) - 1), np.diff(edge))
        odd = np.bincount(owner * SKETCH + part[edge[0] : edge[-1]], minlength=(len(edge) - 1) * SKETCH) & 1
        out.append(np.packbits(odd.astype(np.uint8).reshape(-1, SKETCH), 1).view(np.int64))
    return np.concatenate(out)


_WORDS = [f"p{k}" for k in range(SKETCH // 64)]


def sketches(texts: DataFrame) -> DataFrame:
    """texts(doc_id, text) -> (doc_id, p struct of words)."""

    def run(batches):
        for batch in batches:
            words = np.concatenate([np.zeros((0, len(_WORDS)), np.int64), *[parity(value, first) for _, value, first in shingle_sets(batch.column("text"))]])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(np.ascontiguousarray(words[:, k])) for k in range(len(_WORDS))]], ["doc_id", *_WORDS])

    rows = texts.select("doc_id", "text").mapInArrow(lean(run), "doc_id long, " + ", ".join(f"{c} long" for c in _WORDS))
    return rows.select("doc_id", F.struct(*_WORDS).alias("p"))


def plausible(p, q, n, m, threshold: int = THRESHOLD):
    """Column: whether sets of n and m elements may be similar enough, by their sketches p and q."""
    differ = sum((F.bit_count(p[c].bitwiseXOR(q[c])) for c in _WORDS[1:]), F.bit_count(p[_WORDS[0]].bitwiseXOR(q[_WORDS[0]])))
    return (100 + threshold) * differ <= (100 - threshold) * (n + m)


def picked(texts: DataFrame, ids: DataFrame) -> DataFrame:
    """The texts of some ids(doc_id); the ids are broadcast after a count."""
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    return texts.join(F.broadcast(ids) if few else ids, "doc_id", "left_semi")


def linked(texts: DataFrame, pairs: DataFrame, chunks: int, threshold: int = THRESHOLD) -> DataFrame:
    """texts(chunk, doc_id, text), pairs(a, b) -> the pairs that link, by their whole sets.

    The set of `a` goes once to every chunk that holds a partner, never to every partner.
    """

    def sets(batches):
        for batch in batches:
            n, own = [], []
            for _, value, first in shingle_sets(batch.column("text")):
                n += np.diff(first).tolist()
                own += [value[x:y].tobytes() for x, y in zip(first[:-1], first[1:])]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(own, pa.binary())], ["a", "n", "own"])

    def meet(group: pa.Table, sent: pa.Table) -> pa.Table:
        left, right = [], []
        if group.num_rows and sent.num_rows:
            ids, asked, have = group.column("doc_id").to_numpy(), np.unique(sent.column("bs").combine_chunks().flatten().to_numpy()), {}
            for a, value, first in shingle_sets(group.column("text").combine_chunks()):
                for k in np.flatnonzero(member(ids[a : a + len(first) - 1], asked)):
                    have[int(ids[a + k])] = value[first[k] : first[k + 1]].copy()
            for a, n, own, bs in zip(*(sent.column(c) for c in ("a", "n", "own", "bs"))):
                a, n, whole = a.as_py(), n.as_py(), np.frombuffer(own.as_py(), np.uint64)
                for b in bs.as_py():
                    common = int(member(have[b], whole).sum())
                    if 100 * common >= threshold * (n + len(have[b]) - common):
                        left.append(a)
                        right.append(b)
        return pa.table({"a": pa.array(left, pa.int64()), "b": pa.array(right, pa.int64())})

    texts = picked(texts, pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct())
    bodies = picked(texts, pairs.select(F.col("a").alias("doc_id")).distinct()).select("doc_id", "text").mapInArrow(lean(sets), "a long, n long, own binary")
    sent = pairs.select("a", "b", chunk_of("b", chunks).alias("chunk")).groupBy("chunk", "a").agg(F.collect_list("b").alias("bs")).join(bodies, "a")
    return texts.groupBy("chunk").cogroup(sent.groupBy("chunk")).applyInArrow(meet, "a long, b long")


def contracted(joined: DataFrame, links: DataFrame) -> DataFrame:
    """(id, component) after some more links(a, b)."""
    side = lambda c: joined.select(F.col("id").alias(c), F.col("component").alias(f"c{c}"))
    new = written(links.join(side("a"), "a").join(side("b"), "b").where("ca <> cb").select(F.col("ca").alias("a"), F.col("cb").alias("b")).distinct())
    ends = new.select(F.col("a").alias("id")).unionByName(new.select(F.col("b").alias("id"))).distinct()
    moved = components(ends, new).select(F.col("id").alias("component"), F.col("component").alias("smallest"))
    return written(joined.join(moved, "component", "left").select("id", F.coalesce("smallest", "component").alias("component")))


def still_open(placed: DataFrame) -> DataFrame:
    """(grp, rep, n, component) of the groups with several components."""
    several = placed.groupBy("grp").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high").select("grp")
    return written(placed.join(several, "grp", "left_semi"))


def largest_components(placed: DataFrame) -> DataFrame:
    """(grp, main): each group's component of most members, of equal ones the smallest."""
    by = placed.groupBy("grp", "component").agg(F.count(F.lit(1)).alias("c"))
    return by.groupBy("grp").agg((-F.max(F.struct("c", (-F.col("component")).alias("least")))["least"]).alias("main"))


def near_duplicates(docs: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_shingles, component_id)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    bits = max(3, math.ceil(math.log2(max(1, table_bytes(docs) / BUCKET_BYTES))))
    scan = written(scanned(docs))
    nodes = scan.where("n IS NULL").select("doc_id", "n_shingles", "class")
    # one document stands for each class of equal sets
    classes = nodes.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("class").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"))
    groups = written(signature_groups(docs, bits, threshold, common_shingles(scan.where("n IS NOT NULL").select("value", "n"))))
    shared = written(groups.select("class").distinct().join(classes, "class"))  # the classes that share any signature
    needed = shared.select(F.col("rep").alias("doc_id")).distinct()
    kept_texts = picked(docs, needed)
    # one text an id; where no id is repeated, which narrow rows tell, the texts need no shuffle for that
    repeated = not nodes.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").isEmpty()
    kept_texts = written(kept_texts.dropDuplicates(["doc_id"]) if repeated else kept_texts)
    chunks = chunk_count(kept_texts)
    texts = kept_texts.withColumn("chunk", chunk_of("doc_id", chunks))
    sketch = written(sketches(texts))
    joined = written(needed.select(F.col("doc_id").alias("id"), F.col("doc_id").alias("component")))
    fits = lambda a, b: (100 * F.least(a, b) >= threshold * F.greatest(a, b))
    side = lambda x: sketch.select(F.col("doc_id").alias(x), F.col("p").alias(f"p{x}"))

    def handy(rows):
        """Sketches, broadcast after a count."""
        return F.broadcast(rows) if rows.limit(BROADCAST_SKETCHES + 1).count() <= BROADCAST_SKETCHES else rows

    def compared(star):
        """(hub, rep, n) -> pairs that link, of those that sketches let through."""
        star = star.where((F.col("rep") != F.col("hub.rep")) & fits(F.col("n"), F.col("hub.n")))
        pairs = star.select(F.col("hub.rep").alias("a"), F.col("hub.n").alias("na"), F.col("rep").alias("b"), F.col("n").alias("nb")).distinct()
        # the sketch of a member once, however many hubs it meets; hubs are few
        met = pairs.groupBy("b", "nb").agg(F.collect_list(F.struct("a", "na")).alias("hubs")).join(side("b"), "b").select("b", "nb", "pb", F.explode("hubs").alias("h")).select("b", "nb", "pb", "h.*")
        near = met.join(handy(side("a").join(star.select(F.col("hub.rep").alias("a")).distinct(), "a", "left_semi")), "a").where(plausible(F.col("pa"), F.col("pb"), F.col("na"), F.col("nb"), threshold))
        return written(linked(texts, written(near.select("a", "b")), chunks, threshold))

    # each class with one partner: the least of the hubs of its groups
    partner = groups.where("hub <> class").groupBy("class").agg(F.min("hub").alias("hub")).join(shared, "class")
    hubs = shared.select(F.col("class").alias("hub"), F.struct("rep", "n").alias("with"))
    joined = contracted(joined, compared(partner.join(hubs, "hub").select("rep", "n", F.col("with").alias("hub"))))
    place = shared.join(joined.withColumnRenamed("id", "rep"), "rep").select("class", "rep", "n", "component")
    open_ = still_open(groups.select("grp", "class").join(place, "class").select("grp", "rep", "n", "component"))  # a closed group stays closed
    for seed, most in enumerate(ROUNDS):
        members = open_.join(largest_components(open_), "grp")
        # hubs out of the largest component: the members with the smallest digests under so many seeds
        digest = lambda k: F.min(F.struct(F.xxhash64("rep", F.lit(k)).alias("digest"), "rep", "n"))
        hubs = members.where("component = main").groupBy("grp").agg(F.array_distinct(F.array(*[digest(100 * seed + k) for k in range(most)])).alias("hubs"))
        star = written(members.where("component <> main").join(hubs, "grp").select("rep", "n", F.explode("hubs").alias("hub")).distinct())
        found = compared(star)
        joined = contracted(joined, found)
        open_ = still_open(open_.drop("component").join(joined.withColumnRenamed("id", "rep"), "rep").select("grp", "rep", "n", "component"))
        if found.count() <= LINKING * star.count():
            break
    open_ = written(open_.join(side("rep"), "rep").select("grp", "rep", "n", "component", "prep"))
    one, two = (open_.select("grp", F.col("rep").alias(x), F.col("n").alias(f"n{x}"), F.col("component").alias(f"c{x}"), F.col("prep").alias(f"p{x}")) for x in "ab")
    near = (F.col("a") < F.col("b")) & (F.col("ca") != F.col("cb")) & fits(F.col("na"), F.col("nb")) & plausible(F.col("pa"), F.col("pb"), F.col("na"), F.col("nb"), threshold)
    left = written(one.join(two, "grp").where(near).select("a", "b").distinct())
    if not left.isEmpty():
        joined = contracted(joined, linked(texts, left, chunks, threshold))
    for table in (kept_texts, sketch, groups, open_):  # the result reads none of them
        dropped(table)
    label = classes.select("class", "rep").join(joined.withColumnRenamed("id", "rep"), "rep", "left").select("class", F.coalesce("component", "rep").alias("component_id"))
    return nodes.join(label, "class", "left").select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each group of near duplicates the document with the smallest id stays."""
    gone = near_duplicates(docs).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*[field(c) for c in docs.columns])
