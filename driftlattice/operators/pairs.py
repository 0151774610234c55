"""All ordered pairs of symbols counted 64 at a time: each tick of a batch is a row of bits, one a symbol.

Between two ticks of a symbol a, an occurrence a > b ends if b occurs after the first and up to the second one. So for each
pair of ticks a table has the bits of all symbols that do, and a batch is counted for one a and all b by as many look-ups as a
has ticks. Counts stay in bits (plane i has bit i of every count), as do their sums over windows, so no pair has a value of
its own until it is known to reach a bound. Nothing depends on how many symbols occur at the same ticks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Words of 64 symbols that a task counts against, and words of a step: numpy's calls are worth it, and a step stays in the cache.
WORDS, STEP_WORDS = 64, 16_384
#: Names up to which their numbers are broadcast.
BROADCAST_NAMES = 1_000_000
#: Symbols of a window or batch whose pairs give a first bound.
PILOT = 48


@dataclass
class TickBits:
    """names: symbols in order; lo: first batch; bits[tick, word]; edges: where each batch's ticks begin, and the end."""

    names: list[str]
    lo: int
    bits: np.ndarray
    edges: np.ndarray

    def batches(self) -> int:
        return len(self.edges) - 1

    def of(self, j: int) -> np.ndarray:
        return self.bits[self.edges[j] : self.edges[j + 1]]


def tick_bits(frame: DataFrame) -> TickBits | None:
    """The ticks of frame(batch_id, tick, symbol), from the first to the last batch that has two. None where a batch has more than 64 ticks, which then need sequences."""
    rows, spark = frame.select("batch_id", "tick", "symbol").where("tick IS NOT NULL AND symbol IS NOT NULL"), frame.sparkSession
    ticks = rows.select("batch_id", "tick").distinct().toArrow().sort_by([("batch_id", "ascending"), ("tick", "ascending")])
    ids, n = np.unique(ticks.column("batch_id").to_numpy(), return_counts=True)
    if n.max(initial=0) > 64:
        return None
    lo, hi = (int(ids[n > 1][0]), int(ids[n > 1][-1])) if (n > 1).any() else (0, -1)
    ticks = ticks.filter((pc.field("batch_id") >= lo) & (pc.field("batch_id") <= hi))
    names = sorted(rows.select("symbol").distinct().toArrow().column(0).to_pylist())
    words = -(-len(names) // 64)
    bits = np.zeros((ticks.num_rows, words), np.uint64)

    def packed(batches) -> Iterator[pa.RecordBatch]:
        """What a task has of each tick's row."""
        held = np.zeros(bits_of, np.uint64)
        for x in batches:
            place = np.unique(x.column("place").to_numpy())
            word, first = np.unique(place >> 6, return_index=True)
            if len(word):
                held.reshape(-1)[word] |= np.bitwise_or.reduceat(np.uint64(1) << (place & 63).astype(np.uint64), first)
        some = np.flatnonzero(held.any(1))
        for low in range(0, len(some), 64):
            part = some[low : low + 64]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array([held[i].tobytes() for i in part], pa.binary())], ["at", "bits"])

    def joined(table: pa.Table) -> pa.Table:
        every = np.frombuffer(b"".join(table.column("bits").to_pylist()), np.uint64).reshape(-1, words)
        return pa.table({"at": table.column("at")[:1], "bits": pa.array([np.bitwise_or.reduce(every, axis=0).tobytes()], pa.binary())})

    if ticks.num_rows:
        bits_of = bits.shape
        at = spark.createDataFrame(ticks.append_column("at", pa.array(range(ticks.num_rows), pa.int64())))  # at most 64 a batch
        number = spark.createDataFrame(pa.table({"symbol": pa.array(names, pa.string()), "s": pa.array(range(len(names)), pa.int64())}))
        number = F.broadcast(number) if len(names) <= BROADCAST_NAMES else number
        placed = rows.join(F.broadcast(at), ["batch_id", "tick"]).join(number, "symbol").select((F.col("at") * (64 * words) + F.col("s")).alias("place"))
        got = placed.mapInArrow(packed, "at long, bits binary").groupBy("at").applyInArrow(joined, "at long, bits binary").toArrow()
        for i, row in zip(got.column("at").to_pylist(), got.column("bits")):
            bits[i] = np.frombuffer(row.as_py(), np.uint64)
    return TickBits(names, lo, bits, np.searchsorted(ticks.column("batch_id").to_numpy(), np.arange(lo, hi + 2)))


def tables(bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For ticks i < e (row i * (t + 1) + e; e = t: the end): bits of symbols that occur after i up to e, and all but those that do so at e first."""
    t, w = bits.shape
    upto, later = np.zeros((t, t + 1, w), np.uint64), np.full((t, t + 1, w), ~np.uint64(0))
    for i in range(t - 1):
        np.bitwise_or.accumulate(bits[i + 1 :], axis=0, out=upto[i, i + 1 : t])
        upto[i, t] = upto[i, t - 1]
        later[i, i + 1 : t] = ~(bits[i + 1 :] & ~upto[i, i : t - 1])
    return upto.reshape(-1, w), later.reshape(-1, w)


class Counting:
    """Counts of blocks of first symbols against the symbols of some words."""

    def __init__(self, grid: TickBits, words: slice):
        self.grid, self.words = grid, words
        self.tables = [tables(np.ascontiguousarray(grid.of(j)[:, words])) for j in range(grid.batches())]
        self.w = self.tables[0][0].shape[1] if self.tables else 0
        self.room = self.work = np.empty((0, 0, 0, 0), np.uint64)

    def counts(self, low: int, high: int, last: int) -> Iterator[list[np.ndarray]]:
        """Batch by batch the planes [first symbol, word] of the counts of symbols low .. high; those of the `last` batches stay as they are."""
        rows = high - low
        word, bit = np.arange(low, high) >> 6, (np.arange(low, high) & 63).astype(np.uint64)
        if self.room.shape[1:] != (7, rows, self.w) or len(self.room) != last:  # 7 bits hold the count of any batch; memory is touched once
            self.room = np.empty((last, 7, rows, self.w), np.uint64)
            self.work = np.empty((12, rows, self.w), np.uint64)
        got, after, state, hit, carry = self.work[:5]
        for j, (upto, later) in enumerate(self.tables):
            mine = ((self.grid.of(j)[:, word] >> bit) & np.uint64(1)).astype(bool).T
            t = mine.shape[1]
            n = mine.sum(1)
            order = np.argsort(-n, kind="stable")  # rows with a further tick come first
            row, at = np.nonzero(mine[order])
            nth = np.arange(len(row)) - np.repeat(np.cumsum(n[order]) - n[order], n[order])
            end = np.where(np.append(row[1:] == row[:-1], False), np.append(at[1:], t), t)
            pair = at * (t + 1) + end
            planes: list[np.ndarray] = []
            by_step = np.argsort(nth, kind="stable")
            edges = np.searchsorted(nth[by_step], np.arange(n.max(initial=0) + 1))
            for step, (a, b) in enumerate(zip(edges[:-1], edges[1:])):
                which = pair[by_step[a:b]]
                live = b - a
                g, s, c = got[:live], state[:live], hit[:live]
                if not step:
                    planes = [self.work[5]]
                    np.take(upto, which, axis=0, out=planes[0][:live], mode="clip")
                    planes[0][live:] = 0
                    np.take(later, which, axis=0, out=s, mode="clip")
                    continue
                np.take(upto, which, axis=0, out=g, mode="clip")
                np.bitwise_and(s, g, out=c)
                np.take(later, which, axis=0, out=after[:live], mode="clip")
                np.invert(s, out=s)
                np.bitwise_or(s, after[:live], out=s)
                if step + 1 >= 1 << len(planes):
                    planes.append(self.work[5 + len(planes)])
                    planes[-1].fill(0)
                spare = carry[:live]
                for i, plane in enumerate(planes):
                    p = plane[:live]
                    if i + 1 < len(planes):
                        np.bitwise_and(p, c, out=spare)
                    np.bitwise_xor(p, c, out=p)
                    c, spare = spare, c
            back = np.empty(rows, np.int64)
            back[order] = np.arange(rows)
            most = int(t // 2).bit_length()  # higher planes are empty
            yield [np.take(plane, back, axis=0, out=own, mode="clip") for plane, own in zip(planes[:most], self.room[j % last])]


class Sums:
    """Sums of counts in bits, of which counts are added and taken away."""

    def __init__(self, most: int, shape: tuple[int, int]):
        self.planes = [np.zeros(shape, np.uint64) for _ in range(max(1, most.bit_length()))]
        self.t, self.u, self.c = (np.empty(shape, np.uint64) for _ in range(3))

    def add(self, x: list[np.ndarray]) -> None:
        t, u, c = self.t, self.u, self.c
        for i, s in enumerate(self.planes):
            if i < len(x):
                np.bitwise_xor(s, x[i], out=t)
                np.bitwise_and(s, x[i], out=u)
                if i:
                    np.bitwise_xor(t, c, out=s)
                    np.bitwise_and(t, c, out=c)
                    np.bitwise_or(c, u, out=c)
                else:
                    s[...], c, u = t, u, c
            elif x:
                np.bitwise_and(s, c, out=t)
                np.bitwise_xor(s, c, out=s)
                c, t = t, c

    def take(self, x: list[np.ndarray]) -> None:
        t, u, c = self.t, self.u, self.c
        for i, s in enumerate(self.planes):
            if i < len(x):
                np.bitwise_xor(s, x[i], out=t)
                np.bitwise_and(x[i], t, out=u)
                if i:
                    np.bitwise_xor(t, c, out=s)
                    np.bitwise_and(c, s, out=c)
                    np.bitwise_or(c, u, out=c)
                else:
                    s[...], c, u = t, u, c
            elif x:
                np.bitwise_xor(s, c, out=s)
                np.bitwise_and(c, s, out=c)


def at_least(planes: list[np.ndarray], bound: int) -> np.ndarray | None:
    """Bits of the values that are at least bound (1 or more); None where there are none."""
    if not planes or bound >> len(planes):
        return None
    out = None
    for i, plane in enumerate(planes):
        if bound >> i & 1:
            out = plane.copy() if out is None else np.bitwise_and(out, plane, out=out)
        elif out is not None:
            np.bitwise_or(out, plane, out=out)
    return out


def places(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of the bits that are set: the word in the flat mask, and the bit."""
    word = np.flatnonzero(mask)
    row, bit = np.nonzero(np.unpackbits(mask.reshape(-1)[word].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
    return word[row], bit


def values(planes: list[np.ndarray], word: np.ndarray, bit: np.ndarray) -> np.ndarray:
    out, shift = np.zeros(len(word), np.int64), bit.astype(np.uint64)
    for i, plane in enumerate(planes):
        out |= (plane.reshape(-1)[word] >> shift & np.uint64(1)).astype(np.int64) << i
    return out


def mask_pairs(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Occurrences of a before b in one batch, from the ticks of each symbol as bits; shapes are broadcast."""
    x, y = np.broadcast_arrays(first, second)
    out, one = np.zeros(x.shape, np.uint8), x.dtype.type(1)
    while True:
        at = x & (~x + one)  # the first bit; from no bit the step below leaves none
        y = y & ~((at << one) - one)
        at = y & (~y + one)
        found = at != 0
        if not found.any():
            return out
        out += found
        x = x & ~((at << one) - one)


def masks(grid: TickBits, j: int, which: np.ndarray) -> np.ndarray:
    """The ticks of some symbols in a batch as bits."""
    mine = grid.of(j)[:, which >> 6] >> (which & 63).astype(np.uint64) & np.uint64(1)
    return np.bitwise_or.reduce(mine << np.arange(len(mine), dtype=np.uint64)[:, None], axis=0) if len(mine) else np.zeros(len(which), np.uint64)


def occurring(grid: TickBits) -> np.ndarray:
    """[batch, symbol]: ticks at which a symbol occurs."""
    n = len(grid.names)
    each = [np.unpackbits(grid.of(j).view(np.uint8), axis=1, bitorder="little", count=n).sum(0, dtype=np.int32) for j in range(grid.batches())]
    return np.stack(each) if each else np.zeros((0, n), np.int32)


def kth_best(x: np.ndarray, k: int) -> int:
    """The k-th best of some values, and 1 at least: a bound that whatever is among the k best of more values reaches."""
    return max(1, int(np.partition(x, -k)[-k])) if len(x) >= k else 1


def pilot(grid: TickBits, m: int, k: int) -> np.ndarray:
    """By window a bound that its k best pairs reach: the k-th best among pairs of its commonest symbols."""
    ticks = occurring(grid)
    out = []
    for end in range(m - 1, len(ticks)):
        which = np.argsort(-ticks[end - m + 1 : end + 1].sum(0), kind="stable")[:PILOT]
        total = sum((mask_pairs(x[:, None], x[None, :]).astype(np.int64) for x in (masks(grid, j, which) for j in range(end - m + 1, end + 1))), np.zeros((len(which), len(which)), np.int64))
        out.append(kth_best(total.reshape(-1), k))
    return np.array(out, np.int64)


def common_pairs(grid: TickBits, most: int = 100) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent pairs among each batch's commonest symbols."""
    a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for j, n in enumerate(occurring(grid)):
        which = np.argsort(-n, kind="stable")[:PILOT]
        x = masks(grid, j, which)
        top = np.argsort(-mask_pairs(x[:, None], x[None, :]).reshape(-1).astype(np.int64), kind="stable")[:most]
        a.append(which[top // len(which)])
        b.append(which[top % len(which)])
    return np.concatenate(a), np.concatenate(b)


class Best:
    """Bounds that rise with the k best values met, by number."""

    def __init__(self, bounds: np.ndarray, k: int):
        self.bounds, self.k = bounds.tolist(), k
        self.have: list[np.ndarray] = [np.zeros(0, np.int64)] * len(self.bounds)

    def meet(self, i: int, got: np.ndarray) -> None:
        have = np.concatenate([self.have[i], got])
        if len(have) >= self.k:
            have = np.partition(have, -self.k)[-self.k :]
            self.bounds[i] = max(self.bounds[i], int(have.min()))
        self.have[i] = have


def each_block(spark, grid: TickBits, block: int | None, run, schema: str, *more) -> DataFrame:
    """What run(counting, blocks, *more) yields, in tasks of some words of second symbols and some blocks of first ones; blocks: (low, high)."""
    n, words = len(grid.names), grid.bits.shape[1]
    w = min(WORDS, max(1, words))
    block = block or max(1, min(STEP_WORDS // w, -(-n // 32)))
    parts, lows = -(-words // w), list(range(0, n, block))
    share = max(1, -(-len(lows) // max(1, 64 // max(1, parts))))
    jobs = [(at, i) for at in range(parts) for i in range(0, len(lows), share)]
    shared = spark.sparkContext.broadcast((grid, more))

    def task(batches) -> Iterator[pa.RecordBatch]:
        for x in batches:
            for job in x.column("id").to_pylist():
                (grid, more), (at, i) = shared.value, jobs[job]
                yield from run(Counting(grid, slice(at * w, (at + 1) * w)), [(low, min(n, low + block)) for low in lows[i : i + share]], *more)

    return spark.range(0, len(jobs), 1, max(1, len(jobs))).mapInArrow(task, schema)


def walk(counting: Counting, low: int, high: int, m: int, last: int) -> Iterator[tuple[int, list[np.ndarray], list[np.ndarray], dict[int, list[np.ndarray]]]]:
    """Batch by batch the counts of symbols low .. high, their sums over m batches, and the counts of the `last` batches (more than m)."""
    sums, held = Sums(int(m * (np.diff(counting.grid.edges).max(initial=0) // 2)), (high - low, counting.w)), {}
    for j, planes in enumerate(counting.counts(low, high, last)):
        held.pop(j - last, None)
        held[j] = planes
        if j >= m:
            sums.take(held[j - m])
        sums.add(planes)
        yield j, planes, sums.planes, held


def record(counting: Counting, low: int, word: np.ndarray, bit: np.ndarray, end: int, wfreq: np.ndarray, name: str = "", n: int = 1) -> pa.RecordBatch:
    a, of = np.divmod(word, counting.w)
    return pa.RecordBatch.from_pydict({"name": pa.array([name] * len(word), pa.string()), "end": np.full(len(word), end, np.int64), "a": low + a, "b": (counting.words.start + of) * 64 + bit, "wfreq": wfreq, "n": np.full(len(word), n, np.int64)})


#: What runs yield: reports (name; '' for all pairs' own) by the window's last batch; and with name 'spectrum' how many pairs (n) have a frequency in a batch.
ROWS = "name string, end long, a long, b long, wfreq long, n long"


def window_rows(counting: Counting, blocks: list[tuple[int, int]], m: int, k: int, bounds: np.ndarray, batch_bounds: np.ndarray | None = None) -> Iterator[pa.RecordBatch]:
    """ROWS of pairs that may be among a window's k best: all that reach the bounds, which rise on the way. With batch_bounds also spectra from the k-th best of each batch on."""
    best = Best(bounds, k)
    floor = [] if batch_bounds is None else batch_bounds.tolist()
    spectra: list[dict[int, int]] = [{} for _ in floor]
    for low, high in blocks:
        for j, planes, sums, _ in walk(counting, low, high, m, m + 1):
            if floor:
                f = floor[j]
                while (reached := at_least(planes, f)) is not None and (n := int(np.bitwise_count(reached).sum())):
                    spectra[j][f] = spectra[j].get(f, 0) + n
                    f += 1
                while spectra[j].get(floor[j] + 1, 0) >= k:
                    floor[j] += 1
            if j < m - 1:
                continue
            reached = at_least(sums, best.bounds[j - m + 1])
            if reached is None or not reached.any():
                continue
            word, bit = places(reached)
            got = values(sums, word, bit)
            best.meet(j - m + 1, got)
            keep = got >= best.bounds[j - m + 1]
            yield record(counting, low, word[keep], bit[keep], j, got[keep])
    for j, of in enumerate(spectra):
        for f, n in of.items():
            if f >= floor[j] and n > of.get(f + 1, 0):
                yield pa.RecordBatch.from_pydict({"name": ["spectrum"], "end": [j], "a": [-1], "b": [-1], "wfreq": [f], "n": [n - of.get(f + 1, 0)]})


@dataclass
class Report:
    """A method's report in closed form: which counts it has (from its floors on, `back` batches longer), and whether candidates are those of the whole window."""

    floors: np.ndarray
    back: int
    whole: bool

    def sums(self, freq: np.ndarray, first: int, m: int) -> np.ndarray:
        """[window, pair] of the windows within batches from `first` on, from their counts [batch, pair]; 0: not a candidate. Right from `back` batches after `first` on, or from the first batch of all."""
        took = (freq > 0) & (freq >= self.floors[first : first + len(freq), None])
        held = took.copy()
        for i in range(1, self.back + 1):
            held[i:] |= took[:-i]
        run = np.cumsum(np.concatenate([np.zeros((2, 1, freq.shape[1]), np.int32), np.stack([freq * held, took]).astype(np.int32)], axis=1), axis=1, dtype=np.int32)
        total, any_took = run[:, m:] - run[:, :-m]
        return np.where(any_took > 0 if self.whole else took[m - 1 :], total, 0)


#: Windows whose candidates are looked at together.
TOGETHER = 64


def report_rows(counting: Counting, blocks: list[tuple[int, int]], m: int, k: int, reports: dict[str, Report], bounds: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
    """ROWS of pairs that may be among a report's k best: candidates whose sum over the whole window, which is no less, reaches the bound are looked at one by one."""
    best = {name: Best(bounds[name], k) for name in reports}
    nb = counting.grid.batches()
    for low, high in blocks:
        taken: dict[bytes, dict[int, np.ndarray]] = {r.floors.tobytes(): {} for r in reports.values()}
        met: dict[str, np.ndarray] = {}  # bits of pairs that are a candidate of a report in one of the windows
        start = m - 1
        for j, planes, sums, held in walk(counting, low, high, m, min(nb, TOGETHER + 2 * m) + 1):
            for r in reports.values():
                of = taken[r.floors.tobytes()]
                if j not in of:
                    of.pop(j - m, None)
                    of[j] = at_least(planes, int(r.floors[j]))
            if j < m - 1:
                continue
            reach: dict[int, np.ndarray | None] = {}
            cands: dict[tuple[bytes, bool], np.ndarray | None] = {}
            for name, r in reports.items():
                bound, which = best[name].bounds[j - m + 1], (r.floors.tobytes(), r.whole)
                if which not in cands:
                    some = [x for x in (taken[which[0]].values() if r.whole else [taken[which[0]][j]]) if x is not None]
                    cands[which] = np.bitwise_or.reduce(some) if len(some) > 1 else some[0] if some else None
                if cands[which] is None:
                    continue
                if bound not in reach:
                    reach[bound] = at_least(sums, bound)
                if reach[bound] is not None:
                    both = reach[bound] & cands[which]
                    met[name] = np.bitwise_or(met[name], both, out=both) if name in met else both
            if j - start + 1 < TOGETHER and j < nb - 1:
                continue
            for name, bits in met.items():
                r, (word, bit) = reports[name], places(bits)
                first = max(0, start + 1 - m - r.back)
                for lot in range(0, len(word), 20_000):
                    w, of_bit = word[lot : lot + 20_000], bit[lot : lot + 20_000]
                    freq = np.stack([values(held[i], w, of_bit) for i in range(first, j + 1)])
                    for end, got in enumerate(r.sums(freq, first, m)[start - first - m + 1 :], start):
                        at = np.flatnonzero(got >= best[name].bounds[end - m + 1])
                        if len(at):
                            best[name].meet(end - m + 1, got[at].astype(np.int64))
                            at = at[got[at] >= best[name].bounds[end - m + 1]]
                            yield record(counting, low, w[at], of_bit[at], end, got[at].astype(np.int64), name)
            met, start = {}, j + 1


def report_bounds(grid: TickBits, m: int, k: int, reports: dict[str, Report], a: np.ndarray, b: np.ndarray) -> dict[str, np.ndarray]:
    """What each report's k best reach, from any pairs (a, b): the k-th best of the different ones."""
    nb = grid.batches()
    a, b = np.divmod(np.unique(a * max(1, len(grid.names)) + b), max(1, len(grid.names)))
    freq = np.stack([mask_pairs(masks(grid, j, a), masks(grid, j, b)).astype(np.int32) for j in range(nb)]) if nb else np.zeros((0, len(a)), np.int64)
    out = {}
    for name, r in reports.items():
        sums = r.sums(freq, 0, m) if nb >= m else []
        out[name] = np.array([kth_best(x[x > 0], k) for x in sums], np.int64)
    return out
