"""Level-wise mining with a negative border, from scratch and incrementally.

One relation of sub-patterns (`parents`) drives generation, deletion and pruning: for serial
episodes the two contiguous parts that drop the first or last node ('contig'), or all parts that
drop one node ('subseq'); for multisets and itemsets all parts that drop one label. With one
relation everywhere the incremental lattice equals the one mined from scratch at the same
threshold, border included.

Counting is distributed (counting.count_kernel, one pass for everything already known); the lattice
of one batch, bounded by `max_candidates` a level, is steered from the driver. `mine_batches` is
the all-DataFrame form, which mines many batches at once and keeps nothing on the driver.
"""

from __future__ import annotations

import math
from collections import Counter as Counts
from collections.abc import Callable, Collection, Iterable
from dataclasses import dataclass, field
from itertools import islice

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftlattice.functions.thresholds import frequency_floor, slack
from driftlattice.operators import counting
from driftlattice.params import MineParams, VariantSpec
from driftlattice.sources.ledger import written

Nodes = tuple[str, ...]
Counter = Callable[[list[Nodes]], dict[Nodes, int]]


# ---------------------------------------------------------------- the relation and generation


def parents(nodes: Nodes, klass: str = "serial", relation: str = "contig") -> set[Nodes]:
    """Sub-patterns of one node less."""
    if len(nodes) == 1:
        return set()
    if klass == "serial" and relation == "contig":
        return {nodes[1:], nodes[:-1]}
    return {nodes[:k] + nodes[k + 1 :] for k in range(len(nodes))}


def with_parents(level: Iterable[Nodes], frequent: Collection[Nodes], klass: str, relation: str) -> list[Nodes]:
    """The patterns of a level (of two nodes or more) whose parents are all frequent."""
    if klass == "serial" and relation == "contig":
        return [p for p in level if p[1:] in frequent and p[:-1] in frequent]
    frequent = set(frequent)
    return [p for p in level if parents(p, klass, relation) <= frequent]


#: Candidates of a level up to which a threshold is just tried: this part of max_candidates. Beyond it _capped comes down to it from above.
TRIED = 10


def join_candidates(frequent: Iterable[Nodes], new: set[Nodes] | None = None, klass: str = "serial", relation: str = "contig", repeats: bool = True, most: int | None = None) -> set[Nodes]:
    """Patterns of one node more whose parents are all frequent; with `new`, at least one of them newly so.

    With `new` only pairs that hold a new pattern are looked at, once as the left and once as the
    right part. Beyond `most` contiguous joins OverflowError is raised before any of them is made.
    """
    frequent = set(frequent)
    fresh = frequent if new is None else new & frequent
    if not fresh:
        return set()
    size = len(next(iter(frequent)))
    out: set[Nodes] = set()
    if klass == "serial" and relation == "contig":
        by_head: dict[Nodes, list[Nodes]] = {}
        by_tail: dict[Nodes, list[Nodes]] = {}
        for p in frequent:
            by_head.setdefault(p[:-1], []).append(p[-1:])
            by_tail.setdefault(p[1:], []).append(p[:1])
        if most is not None and repeats:
            n = sum(len(by_head.get(p[1:], ())) for p in fresh)
            if len(fresh) < len(frequent):
                met = Counts(p[1:] for p in fresh)  # left parts that have been taken with their right ones
                n += sum(len(by_tail.get(p[:-1], ())) - met[p[:-1]] for p in fresh)
            if n > most:
                raise OverflowError(f"{n} candidates of size {size + 1}")
        for p in fresh:
            out.update(map(p.__add__, by_head.get(p[1:], ())))
            if len(fresh) < len(frequent):  # else every pair has been formed from its left part
                out.update([q + p for q in by_tail.get(p[:-1], ())])
    elif klass == "serial":
        symbols = {x for p in frequent for x in p}
        out.update(p[:k] + (x,) + p[k:] for p in fresh for x in symbols for k in range(size + 1))
    else:
        symbols = sorted({x for p in frequent for x in p})
        out.update(tuple(sorted((*p, x))) for p in fresh for x in symbols)
    if not repeats or klass == "itemset":
        out = {p for p in out if len(set(p)) == len(p)}
    if klass != "serial" or relation != "contig":
        out = {p for p in out if parents(p, klass, relation) <= frequent}
    return out


def join_candidates_df(frequent: DataFrame) -> DataFrame:
    """The serial contiguous join as an equi-join: (batch_id, nodes, is_new) -> distinct (batch_id, nodes).

    Two joins, new patterns as left and as right part, so old pairs are never formed.
    """
    rows = frequent.withColumn("head", F.slice("nodes", F.lit(1), F.size("nodes") - 1)).withColumn("tail", F.slice("nodes", F.lit(2), F.size("nodes") - 1))
    left = rows.select("batch_id", F.col("tail").alias("mid"), F.element_at("nodes", 1).alias("first"), F.col("is_new").alias("l"))
    right = rows.select("batch_id", F.col("head").alias("mid"), F.element_at("nodes", -1).alias("last"), F.col("is_new").alias("r"))
    joined = left.where("l").join(right, ["batch_id", "mid"]).unionByName(left.where("NOT l").join(right.where("r"), ["batch_id", "mid"]))
    return joined.select("batch_id", F.concat(F.array("first"), "mid", F.array("last")).alias("nodes")).distinct()


def mine_batches(seqs: DataFrame, symbols: DataFrame, thresholds: DataFrame, ell: int) -> DataFrame:
    """All batches mined from scratch at their own thresholds (batch_id, f_min).

    Returns (batch_id, size, key, nodes, freq, status): frequent patterns (F) and counted infrequent
    candidates (B), sizes 1 .. ell. One plan per level; levels are written, so lineage stays short.
    """
    seqs = written(seqs)
    cands = seqs.select("batch_id").distinct().crossJoin(counting.small(symbols.select(F.array("symbol").alias("nodes"))))
    out = None
    for size in range(1, ell + 1):
        level = counting.count_grid(seqs, cands).join(F.broadcast(thresholds), "batch_id")  # a row per batch
        level = level.select("batch_id", F.lit(size).cast("long").alias("size"), F.array_join("nodes", ">").alias("key"), "nodes", "freq", F.when(F.col("freq") >= F.col("f_min"), "F").otherwise("B").alias("status"))
        level = written(level)
        out = level if out is None else out.unionByName(level)
        cands = join_candidates_df(level.where("status = 'F'").select("batch_id", "nodes", F.lit(True).alias("is_new")))
    return out


# ---------------------------------------------------------------- one batch at a time


@dataclass
class Lattice:
    """Frequent patterns, their border, and which are new, per size 1 .. ell."""

    frequent: list[dict[Nodes, int]]
    border: list[dict[Nodes, int]]
    new: list[set[Nodes]]

    @property
    def rows(self) -> int:
        return sum(map(len, self.frequent)) + sum(map(len, self.border))

    def top(self) -> dict[Nodes, int]:
        return self.frequent[-1]


@dataclass
class BatchStats:
    batch_id: int
    fk_seed: int = 0
    fk: int = 0
    delta: float = 0.0
    theta: float = 0.0
    f_min: int = 1
    passes: int = 0
    n_counted: int = 0
    n_frequent: int = 0
    n_border: int = 0
    n_new: int = 0
    depth_exhausted: bool = False
    capped: bool = False
    by_level: list[tuple[int, int, int, int]] = field(default_factory=list)


class Memo:
    """Counts of one batch, each candidate counted once; knows its passes."""

    def __init__(self, count: Counter):
        self.count, self.have, self.passes, self.unkept = count, {}, 0, 0

    def __call__(self, patterns: Iterable[Nodes]) -> dict[Nodes, int]:
        patterns = list(patterns)
        try:
            return dict(zip(patterns, map(self.have.__getitem__, patterns)))
        except KeyError:
            pass
        missing = [p for p in patterns if p not in self.have] if self.have else patterns
        self.passes += 1
        got = self.count(missing)
        if len(got) < len(missing):
            got = {**dict.fromkeys(missing, 0), **got}
        self.have.update(got)
        return got if len(got) == len(patterns) else dict(zip(patterns, map(self.have.__getitem__, patterns)))

    def once(self, patterns: list[Nodes]) -> dict[Nodes, int]:
        """The same without keeping what is counted."""
        missing = [p for p in patterns if p not in self.have]
        if missing:
            self.passes, self.unkept = self.passes + 1, self.unkept + len(missing)
        got = self.count(missing) if missing else {}
        return {p: self.have[p] if p in self.have else got.get(p, 0) for p in patterns}


def kth(counts: Iterable[int], k: int) -> int:
    best = sorted((c for c in counts if c > 0), reverse=True)
    return best[k - 1] if len(best) >= k else (best[-1] if best else 0)


def mine_batch(memo: Memo, symbols: Iterable[Nodes], ell: int, f_min: int, klass: str = "serial", relation: str = "contig", repeats: bool = True, max_candidates: int = 2_000_000) -> Lattice:
    """Sizes 1 .. ell from scratch at a threshold. Raises OverflowError where a level has more candidates than allowed."""
    cands = set(symbols)
    lattice = Lattice([], [], [])
    for size in range(1, ell + 1):
        if len(cands) > max_candidates:
            raise OverflowError(f"{len(cands)} candidates of size {size}")
        counts = memo(cands)
        lattice.frequent.append({p: c for p, c in counts.items() if c >= f_min})
        lattice.border.append({p: c for p, c in counts.items() if c < f_min})
        lattice.new.append(set(lattice.frequent[-1]))
        cands = join_candidates(lattice.frequent[-1], None, klass, relation, repeats, max_candidates) if size < ell and lattice.frequent[-1] else set()
    return lattice


def lowered_topk(memo: Memo, symbols: Iterable[Nodes], k: int, ell: int, params: MineParams, step: float = 0.8) -> tuple[Lattice, int]:
    """The k best patterns of size ell by lowering a threshold from the k-th best symbol; counts are kept between rounds.

    Raises OverflowError where a level has more candidates than allowed."""
    symbols = sorted(set(symbols))
    f_min = max(1, kth(memo(symbols).values(), k))
    while True:
        lattice = mine_batch(memo, symbols, ell, f_min, params.klass, params.relation, params.repeats, params.max_candidates)
        if len(lattice.top()) >= k or f_min == 1:
            return lattice, kth(lattice.top().values(), k)
        f_min = max(1, min(f_min - 1, math.floor(f_min * step)))


def mine_topk(memo: Memo, symbols: Iterable[Nodes], k: int, ell: int, params: MineParams, step: float = 0.8) -> tuple[Lattice, int]:
    """The k best patterns of size ell, and the k-th frequency: by lowering a threshold, and depth first where a level would exceed the guard.

    The lower levels are then those of the deepest threshold within the guard; the last one always has all of the k best."""
    symbols = sorted(set(symbols))
    try:
        return lowered_topk(memo, symbols, k, ell, params, step)
    except OverflowError:
        pass
    try:
        lattice = _capped(memo, set(symbols), params.with_(ell=ell), 1)[0]
    except OverflowError:  # more symbols than the guard allows
        lattice = Lattice([{} for _ in range(ell)], [{} for _ in range(ell)], [set() for _ in range(ell)])
    best = _k_best(memo, symbols, k, ell, params, lattice.top())
    lattice.frequent[-1], lattice.new[-1] = best, set(best)
    lattice.border[-1] = {p: c for p, c in lattice.border[-1].items() if p not in best}
    return lattice, kth(best.values(), k)


def _k_best(memo: Memo, symbols: list[Nodes], k: int, ell: int, params: MineParams, found: dict[Nodes, int]) -> dict[Nodes, int]:
    """All patterns of size ell that occur at least as often as the k-th best one (all that occur, if fewer), from some that are known.

    Depth first: patterns grow by one symbol at the end, in blocks, the most frequent first, as long as neither they nor the symbol fall
    below the k-th best so far, which only rises. What is below is passed over as no longer pattern can be more frequent; nothing else is.
    Held are a block a size and the best; counts beyond those that memo has are not kept by it.
    """
    one = sorted(((p, c) for p, c in memo(symbols).items() if c > 0), key=lambda x: (-x[1], x[0]))
    best = {p: c for p, c in found.items() if c > 0}
    bar = kth(best.values(), k) if len(best) >= k else 1
    ordered, distinct = params.klass != "serial", params.klass == "itemset" or not params.repeats

    def longer(patterns: list[tuple[Nodes, int]]) -> Iterable[Nodes]:
        for p, c in patterns:
            if c < bar:
                return
            for x, n in one:
                if n < bar:
                    break
                if (ordered and x[0] < p[-1]) or (distinct and x[0] in p):
                    continue
                q = p + x
                if all(memo.have.get(part, bar) >= bar for part in parents(q, params.klass, params.relation)):
                    yield q

    def grow(patterns: list[tuple[Nodes, int]], size: int) -> None:
        nonlocal best, bar
        if size == ell:
            best.update(patterns)
            if len(best) >= k:
                bar = max(bar, kth(best.values(), k))
                best = {p: c for p, c in best.items() if c >= bar}
            return
        rest = iter(longer(patterns))
        while block := list(islice(rest, max(1, params.max_candidates // TRIED))):
            counted = sorted(((p, c) for p, c in memo.once(block).items() if c >= bar), key=lambda x: (-x[1], x[0]))
            grow(counted, size + 1)

    grow(one, 1)
    return best


def tightened(lattice: Lattice, f_min: int, klass: str, relation: str) -> Lattice:
    """The lattice at a higher threshold: demotes, and drops what then lacks a frequent parent."""
    frequent, border = [], []
    for size, (f, b) in enumerate(zip(lattice.frequent, lattice.border)):
        ok = {**f, **b}
        if size:
            ok = {p: ok[p] for p in with_parents(ok, frequent[-1].keys(), klass, relation)}
        frequent.append({p: c for p, c in ok.items() if c >= f_min})
        border.append({p: c for p, c in ok.items() if c < f_min})
    return Lattice(frequent, border, [n & f.keys() for n, f in zip(lattice.new, frequent)])


def advance(prev: Lattice | None, count: Counter, symbols: Iterable[Nodes], params: MineParams, theta_of: Callable[[float], float], delta_of: Callable[[dict, dict], float], batch_id: int = 0) -> tuple[Lattice, BatchStats]:
    """The lattice of the next batch.

    symbols: the known dictionary (size-1 patterns). The first pass counts all that is known, of all
    sizes, and new symbols; its counts of the old size-ell frequent set seed the k-th frequency and
    the drift estimate, hence the threshold. Further passes exist only for levels where a newly
    frequent pattern made new candidates. At the end the exact k-th frequency tightens the result.
    """
    memo, stats = Memo(count), BatchStats(batch_id)
    symbols = set(symbols)
    ell, klass, relation = params.ell, params.klass, params.relation
    usable = prev is not None and len(prev.top()) >= params.k
    if usable:
        known = [f | b for f, b in zip(prev.frequent, prev.border)]
        symbols |= set(known[0])
        counts = memo([*sorted(symbols), *[p for level in known[1:] for p in level]])
        seed = {p: counts[p] for p in prev.top()}
        stats.fk_seed = kth(seed.values(), params.k)
        usable = sum(c > 0 for c in seed.values()) >= params.k
    if usable:
        stats.delta = delta_of(prev.top(), seed)
        stats.theta = theta_of(stats.delta)
        f_min = frequency_floor(stats.fk_seed, stats.theta)
        frequent: list[dict] = []
        border: list[dict] = []
        new: list[set] = []
        made: set[Nodes] | None = symbols - set(known[0])
        for size in range(1, ell + 1):
            level = [*known[size - 1], *(made or ())]
            # parents of known patterns were frequent in the batch before, those of made ones are now
            if size > 1 and not prev.frequent[size - 2].keys() <= frequent[-1].keys():
                level = with_parents(level, frequent[-1].keys(), klass, relation)
            if made is None or len(level) > params.max_candidates:
                lattice, stats.fk, least = _capped(memo, symbols, params, f_min)
                stats.capped = least > f_min
                lattice.new = [f.keys() - b.keys() for f, b in zip(lattice.frequent, prev.frequent)]
                if stats.capped:
                    return lattice, _filled(stats, lattice, memo, least)
                frequent, border, new = lattice.frequent, lattice.border, lattice.new
                break
            got = memo(level)
            frequent.append({p: c for p, c in got.items() if c >= f_min})
            border.append({p: c for p, c in got.items() if c < f_min})
            new.append(frequent[-1].keys() - prev.frequent[size - 1].keys())
            stats.by_level.append((size, len(made), len(frequent[-1]), len(new[-1])))
            made = set()
            if size < ell and new[-1]:
                try:
                    made = join_candidates(frequent[-1], new[-1], klass, relation, params.repeats, params.max_candidates // TRIED) - known[size].keys()
                except OverflowError:
                    made = None
        lattice = Lattice(frequent, border, new)
        usable = len(lattice.top()) >= params.k
    if not usable:
        least = None
        try:
            fk = lowered_topk(memo, symbols, params.k, ell, params)[1]
        except OverflowError:
            lattice, fk, least = _capped(memo, symbols, params, 1)
            if len(lattice.top()) >= params.k:  # then these hold the k best
                least = None
        before = prev.frequent if prev is not None else [{}] * ell
        stats.delta = delta_of(prev.top(), memo(list(prev.top()))) if prev is not None and prev.top() else params.delta_first if params.delta == "estimate" else float(params.delta)
        stats.theta = theta_of(stats.delta)
        f_min = frequency_floor(fk, stats.theta)
        if least is not None:  # the k-th frequency lies below the guard's threshold, and the depth below that
            stats.capped, f_min = True, least
        else:
            try:
                lattice = mine_batch(memo, symbols, ell, f_min, klass, relation, params.repeats, params.max_candidates // TRIED)
            except OverflowError:
                lattice, fk, least = _capped(memo, symbols, params, f_min)
                stats.capped, f_min = least > f_min, least
        lattice.new = [f.keys() - b.keys() for f, b in zip(lattice.frequent, before)]
    stats.fk = kth(lattice.top().values(), params.k)
    exact = max(f_min, frequency_floor(stats.fk, stats.theta)) if not stats.capped else f_min
    stats.depth_exhausted = stats.fk - stats.theta <= 0
    if exact > f_min:
        lattice = tightened(lattice, exact, klass, relation)
    return lattice, _filled(stats, lattice, memo, exact)


def _capped(memo: Memo, symbols: set[Nodes], params: MineParams, f_min: int) -> tuple[Lattice, int, int]:
    """The deepest affordable lattice from f_min up, its k-th frequency and threshold.

    Comes down from the most frequent symbol, as candidates only become more: what would exceed the guard is not counted for it.
    """
    steps, most = [f_min], max(memo(sorted(symbols)).values(), default=0)
    while steps[-1] <= most:
        steps.append(math.ceil(steps[-1] * 1.25))
    found = None
    for f in reversed(steps):
        try:
            found = mine_batch(memo, symbols, params.ell, f, params.klass, params.relation, params.repeats, params.max_candidates), f
        except OverflowError:
            if found is None:
                raise
            break
    lattice, f_min = found
    return lattice, kth(lattice.top().values(), params.k), f_min


def _filled(stats: BatchStats, lattice: Lattice, memo: Memo, f_min: int) -> BatchStats:
    stats.f_min, stats.passes, stats.n_counted = f_min, memo.passes, len(memo.have) + memo.unkept
    stats.n_frequent, stats.n_border, stats.n_new = sum(map(len, lattice.frequent)), sum(map(len, lattice.border)), sum(map(len, lattice.new))
    return stats


# ---------------------------------------------------------------- runs over a stream of batches


def spark_counter(seqs: DataFrame, batch_id: int, klass: str = "serial") -> Counter:
    """Counts candidates of a class in one batch of written sequences; the filter prunes to that batch's partition."""
    one = seqs.where(F.col("batch_id") == batch_id)
    whole: list[bool] = []

    def count(patterns: list[Nodes]) -> dict[Nodes, int]:
        if not whole:
            whole.append(counting.one_slice(one))
        rows = counting.count_kernel(one, patterns, klass, whole[0]).select("cand", "freq").toArrow()
        return {patterns[c]: f for c, f in zip(rows.column("cand").to_pylist(), rows.column("freq").to_pylist())}

    return count


def shared_counters(seqs: DataFrame, ids: Iterable[int], klass: str = "serial") -> dict[int, Counter]:
    """Counters of the batches of a bounded history: what one batch asks for is counted in all of them by one pass, and kept.

    For evaluations, which run many methods over the same batches; a stream has no later batches to count.
    """
    have: dict[Nodes, dict[int, int]] = {}
    whole = counting.one_slice(seqs)

    def counter(s: int) -> Counter:
        def count(patterns: list[Nodes]) -> dict[Nodes, int]:
            missing = [p for p in patterns if p not in have]
            if missing:
                rows = counting.count_kernel(seqs, missing, klass, whole).where("freq > 0").toArrow()
                have.update((p, {}) for p in missing)
                for b, c, f in zip(*(rows.column(x).to_pylist() for x in ("batch_id", "cand", "freq"))):
                    have[missing[c]][b] = f
            return {p: have[p].get(s, 0) for p in patterns}

        return count

    return {s: counter(s) for s in ids}


def delta_rule(params: MineParams) -> Callable[[dict, dict], float]:
    """Fixed delta, or the quantile of the changes of patterns known in both batches."""
    if params.delta != "estimate":
        return lambda prev, cur: float(params.delta)

    def estimate(prev: dict, cur: dict) -> float:
        change = sorted(abs(cur[p] - prev[p]) for p in prev.keys() & cur.keys())
        if not change:
            return params.delta_first
        place = params.quantile * (len(change) - 1)
        low = math.floor(place)
        high = min(low + 1, len(change) - 1)
        return max(params.delta_min, change[low] + (place - low) * (change[high] - change[low]))

    return estimate


@dataclass
class RunResult:
    """What a run kept: reports per window, lattices and stats per batch; with missing='interval' also (window_end, key, low, high)."""

    topk: list[tuple[int, str, int, int]]
    lattices: dict[int, Lattice]
    stats: list[BatchStats]
    known: dict[int, dict[Nodes, int]] = field(default_factory=dict)
    bounds: list[tuple[int, str, int, int]] = field(default_factory=list)


def ranked(sums: dict[str, int], k: int) -> list[tuple[str, int, int]]:
    """(key, sum, rank) of the k best with ties."""
    order = sorted(sums.items(), key=lambda x: (-x[1], x[0]))
    out, rank = [], 0
    for place, (key, n) in enumerate(order, 1):
        rank = rank if place > 1 and n == order[place - 2][1] else place
        if rank > k or n <= 0:
            break
        out.append((key, n, rank))
    return out


def take_in(result: RunResult, lat: Lattice, stats: BatchStats, before: Lattice | None, seen: dict[Nodes, int], params: MineParams) -> None:
    """Keeps a batch's lattice, and the counts of size-ell patterns that the method has of it (`params.known`)."""
    s = stats.batch_id
    result.lattices[s] = lat
    result.stats.append(stats)
    have = dict(lat.top())
    if params.known in ("seeded", "counted") and before is not None:
        have.update({p: seen[p] for p in before.top() if p in seen})
    if params.known == "counted":
        have.update(lat.border[-1])
    result.known[s] = have


def report(result: RunResult, s: int, spec: VariantSpec, params: MineParams) -> list[tuple[int, str, int, int]]:
    """(window_end, key, wfreq, rank) of the window that ends with batch s, from what the run kept; nothing before a full window."""
    window = range(s - params.m + 1, s + 1)
    if any(j not in result.lattices for j in window):
        return []
    stats = {st.batch_id: st for st in result.stats}
    cands = set(result.lattices[s].top())
    if params.candidates == "window":
        cands |= {p for j in window for p in result.lattices[j].top()}
    if params.report == "persistent":
        cands = {p for p in cands if sum(result.lattices[j].top().get(p, 0) >= stats[j].fk for j in window) >= spec.hits()}
    mark = counting.MARK[params.klass]
    # a count that the method lacks is zero, or lies between zero and that batch's threshold less one
    low = {p: sum(result.known[j].get(p, 0) for j in window) for p in cands}
    rows = [(s, *row) for row in ranked({mark.join(p): n for p, n in low.items()}, params.k)]
    if params.missing == "interval":
        room = {mark.join(p): sum(max(0, stats[j].f_min - 1) for j in window if p not in result.known[j]) for p in cands}
        result.bounds += [(s, key, n, n + room[key]) for _, key, n, _ in rows]
    return rows


def run_variant(counters: dict[int, Counter], symbols: Iterable[Nodes], spec: VariantSpec, params: MineParams) -> RunResult:
    """One incremental variant over consecutive batches (batch_id -> counter).

    Known counts, candidates and reports follow `params`. Batches are taken in order; a gap restarts from the symbols.
    """
    spec = spec.checked(params.m)
    theta_of = lambda delta: slack(spec.name, params.m, spec.v, delta)
    delta_of = delta_rule(params)
    result = RunResult([], {}, [])
    for s in sorted(counters):
        seen: dict[Nodes, int] = {}

        def count(patterns, s=s, seen=seen):
            got = counters[s](patterns)
            if len(got) < len(patterns):
                got = {**dict.fromkeys(patterns, 0), **got}
            seen.update(got)
            return got

        prev = result.lattices.get(s - 1)
        lat, stats = advance(prev, count, symbols, params, theta_of, delta_of, s)
        take_in(result, lat, stats, prev, seen, params)
        result.topk += report(result, s, spec, params)
    return result


def interval(result: RunResult, params: MineParams, key: str, window_end: int) -> tuple[int, int]:
    """Window frequency of a tracked pattern as an interval: a batch where it is unknown adds at most that batch's threshold less one."""
    nodes = tuple(key.split(counting.MARK[params.klass]))
    stats = {s.batch_id: s for s in result.stats}
    low = high = 0
    for j in range(window_end - params.m + 1, window_end + 1):
        n = result.lattices[j].top().get(nodes)
        low += n or 0
        high += n if n is not None else max(0, stats[j].f_min - 1)
    return low, high


def exact_window_topk(counters: dict[int, Counter], symbols: Iterable[Nodes], params: MineParams, delta: float) -> RunResult:
    """The exact answer in two stages, begun anew with every window: mine its first batch down to fk - 2 (m - 1) delta, then add up
    just these patterns over the window's batches. Exact as long as no frequency changes by more than delta between batches. Where the
    depth is below one occurrence, patterns that the first batch lacks are no longer ruled out, and all batches are mined whole."""
    theta = slack("exact_depth", params.m, None, delta)
    mark, memos = counting.MARK[params.klass], {s: Memo(counters[s]) for s in counters}
    result = RunResult([], {}, [])
    for first in sorted(counters):
        window = range(first, first + params.m)
        if window[-1] not in counters:
            break
        lattice, fk = mine_topk(memos[first], symbols, params.k, params.ell, params)
        f_min = frequency_floor(fk, theta)
        lattice = mine_batch(memos[first], symbols, params.ell, f_min, params.klass, params.relation, params.repeats, params.max_candidates)
        cands, exhausted = set(lattice.top()), fk - theta <= 0
        if exhausted:
            cands |= {p for j in window[1:] for p in mine_batch(memos[j], symbols, params.ell, 1, params.klass, params.relation, params.repeats, params.max_candidates).top()}
        cands = sorted(cands)
        each = [memos[j](cands) for j in window]
        result.lattices[window[-1]] = lattice
        result.stats.append(_filled(BatchStats(window[-1], fk=fk, delta=delta, theta=theta, depth_exhausted=exhausted), lattice, memos[first], f_min))
        result.topk += [(window[-1], *row) for row in ranked({mark.join(p): sum(c[p] for c in each) for p in cands}, params.k)]
        memos[first] = Memo(counters[first])  # never asked again
    return result


def window_recount(counters: dict[int, Counter], symbols: Iterable[Nodes], params: MineParams, memoize: bool = True) -> RunResult:
    """The baseline that keeps every batch of the window and mines each window's top k anew by lowering."""
    memos: dict[int, Memo] = {}
    before: dict[Nodes, int] = {}  # sums of the window that ended one batch earlier
    result = RunResult([], {}, [])
    for s in sorted(counters):
        window = range(s - params.m + 1, s + 1)
        if window[0] not in counters:
            continue
        if not memoize:
            memos = {}
        if not memoize or s - 1 not in result.lattices:
            before = {}
        for j in window:
            memos.setdefault(j, Memo(counters[j]))

        def count(patterns, window=window, before=before):
            total, slid = {}, [p for p in patterns if p in before]
            if slid:  # one batch has left the window and one has come
                gone, come = memos[window[0] - 1](slid), memos[window[-1]](slid)
                total = dict(zip(slid, (n - g + c for n, g, c in zip(map(before.__getitem__, slid), gone.values(), come.values()))))
            rest = [p for p in patterns if p not in total] if len(slid) < len(patterns) else []
            each = [memos[j](rest).values() for j in window]
            total.update(zip(rest, map(sum, zip(*each))))
            return total

        memo = Memo(count)
        lattice, fk = mine_topk(memo, symbols, params.k, params.ell, params)
        result.lattices[s] = lattice
        result.stats.append(_filled(BatchStats(s, fk=fk), lattice, memo, 1))
        result.stats[-1].passes *= params.m  # a pass reads the whole window
        result.topk += [(s, *row) for row in ranked({counting.MARK[params.klass].join(p): c for p, c in lattice.top().items()}, params.k)]
        memos, before = {j: memos[j] for j in window}, memo.have
    return result


def union_variants(counters: dict[int, Counter], symbols: Iterable[Nodes], params: MineParams, sticky: bool) -> RunResult:
    """The batch-wise baselines: top k of each batch by lowering; a sticky pattern stays counted for m batches after its last hit."""
    result = RunResult([], {}, [])
    last_hit: dict[Nodes, int] = {}
    known: dict[int, dict[Nodes, int]] = {}
    tops: dict[int, set[Nodes]] = {}
    for s in sorted(counters):
        memo = Memo(counters[s])
        lattice, fk = mine_topk(memo, symbols, params.k, params.ell, params)
        top = {p for p, c in lattice.top().items() if c >= fk}
        tops[s] = top
        last_hit.update(dict.fromkeys(top, s))
        keep = {p for p, j in last_hit.items() if j >= s - params.m} if sticky else top
        known[s] = memo(sorted(keep))
        result.lattices[s] = lattice
        result.stats.append(_filled(BatchStats(s, fk=fk), lattice, memo, 1))
        result.stats[-1].n_frequent, result.stats[-1].n_border = len(keep), 0  # all that is kept for later batches
        window = range(s - params.m + 1, s + 1)
        if window[0] in counters:
            cands = {p for j in window for p in tops[j]}
            result.topk += [(s, *row) for row in ranked({counting.MARK[params.klass].join(p): sum(known[j].get(p, 0) for j in window) for p in cands}, params.k)]
    return result
