"""Counting candidates over batches: expression plans, sliced plans, and an Arrow kernel.

`seqs` has (batch_id, seg, seq) from batching.sequences; `cands` has (nodes array<string>).
Three routes give the same counts:

* count_serial / count_parallel / count_partial: one higher-order expression per (batch, candidate),
  all inside the JVM; candidates are broadcast when their number is checked to be small;
* count_segmented: the same over slices of a batch, whose summaries compose, so a batch of any size
  is counted in parallel and only ell numbers per candidate and slice are shuffled;
* count_kernel and count_grid: Arrow kernels that jump from match to match through sorted (symbol,
  place) keys, for many candidates over long slices. The kernel takes one bounded list for all
  batches, the grid a table of candidates per batch, dealt in blocks that meet every slice once.

The kernels know three classes: serial episodes, parallel ones (multisets of labels, which need a
batch in one slice) and itemsets (ticks that hold all labels; slices add up).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftlattice.functions import episodes as E
from driftlattice.operators import pairs
from driftlattice.params import EpisodeSpec
from driftlattice.plans.window import topk_with_ties
from driftlattice.sources.ledger import written

#: Candidates that may be broadcast to a counting join; beyond it the join shuffles.
BROADCAST_CANDIDATES = 100_000
#: Candidates of a batch that meet a slice in one task of the grid.
GRID_BLOCK = 50_000
MARK = {"serial": ">", "parallel": "+", "itemset": "+"}


def small(df: DataFrame, most: int = BROADCAST_CANDIDATES) -> DataFrame:
    """`df` marked for broadcast if it is checked to have at most `most` rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def enumerate_all(symbols: DataFrame, ell: int, kind: str = "serial", repeats: bool = True) -> DataFrame:
    """(nodes) of all episodes of a size over an alphabet (symbol): brute force for small alphabets."""
    out = symbols.select(F.array("symbol").alias("nodes"))
    one = small(symbols.select(F.col("symbol").alias("nxt")))
    for _ in range(ell - 1):
        out = out.crossJoin(one)
        if kind != "serial":
            last = F.element_at("nodes", -1)
            out = out.where(F.col("nxt") >= last if repeats else F.col("nxt") > last)
        elif not repeats:
            out = out.where(~F.array_contains("nodes", F.col("nxt")))
        out = out.select(F.concat("nodes", F.array("nxt")).alias("nodes"))
    return out


def _pairs(seqs: DataFrame, cands: DataFrame) -> DataFrame:
    """Sequences beside candidates: by batch where candidates have one, else every candidate in every batch."""
    return seqs.join(small(cands), "batch_id") if "batch_id" in cands.columns else seqs.crossJoin(small(cands))


def count_serial(seqs: DataFrame, cands: DataFrame, ell: int, ties: bool = True, zeros: bool = False) -> DataFrame:
    out = _pairs(seqs, cands).select("batch_id", "nodes", E.serial_frequency(F.col("seq"), F.col("nodes"), ell, ties).alias("freq"))
    return _named(out if zeros else out.where("freq > 0"), ">")


def count_parallel(seqs: DataFrame, cands: DataFrame, ties: bool = True, zeros: bool = False) -> DataFrame:
    out = _pairs(seqs, cands).select("batch_id", "nodes", E.parallel_frequency(F.col("seq"), F.col("nodes"), ties).alias("freq"))
    return _named(out if zeros else out.where("freq > 0"), "+")


def count_partial(seqs: DataFrame, spec: EpisodeSpec, ties: bool = True) -> DataFrame:
    nodes = F.array(*[F.lit(x) for x in spec.nodes])
    preds = F.array(*[F.array(*[F.lit(q) for q in p]).cast("array<int>") for p in spec.preds])
    return seqs.select("batch_id", F.lit(spec.key).alias("key"), E.partial_frequency(F.col("seq"), nodes, preds, ties).alias("freq"))


def _named(df: DataFrame, mark: str) -> DataFrame:
    return df.select("batch_id", F.array_join("nodes", mark).alias("key"), "nodes", "freq")


def count_segmented(seqs: DataFrame, cands: DataFrame, ell: int, ties: bool = True) -> DataFrame:
    """(batch_id, key, nodes, freq) from several slices per batch: the grid over every candidate in every batch."""
    every = small(seqs.select("batch_id").distinct()).crossJoin(cands.select("nodes"))
    return _named(count_grid(seqs, every).where("freq > 0"), ">")


def count_carried(seqs: DataFrame, cands: DataFrame, ell: int, ties: bool = True) -> DataFrame:
    """(batch_id, key, nodes, freq): occurrences completed in each batch when the automaton's state crosses batch borders."""
    sums = seqs.crossJoin(small(cands)).select("batch_id", "nodes", E.slice_moves(F.col("seq"), F.col("nodes"), ell, ties).alias("g"))
    # one summary per batch and candidate: the running fold is over batches, not over events
    upto = Window.partitionBy("nodes").orderBy("batch_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    run = sums.withColumn("parts", F.collect_list("g").over(upto)).withColumn("done", F.floor(E.fold_slices(F.col("parts"), ell) / ell).cast("long"))
    before = F.coalesce(F.lag("done").over(Window.partitionBy("nodes").orderBy("batch_id")), F.lit(0))
    return _named(run.select("batch_id", "nodes", (F.col("done") - before).alias("freq")), ">")


def waits(keys: np.ndarray, width: int, cands: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Moves of each automaton over a slice: row i of `cands` (symbol ids), entered at residue start[i].

    keys: sorted symbol * width + place. Each step sends all automata that can still move to their
    next match, so the work is the number of moves, not places times candidates.
    """
    ell = cands.shape[1]
    moves = np.zeros(len(cands), np.int64)
    place = np.zeros(len(cands), np.int64)
    live = np.arange(len(cands))
    while len(live):
        want = cands[live, (start[live] + moves[live]) % ell] * width
        at = np.searchsorted(keys, want + place[live])
        found = at < len(keys)
        found[found] = keys[at[found]] < want[found] + width
        live, at, want = live[found], at[found], want[found]
        place[live] = keys[at] - want + 1
        moves[live] += 1
    return moves


def parallel_waits(keys: np.ndarray, width: int, cands: np.ndarray) -> np.ndarray:
    """Occurrences of each multiset of labels (row of sorted symbol ids): each round goes to the tick where the last label is found."""
    n, ell = cands.shape
    again = np.zeros(cands.shape, np.int64)  # equal labels before a node: it takes so many matches more
    for i in range(1, ell):
        again[:, i] = np.where(cands[:, i] == cands[:, i - 1], again[:, i - 1] + 1, 0)
    done, place, live = np.zeros(n, np.int64), np.zeros(n, np.int64), np.arange(n)
    while len(live):
        want = cands[live] * width
        at = np.searchsorted(keys, want + place[live][:, None]) + again[live]
        found = at < len(keys)
        found[found] = keys[at[found]] < (want + width)[found]
        whole = found.all(1)
        live, at, want = live[whole], at[whole], want[whole]
        place[live] = (keys[at] - want).max(1) + 1 if len(live) else place[live]
        done[live] += 1
    return done


def itemset_ticks(keys: np.ndarray, width: int, cands: np.ndarray) -> np.ndarray:
    """Ticks that hold all labels of each set (row of symbol ids)."""
    edge = np.searchsorted(keys, np.arange(int(cands.max(initial=0)) + 2) * width)
    out = np.zeros(len(cands), np.int64)
    for k, row in enumerate(cands):
        lists = sorted((keys[edge[x] : edge[x + 1]] - x * width for x in row), key=len)
        have = lists[0]
        for other in lists[1:]:
            have = have[np.isin(have, other, assume_unique=True)]
        out[k] = len(have)
    return out


#: Events of a block in which pair_matrix keeps running counts of every symbol.
PAIR_BLOCK = 8192


def pair_matrix(places: list[np.ndarray]) -> np.ndarray:
    """[a, b]: occurrences of a before b for all pairs of symbols, from sorted places that no two symbols share.

    Between two events of b an occurrence ends at the second exactly where an a lies between them. Running counts of
    all symbols tell this for all a at once, so the work is events times symbols, whatever the number of pairs.
    """
    n = len(places)
    symbol = np.repeat(np.arange(n), [len(x) for x in places])[np.argsort(np.concatenate(places), kind="stable")] if n else np.zeros(0, np.int64)
    out, since = np.zeros((n, n), np.int64), np.zeros((n, n), bool)  # rows are b; since: an a has come after the last b
    for low in range(0, len(symbol), PAIR_BLOCK):
        block = symbol[low : low + PAIR_BLOCK]
        run = np.zeros((len(block), n), np.uint16)
        run[np.arange(len(block)), block] = 1
        np.cumsum(run, axis=0, dtype=np.uint16, out=run)
        order = np.argsort(block, kind="stable")
        which, first = np.unique(block[order], return_index=True)
        for b, rows in zip(which, np.split(order, first[1:])):
            seen = run[rows]
            out[b] += since[b] | (seen[0] > 0)
            out[b] += np.add.reduce((seen[1:] != seen[:-1]).view(np.uint8), axis=0, dtype=np.uint16)
            since[b] = run[-1] != seen[-1]
        rest = np.setdiff1d(np.arange(n), which, assume_unique=True)
        since[rest] |= run[-1] > 0
    own = np.arange(n)
    out[own, own] = [len(x) // 2 for x in places]
    return out.T


def units(places: dict[str, np.ndarray]) -> dict[str, tuple[str, int]]:
    """symbol -> (head, number): symbols that only occur as whole runs head, next, ... without an event between are one unit.

    Found in the places themselves; a symbol without such neighbours is a unit of its own. No two symbols share a place.
    """
    names = [x for x in places if len(places[x])]
    every = np.sort(np.concatenate([places[x] for x in names])) if names else np.zeros(0, np.int64)
    first = np.searchsorted(every, np.array([places[x][0] for x in names], every.dtype)).tolist()
    opened = dict(zip(first, range(len(names))))
    after: dict[int, int] = {}
    ranks: dict[int, np.ndarray] = {}
    for x, place in enumerate(first):
        y = opened.get(place + 1)  # what stands behind each x opens behind the first one
        own = places[names[x]]
        if y is not None and len(own) == len(places[names[y]]) and own[-1] < every[-1]:
            if np.array_equal(own + 1, places[names[y]]):  # no place lies between
                after[x] = y
                continue
            behind = (ranks[x] if x in ranks else np.searchsorted(every, own)) + 1
            if np.array_equal(every[behind], places[names[y]]):
                after[x], ranks[y] = y, behind
    out = {}
    for head in set(range(len(names))) - set(after.values()):
        x, i = head, 0
        while x is not None:
            out[names[x]] = (names[head], i)
            x, i = after.get(x), i + 1
    return out


def in_units(pattern: tuple[str, ...], of: dict[str, tuple[str, int]]) -> tuple[tuple[str, ...], bool]:
    """The pattern of unit heads with the same count, and whether an occurrence may start in the run that ends the one before.

    A node that stands behind the node before it in one unit is met in the same run, so it takes no step.
    """
    nodes = [of[x] for x in pattern]
    heads = [nodes[0][0]]
    for (u, i), (v, j) in zip(nodes, nodes[1:]):
        if u != v or j <= i:
            heads.append(v)
    return tuple(heads), nodes[0][0] == nodes[-1][0] and nodes[0][1] > nodes[-1][1]


def place_counts(places: dict[str, np.ndarray], cands: list[tuple[str, ...]], held: dict[tuple[str, str], int] | None = None, again: set[int] | frozenset[int] = frozenset()) -> list[int]:
    """Frequencies of serial episodes of any size from the sorted places of symbols, which no two symbols share.

    held: pairs counted before, which grows by all that a matrix counts. Lower thresholds ask for further pairs of symbols
    little rarer than those asked now, so a matrix takes in symbols down to half as frequent.
    again: candidates (by number, of two nodes or more and equal ends) whose occurrences may start at the place that ends the one before.
    """
    held = {} if held is None else held
    out = [0] * len(cands)
    follow: dict[tuple[str, str], np.ndarray] = {}

    def after(a: str, b: str) -> np.ndarray:
        """Per place of a the number of the first b after it; one more entry stands for no place at all."""
        if (a, b) not in follow:
            follow[a, b] = np.append(np.searchsorted(places[b], places[a], "right"), len(places[b]))
        return follow[a, b]

    pairs: list[int] = []
    deep: list[int] = []
    for k, c in enumerate(cands):
        if all(x in places for x in c):
            if len(c) == 1:
                out[k] = len(places[c[0]])
            elif k in again:
                deep.append(k)
            else:
                if c in held:
                    out[k] = held[c]
                else:
                    (pairs if len(c) == 2 else deep).append(k)
    names = sorted({x for k in pairs for x in cands[k]})
    # a step of the matrix costs about a tenth of one search
    if sum(len(places[cands[k][1]]) for k in pairs) * 10 > sum(len(places[x]) for x in names) * len(names):
        least = min(len(places[x]) for x in names) / 2
        wide = [x for x in places if len(places[x]) >= least]
        names = wide if len(wide) < 2 * len(names) + 400 else names
        for a, row in zip(names, pair_matrix([places[x] for x in names]).tolist()):
            held.update(zip([(a, b) for b in names], row))
        for k in pairs:
            out[k] = held[cands[k]]
    else:
        for k in pairs:
            a, b = cands[k]
            if a == b:
                out[k] = len(places[a]) // 2
            else:
                to = np.searchsorted(places[b], places[a])
                out[k] = int(np.count_nonzero(np.diff(to[to < len(places[b])], prepend=-1)))
    for k in sorted(deep, key=lambda k: cands[k]):
        c = cands[k]
        last = after(c[0], c[1])
        for a, b in zip(c[1:], c[2:]):
            last = after(a, b)[last]
        # whole occurrences by their start; later starts end no earlier, so those that do not end come last
        whole = int(np.searchsorted(last, len(places[c[-1]])))
        nxt = (last[:whole] if k in again else after(c[-1], c[0])[last[:whole]]).tolist()
        i = n = 0
        while i < whole:
            i = nxt[i]
            n += 1
        out[k] = n
        if len(follow) > 4096:
            follow.clear()
    return out


def slice_keys(seq: pa.Array, symbols: pa.Array) -> tuple[np.ndarray, int]:
    """A slice's ticks (labels, or lists of labels) as sorted symbol * width + place, and the width."""
    if pa.types.is_list(seq.type):
        place, flat = np.repeat(np.arange(len(seq)), pc.list_value_length(seq).to_numpy(zero_copy_only=False).astype(np.int64)), seq.flatten()
    else:
        place, flat = np.arange(len(seq)), seq
    number = pc.fill_null(pc.index_in(flat, value_set=symbols), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    known = number >= 0
    return np.unique(number[known] * (len(seq) + 1) + place[known]), len(seq) + 1


def slice_counts(seq: pa.Array, symbols: pa.Array, nodes: np.ndarray, klass: str, whole: bool) -> np.ndarray:
    """Per candidate of one size a row of moves by entry residue (serial; whole slices: residue 0 only), or its count."""
    keys, width = slice_keys(seq, symbols)
    if klass == "parallel":
        return parallel_waits(keys, width, nodes)[:, None]
    if klass == "itemset":
        return itemset_ticks(keys, width, nodes)[:, None]
    starts = 1 if whole else nodes.shape[1]
    return waits(keys, width, np.repeat(nodes, starts, 0), np.tile(np.arange(starts), len(nodes))).reshape(-1, starts)


def _folded(parts, size, klass: str):
    """Column: frequency from the sorted slices' counts array<struct<seg, g>>."""
    if klass == "itemset":
        return F.aggregate(parts, F.lit(0).cast("long"), lambda n, x: n + F.element_at(x["g"], 1))
    if klass == "parallel":
        return F.when(F.size(parts) > 1, F.raise_error(F.lit("parallel episodes are counted over whole batches")).cast("long")).otherwise(F.element_at(F.element_at(parts, 1)["g"], 1))
    moves = F.aggregate(F.transform(parts, lambda x: x["g"]), F.lit(0).cast("long"), lambda n, g: n + F.element_at(g, (n % F.size(g) + 1).cast("int")))
    return F.floor(moves / size).cast("long")


def one_slice(seqs: DataFrame) -> bool:
    """Whether every batch is in one slice."""
    return not seqs.where("seg > 0").limit(1).count()


def count_kernel(seqs: DataFrame, cands: list[tuple[str, ...]], klass: str = "serial", whole: bool | None = None) -> DataFrame:
    """(batch_id, cand int, freq long) for candidates of one or several sizes, by their place in the list.

    The candidate list is bounded by the caller (the lattice's guard) and travels as one broadcast.
    whole: whether batches have one slice each, where the caller knows.
    """
    symbols = sorted({x for c in cands for x in c})
    number = {x: k for k, x in enumerate(symbols)}
    groups = [(np.array([k for k, c in enumerate(cands) if len(c) == ell]), np.array([[number[x] for x in c] for c in cands if len(c) == ell], np.int64)) for ell in sorted({len(c) for c in cands})]
    whole = one_slice(seqs) if whole is None else whole
    shared = seqs.sparkSession.sparkContext.broadcast((symbols, groups))

    def run(batches):
        symbols, groups = shared.value
        symbols = pa.array(symbols, pa.string())
        for batch in batches:
            ids, segs, seq = (batch.column(c) for c in ("batch_id", "seg", "seq"))
            for i in range(batch.num_rows):
                for which, nodes in groups:
                    g = slice_counts(seq[i].values, symbols, nodes, klass, whole)
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(g) + 1, dtype=np.int32) * g.shape[1]), pa.array(g.ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(which), ids[i].as_py(), np.int64)), pa.array(np.full(len(which), segs[i].as_py(), np.int32)), pa.array(which.astype(np.int32)), pa.array(np.full(len(which), nodes.shape[1], np.int32)), lists], ["batch_id", "seg", "cand", "size", "g"])

    out = seqs.select("batch_id", "seg", "seq").mapInArrow(run, "batch_id long, seg int, cand int, size int, g array<long>")
    if whole:  # one slice a batch: nothing to fold, nothing to shuffle
        g = F.element_at("g", 1)
        return out.select("batch_id", "cand", (F.floor(g / F.col("size")).cast("long") if klass == "serial" else g).alias("freq"))
    folded = out.groupBy("batch_id", "cand", "size").agg(F.array_sort(F.collect_list(F.struct("seg", "g"))).alias("parts"))
    return folded.select("batch_id", "cand", _folded(F.col("parts"), F.col("size"), klass).alias("freq"))


def count_grid(seqs: DataFrame, cands: DataFrame, klass: str = "serial") -> DataFrame:
    """(batch_id, nodes, freq long) of cands(batch_id, nodes), each in its batch, zeros included.

    Candidates are dealt to blocks of about GRID_BLOCK a batch; a block meets each slice of its batch
    in a task of its own, so neither a long batch nor a long list of candidates is held by one task.
    """
    most = cands.groupBy("batch_id").count().agg(F.max("count")).first()[0]
    if not most:
        return cands.select("batch_id", "nodes", F.lit(0).cast("long").alias("freq"))
    blocks, whole = -(-most // GRID_BLOCK), one_slice(seqs)
    dealt = cands.select("batch_id", "nodes", F.pmod(F.xxhash64("nodes"), F.lit(blocks)).alias("block")).join(seqs.select("batch_id", "seg"), "batch_id")
    slices = seqs.select("batch_id", "seg", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"), "seq")

    def run(part: pa.Table, asked: pa.Table) -> pa.Table:
        if not part.num_rows or not asked.num_rows:
            return pa.table({"batch_id": pa.array([], pa.int64()), "seg": pa.array([], pa.int32()), "nodes": pa.array([], pa.list_(pa.string())), "g": pa.array([], pa.list_(pa.int64()))})
        nodes = asked.column("nodes").combine_chunks()
        size = pc.list_value_length(nodes).to_numpy(zero_copy_only=False)
        flat = pc.dictionary_encode(nodes.flatten())
        flat = flat.combine_chunks() if isinstance(flat, pa.ChunkedArray) else flat
        number, ends = flat.indices.to_numpy().astype(np.int64), np.cumsum(size)
        out = []
        for ell in np.unique(size):
            rows = np.flatnonzero(size == ell)
            g = slice_counts(part.column("seq")[0].values, flat.dictionary, number[(ends[rows] - ell)[:, None] + np.arange(ell)], klass, whole)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(g) + 1, dtype=np.int32) * g.shape[1]), pa.array(g.ravel()))
            out.append(pa.table({"batch_id": pa.array(np.full(len(rows), part.column("batch_id")[0].as_py(), np.int64)), "seg": pa.array(np.full(len(rows), part.column("seg")[0].as_py(), np.int32)), "nodes": nodes.take(pa.array(rows)), "g": lists}))
        return pa.concat_tables(out)

    # both sides may come from one table, so theirs are columns of other names
    by, beside = ("batch_id", "seg", "block"), ("of_batch", "of_seg", "of_block")
    dealt = dealt.select(*[F.col(a).alias(b) for a, b in zip(by, beside)], "nodes")
    met = slices.groupBy(*by).cogroup(dealt.groupBy(*beside)).applyInArrow(run, "batch_id long, seg int, nodes array<string>, g array<long>")
    folded = met.groupBy("batch_id", "nodes").agg(F.array_sort(F.collect_list(F.struct("seg", "g"))).alias("parts"))
    return folded.select("batch_id", "nodes", _folded(F.col("parts"), F.size("nodes"), klass).alias("freq"))


def pair_windows(frame: DataFrame, m: int, k: int, block: int | None = None) -> DataFrame | None:
    """(window_end, key, wfreq, rank): the k best pairs of symbols of each window, ties included, of frame(batch_id, tick, symbol).

    Every pair is counted, 64 at a time (operators.pairs). None where pairs.tick_bits gives none.
    """
    grid = pairs.tick_bits(frame)
    if grid is None:
        return None
    spark = frame.sparkSession
    rows = pairs.each_block(spark, grid, block, pairs.window_rows, pairs.ROWS, m, k, pairs.pilot(grid, m, k))
    best = topk_with_ties(rows.select((F.col("end") + grid.lo).alias("window_end"), "a", "b", "wfreq"), k, "window_end", "wfreq")
    names = small(spark.createDataFrame(pa.table({"i": pa.array(range(len(grid.names)), pa.int64()), "name": pa.array(grid.names, pa.string())})))
    named = best.join(names.toDF("a", "s"), "a").join(names.toDF("b", "t"), "b")
    return named.select("window_end", F.concat("s", F.lit(MARK["serial"]), "t").alias("key"), "wfreq", "rank")


def choose(events_per_batch: int, candidates: int) -> str:
    """Route by the work of the expression plan, a step per event and candidate, against moves of the kernel."""
    return "kernel" if events_per_batch * candidates > 10**6 else "expression"


def count(seqs: DataFrame, cands: DataFrame, ell: int, klass: str = "serial", ties: bool = True) -> DataFrame:
    """(batch_id, key, nodes, freq) of every candidate (nodes) that occurs, by the route that choose() takes."""
    events = seqs.groupBy("batch_id").agg(F.sum(F.size("seq")).alias("n")).agg(F.max("n")).first()[0] or 0
    if klass == "itemset" or choose(events, cands.count()) == "kernel":
        every = small(seqs.select("batch_id").distinct()).crossJoin(cands.select("nodes"))
        return _named(count_grid(seqs, every, klass).where("freq > 0"), MARK[klass])
    return count_serial(seqs, cands, ell, ties) if klass == "serial" else count_parallel(seqs, cands, ties)


def occurrences(seqs: DataFrame, spec: EpisodeSpec) -> DataFrame:
    """(batch_id, occ_no, node, tick) of the greedy non-overlapped occurrences of a serial episode.

    seqs: (batch_id, ticks array<struct<tick, symbols>>) in order.
    """
    nodes = F.array(*[F.lit(x) for x in spec.nodes])
    ell = len(spec.nodes)
    start = F.struct(F.lit(0).alias("n"), F.array().cast("array<bigint>").alias("at"))

    def step(s, y):
        hit = F.array_contains(y["symbols"], F.element_at(nodes, s["n"] % ell + 1))
        return F.when(hit, F.struct((s["n"] + 1).alias("n"), F.concat(s["at"], F.array(y["tick"])).alias("at"))).otherwise(s)

    run = seqs.select("batch_id", F.aggregate("ticks", start, step, lambda s: F.slice(s["at"], F.lit(1), s["n"] - s["n"] % ell)).alias("at"))
    out = run.select("batch_id", F.posexplode("at").alias("i", "tick"))
    return out.select("batch_id", F.floor(F.col("i") / ell).cast("long").alias("occ_no"), (F.col("i") % ell).cast("long").alias("node"), "tick")


def itemset_counts(baskets: DataFrame, size: int) -> DataFrame:
    """(batch_id, key, freq): baskets (batch_id, items sorted array) that hold each itemset of a size."""
    grown = baskets.select("batch_id", "items", F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.size("items"), F.lit(1))), lambda i: i)).alias("i")).where(F.size("items") >= size)
    grown = grown.select("batch_id", "items", "i", F.array(F.element_at("items", F.col("i"))).alias("nodes"))
    for _ in range(size - 1):
        rest = F.when(F.col("i") < F.size("items"), F.sequence(F.col("i") + 1, F.size("items"))).otherwise(F.array().cast("array<int>"))
        grown = grown.select("batch_id", "items", "nodes", F.explode(rest).alias("i")).select("batch_id", "items", "i", F.concat("nodes", F.array(F.element_at("items", F.col("i")))).alias("nodes"))
    return grown.groupBy("batch_id", F.array_join("nodes", "+").alias("key")).agg(F.count(F.lit(1)).alias("freq"))
