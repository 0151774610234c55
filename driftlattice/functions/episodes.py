"""Counting non-overlapped episode occurrences as column expressions.

Sequences are arrays with one element per tick, either a symbol or an array of symbols. Greedy
earliest matching is best for all kinds here. Ticks are atomic: a node moves at most once a tick,
order needs strictly increasing ticks, and an occurrence that completes starts anew with the next.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _meets(tick: Column, label: Column, ties: bool) -> Column:
    return F.array_contains(tick, label) if ties else tick == label


def serial_moves(seq: Column, nodes: Column, ell: int, ties: bool = False, start: Column | int = 0) -> Column:
    """Moves made over `seq` by the automaton that has made `start` moves; it waits for node moves mod ell."""
    begin = F.lit(start) if isinstance(start, int) else start
    return F.aggregate(seq, begin, lambda n, y: n + F.when(_meets(y, F.element_at(nodes, n % ell + 1), ties), 1).otherwise(0))


def serial_frequency(seq: Column, nodes: Column, ell: int, ties: bool = False) -> Column:
    return F.floor(serial_moves(seq, nodes, ell, ties) / ell).cast("long")


def slice_moves(seq: Column, nodes: Column, ell: int, ties: bool = False) -> Column:
    """Summary of a slice: moves made when it is entered at residue 0, 1, ... ell - 1."""
    return F.transform(F.sequence(F.lit(0), F.lit(ell - 1)), lambda r: serial_moves(seq, nodes, ell, ties, r) - r)


def fold_slices(summaries: Column, ell: int, start: Column | int = 0) -> Column:
    """Moves over slices in order: summaries compose as n + g[n mod ell], so slices are counted apart."""
    begin = F.lit(start) if isinstance(start, int) else start
    return F.aggregate(summaries, begin, lambda n, g: n + F.element_at(g, n % ell + 1))


def partial_frequency(seq: Column, nodes: Column, preds: Column, ties: bool = False) -> Column:
    """Frequency of a partial order: a node joins when its label occurs and its predecessors joined at earlier ticks.

    preds: array<array<int>>, 0-based. Equal labels (of a multiset without order) fill one node a tick.
    """
    none = F.transform(nodes, lambda x: F.lit(False))
    state = F.struct(F.lit(0).cast("long").alias("n"), none.alias("f"))

    def step(s, y):
        def joins(x, i):
            free = F.forall(F.element_at(preds, i + 1), lambda p: F.element_at(s["f"], p + 1))
            turn = (i == 0) | (F.element_at(nodes, F.greatest(i, F.lit(1))) != x) | F.element_at(s["f"], F.greatest(i, F.lit(1)))
            return F.element_at(s["f"], i + 1) | (_meets(y, x, ties) & free & turn)

        joined = F.transform(nodes, joins)
        # struct fields are evaluated per use, so the joined flags are bound once by a one-element transform
        return F.element_at(
            F.transform(F.array(joined), lambda f: F.when(F.forall(f, lambda b: b), F.struct((s["n"] + 1).alias("n"), none.alias("f"))).otherwise(F.struct(s["n"].alias("n"), f.alias("f")))), 1
        )

    return F.aggregate(seq, state, step, lambda s: s["n"])


def parallel_frequency(seq: Column, nodes: Column, ties: bool = False) -> Column:
    """Frequency of a multiset of labels (sorted) in any order."""
    return partial_frequency(seq, nodes, F.transform(nodes, lambda x: F.array().cast("array<int>")), ties)


def serial_key(symbols: Column) -> Column:
    return F.array_join(symbols, ">")


def parallel_key(symbols: Column) -> Column:
    return F.array_join(symbols, "+")
