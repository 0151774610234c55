"""Grouped aggregates for SQL and DataFrames."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import LongType


def greedy_count(ticks, symbols, key: str) -> int:
    """Non-overlapped occurrences of a serial episode ('A>B>C') among events; a tick moves the automaton once."""
    nodes, n, last = key.split(">"), 0, None
    here: set = set()
    for tick, symbol in [*sorted((t, x) for t, x in zip(ticks, symbols) if t is not None and t == t and x is not None), (None, None)]:
        if tick != last:
            n += last is not None and nodes[n % len(nodes)] in here
            last, here = tick, set()
        here.add(symbol)
    return n // len(nodes)


@pandas_udf(LongType())
def nonoverlap_count(ticks: pd.Series, symbols: pd.Series, key: pd.Series) -> int:
    """Frequency of one serial episode in a group of events: nonoverlap_count(tick, symbol, 'A>B'), events in any order.

    A group's events are held by one task, as for every grouped pandas aggregate; batches beyond
    that are counted in slices (operators.counting.count_grid). Null ticks and symbols are left out.
    """
    return greedy_count(ticks, symbols, key.iloc[0]) if len(key) else 0
