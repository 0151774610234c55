"""All queries of the library (the llm subpackage has its own), with their DuckDB counterparts."""

from __future__ import annotations

from driftlattice.queries import episodes, planted, relational, windows, workloads

QUERIES = {**episodes.QUERIES, **windows.QUERIES, **workloads.QUERIES, **planted.QUERIES, **relational.QUERIES}
ORACLES = {**episodes.ORACLES, **windows.ORACLES, **workloads.ORACLES, **planted.ORACLES, **relational.ORACLES}
