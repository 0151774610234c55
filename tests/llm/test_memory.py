"""What Python workers hold: arrays of the shingle counts, and memory that is free after a task."""

import os
import re

import numpy as np
import pytest

from driftlattice.llm import jaccard, shared


def test_frequent_values_equal_a_count_of_all():
    rng = np.random.default_rng(0)
    for n in (0, 1, 5, 6, 7, 50, 1000, 5000):
        v = rng.integers(0, max(1, n // 4), n).astype(np.uint64)
        value, count = np.unique(v, return_counts=True)
        kept = [v[: n // 2], v[n // 2 :]]
        found, often = jaccard.frequent(kept)
        assert found.tolist() == value[count >= 6].tolist() and often.tolist() == count[count >= 6].tolist()
        assert kept == []


def resident():
    return int(re.search(r"RssAnon:\s+(\d+)", open("/proc/self/status").read())[1]) / 1024


def test_a_finished_task_gives_its_memory_back():
    """Many blocks below malloc's threshold, a few of them still used: what lies between goes back to the system."""
    if "glibc" not in str(os.confstr("CS_GNU_LIBC_VERSION")):
        pytest.skip("another C library")
    few = []

    def run(batches):
        for _ in batches:
            blocks = [np.ones(8000) for _ in range(3000)]  # 64 kB each, 190 MB
            few.extend(blocks[::500] + [np.ones(8000)])
            yield len(blocks)

    before = resident()
    assert list(shared.lean(run)([1])) == [3000]
    assert resident() - before < 60
