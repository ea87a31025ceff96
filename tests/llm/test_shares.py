"""What decides by shares and thresholds, on plain numbers."""

import math

import numpy as np
import pyarrow as pa
import pytest


@pytest.mark.parametrize("share", [0.1, 0.4, 0.75])
def test_long_tail_of_lengths_gives_a_like_share(share):
    from devicelens.llm.mixing import fill

    lengths = {n: 1 for n in range(1, 3_001)} | {n: 7 for n in range(3, 40, 5)}
    total = sum(n * c for n, c in lengths.items())
    budget = int(share * total)
    got = fill(budget, lengths)
    assert sum(n * c for n, c in got.items()) == budget
    for low in range(1, 3_001, 300):
        here = range(low, low + 300)
        assert abs(sum(got.get(n, 0) for n in here) - share * sum(lengths[n] for n in here)) <= 12
    assert all(0 < c <= lengths[n] for n, c in got.items())


@pytest.mark.parametrize("threshold", [0.9, 0.98])
def test_dealing_has_the_tables_of_its_threshold(threshold):
    from devicelens.llm.neighbour_graph import MISSED, deal

    vectors = np.random.default_rng(1).standard_normal((3, 8)).astype(np.float32)
    names = ["class", "label", "rows", "vector", "classes"]
    rows = [pa.array([b"a", b"b", b"c"]), pa.array(["1"] * 3), pa.array([1] * 3), pa.array(vectors.tolist(), pa.list_(pa.float32())), pa.array([90_000] * 3)]
    tables = len(list(deal(iter([pa.RecordBatch.from_arrays(rows, names)]), threshold)))
    apart = 1 - (1 - math.acos(threshold) / math.pi) ** 4
    assert apart**tables <= MISSED < apart ** (tables - 1)
