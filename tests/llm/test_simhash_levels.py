"""Crowded trie nodes: bounded memory in the kernel, and nodes that are cut again by further segments."""

import tracemalloc

import numpy as np
import pytest

from neargraph.llm import simhash_dedup
from neargraph.runtime import Scratch


def near(rng, count, flips, low=0):
    """Distinct fingerprints that differ from one in up to ``flips`` of the bits from ``low`` on."""
    v = np.full(3 * count, 0x123456789ABCDEF0, np.uint64)
    for _ in range(flips):
        v ^= np.uint64(1) << rng.integers(low, 64, len(v)).astype(np.uint64)
    return rng.permutation(np.unique(v))[:count]


@pytest.mark.parametrize("flips", [4, 9])
def test_a_crowded_group_needs_little_memory(flips):
    values = near(np.random.default_rng(2), 50_000, flips)
    tracemalloc.start()
    a, b = simhash_dedup.link_forest(np.zeros(len(values), np.int64), values, np.arange(len(values)), 4)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120e6
    if flips == 4:
        assert len(set(a.tolist())) == len(values) - 1 and len(set(b.tolist())) == 1  # one component


def test_crowded_nodes_are_cut_again(spark):
    rng = np.random.default_rng(3)
    values = np.unique(np.concatenate([near(rng, 500, 9), near(rng, 200, 3, low=40), rng.integers(0, 2**63, 100, dtype=np.uint64)]))
    label = np.arange(len(values))
    close = np.bitwise_count(values[:, None] ^ values[None, :]) <= 4
    while True:
        new = np.where(close, label[None, :], len(values)).min(axis=1)
        if (new == label).all():
            break
        label = new
    classes = spark.createDataFrame([(int(v), i) for i, v in enumerate(values.view(np.int64).tolist())], "fp long, rep long")
    for block_rows, levels in ((10_000, 3), (30, 1), (30, 3), (5, 4)):
        got = simhash_dedup.hamming_components(classes, Scratch(spark, "test"), block_rows=block_rows, levels=levels).collect()
        found = np.arange(len(values))
        for r in got:
            found[r.id] = r.component_id
        assert found.tolist() == label.tolist()
