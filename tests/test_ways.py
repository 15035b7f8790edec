"""Detours from arrays against detours by joins."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from neargraph.operators import relational as rel
from neargraph.operators import ways


@pytest.fixture(scope="module")
def edges(spark):
    """Lists of unequal lengths, ids far apart, nodes without a list, equal distances."""
    rng = np.random.default_rng(3)
    rows = []
    for src in range(60):
        near = rng.choice(75, int(rng.integers(0, 14)), replace=False)
        for rank, (dst, dist) in enumerate(zip(near, np.sort(rng.integers(1, 8, len(near))), strict=True)):
            rows.append((1000 * src - 9, rank, 1000 * int(dst) - 9, float(dist) if dist < 7 else float("inf")))
    return spark.createDataFrame(rows, "src long, rank int, dst long, dist double").cache()


def _both(frame, weight, monkeypatch, capsys):
    out = []
    for most in (1 << 22, 0):
        monkeypatch.setattr(ways, "SENT_EDGES", most)
        found = rel.detours(frame, weight)
        found.explain()
        out.append((sorted(tuple(r) for r in found.collect()), found.dtypes, "Join" in capsys.readouterr().out))
    return out


@pytest.mark.parametrize("weight", ["rank", "distance"])
def test_arrays_count_as_joins_do_and_need_none(spark, edges, weight, monkeypatch, capsys):
    """q_detour_rank took every pair of a list's entries, 14 million at 51,282 nodes, through a join."""
    monkeypatch.setattr(ways, "LOOKED_UP", 50)
    held, joined = _both(edges, weight, monkeypatch, capsys)
    assert held[:2] == joined[:2] and not held[2] and joined[2] and any(r[3] for r in held[0])


def test_edges_that_stand_twice_or_have_no_length_are_joined(spark, edges, monkeypatch, capsys):
    twice = edges.union(edges.limit(3))
    gaps = edges.withColumn("dist", F.when(F.col("rank") == 4, F.lit(None)).when(F.col("rank") == 5, F.lit(float("nan"))).otherwise(F.col("dist")))
    for frame in (twice, gaps):
        held, joined = _both(frame, "distance", monkeypatch, capsys)
        assert repr(held[:2]) == repr(joined[:2]) and held[2]
    assert rel.detours(edges.where("false")).count() == 0


@pytest.mark.parametrize("weight", ["rank", "distance"])
def test_lists_are_cut_where_they_are_counted(spark, edges, weight, monkeypatch, capsys):
    """q_distance_pruned and q_rank_pruned shuffled every edge once more to keep a third of them."""
    out = []
    for most in (1 << 22, 0):
        monkeypatch.setattr(ways, "SENT_EDGES", most)
        found = rel.reordered(edges, 5, weight)
        found.explain()
        out.append((sorted(tuple(r) for r in found.collect()), found.dtypes, "Exchange" in capsys.readouterr().out))
    asked = rel.pruned(rel.detours(edges, weight), 5)
    assert out[0][:2] == out[1][:2] == (sorted(tuple(r) for r in asked.collect()), asked.dtypes)
    assert not out[0][2] and out[1][2] and rel.reordered(edges.where("false"), 5, weight).count() == 0
