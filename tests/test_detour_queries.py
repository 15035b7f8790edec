"""Queries that read detours: none joins pairs of edges, and none counts them twice."""

import pytest

from neargraph.operators import relational as rel
from neargraph.plans import workload_queries


@pytest.mark.parametrize("name", ["q_detour_prune_baseline", "q_distance_pruned", "q_rank_pruned"])
def test_no_join_of_edges(spark, sf, name, capsys):
    workload_queries.queries()[name](spark, sf).explain()
    plan = capsys.readouterr().out
    assert "Join" not in plan and "MapInArrow" in plan


@pytest.mark.parametrize("name", ["q_forget_reset", "q_forget_reset_counts", "q_forget_every_third_counts"])
def test_a_walk_counts_detours_once(spark, sf, name, monkeypatch, capsys):
    """Both halves of the lists came from one plan that counted the detours each time."""
    plans, mix = [], rel.interleaved

    def seen(edges, d):
        edges.explain()
        plans.append(capsys.readouterr().out)
        return mix(edges, d)

    monkeypatch.setattr(rel, "interleaved", seen)
    workload_queries.queries()[name](spark, sf)
    assert len(plans) == 1 and "MapInArrow" not in plans[0] and "Scan parquet" in plans[0]


@pytest.mark.parametrize("name", ["q_distance_pruned", "q_rank_pruned", "q_forget_reset_counts", "q_forget_every_third_counts"])
def test_counted_edges_are_not_shuffled_to_be_cut(spark, sf, name, monkeypatch):
    calls, cut = [], rel.pruned
    monkeypatch.setattr(rel, "pruned", lambda *a: calls.append(a) or cut(*a))
    workload_queries.queries()[name](spark, sf)
    assert not calls
