"""Worked examples, invariants and searches of the shard kernels."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from neargraph.operators import baselines as base
from neargraph.operators import local
from neargraph.params import SearchParams, aligned_degree, choose_merge, choose_mode, initial_degree, seed_point, table_size

SIX = np.array([[1, 2, 3, 4, 5], [3, 0, 2, 4, 5], [4, 3, 0, 1, 5], [1, 4, 0, 2, 5], [2, 3, 0, 1, 5], [4, 3, 2, 1, 0]])


def components(adj):
    return len(np.unique(local.strong_components(adj)))


def test_six_nodes_by_hand():
    counts = local.detour_counts(SIX)
    assert counts.tolist() == [[0, 0, 2, 2, 0], [0, 0, 1, 2, 0], [0, 0, 0, 2, 0], [0, 0, 1, 3, 0], [0, 0, 0, 2, 0], [0, 0, 1, 1, 4]]
    cut = local.prune(SIX, counts, 3)
    assert cut.tolist() == [[1, 2, 5], [3, 0, 5], [4, 3, 0], [1, 4, 5], [2, 3, 0], [4, 3, 2]]
    back = local.reversed_lists(cut, 3)
    assert back.tolist() == [[1, 2, 4], [0, 3, -1], [4, 0, 5], [1, 2, 4], [2, 5, 3], [0, 1, 3]]
    mixed = local.interleave(cut, back, 3)
    assert mixed.tolist() == [[1, 4, 2], [3, 0, 5], [4, 0, 3], [1, 2, 4], [2, 5, 3], [4, 0, 3]]
    assert [components(g) for g in (SIX[:, :3], cut, mixed)] == [2, 1, 1]
    assert local.two_hop_counts(SIX[:, :3]).tolist() == [4, 4, 4, 4, 4, 5]
    assert local.two_hop_counts(mixed).tolist() == [5] * 6
    two = local.uniform_graph(SIX, 2)
    assert two.tolist() == [[1, 2], [3, 0], [4, 0], [1, 2], [2, 5], [4, 3]]
    assert (components(SIX[:, :2]), components(two)) == (2, 1)
    assert local.uniform_graph(SIX, 4).tolist() == [[1, 4, 2, 3], [3, 5, 0, 2], [4, 0, 3, 5], [1, 2, 4, 5], [2, 5, 3, 0], [4, 0, 3, 1]]


def test_points_on_a_line():
    x = np.array([[0], [1], [2.1], [3.3], [4.6], [6]])
    ids, dist = local.exact_graph(x, 4)
    assert ids.tolist() == [[1, 2, 3, 4], [0, 2, 3, 4], [1, 3, 0, 4], [2, 4, 1, 5], [3, 5, 2, 1], [4, 3, 2, 1]]
    assert local.detour_counts(ids).tolist() == [[0, 0, 1, 1]] * 4 + [[0, 0, 1, 2], [0, 1, 1, 2]]
    by_table = local.detour_counts(ids, "distance", dist=dist)
    assert by_table.tolist() == [[0, 1, 2, 3], [0, 0, 1, 2], [0, 0, 1, 1], [0, 0, 1, 1], [0, 0, 1, 2], [0, 1, 2, 3]]
    assert (by_table == local.detour_counts(ids, "distance", x=x)).all()


def test_rules():
    assert initial_degree(16) == 48 and initial_degree(16, 2) == 32
    assert [aligned_degree(v) for v in (15.9, 16, 47.3)] == [0, 16, 32]
    assert [choose_mode(b, m, b_t=8) for b, m in ((7, 64), (8, 64), (8, 512), (8, 513))] == ["team", "solo", "solo", "team"]
    assert [choose_merge(c) for c in (512, 513)] == ["merge", "partition"]
    assert all((s := table_size(i, p, d)) >= 2 * i * p * d and s & (s - 1) == 0 for i, p, d in ((1, 1, 3), (20, 2, 16)))
    assert local.seed_nodes(np.array([5]), 3, 1, 100).tolist() == [[seed_point(5, j, 1, 100) for j in range(3)]]
    with pytest.raises(ValueError):
        SearchParams(k=10, M=5)
    with pytest.raises(ValueError):
        local.exact_graph(np.zeros((4, 2)), 4)


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 1000), st.integers(2, 7))
def test_graph_invariants(seed, d):
    x = np.random.default_rng(seed).normal(size=(40, 5))
    ids, dist = local.exact_graph(x, 3 * d)
    for reorder in ("rank", "distance_table", "none"):
        cut = local.uniform_graph(ids, d, reorder=reorder, reverse=False, dist=dist)
        g = local.uniform_graph(ids, d, reorder=reorder, dist=dist)
        assert g.shape == (40, d)
        back = local.reversed_lists(cut, d)
        for i in range(40):
            assert len(set(g[i])) == d and i not in g[i]
            assert set(cut[i]) <= set(ids[i]) and set(g[i]) <= set(cut[i]) | set(back[i])
        assert local.two_hop_counts(g).max() <= d + d * d
        assert len(np.unique(local.strong_components(g))) >= len(np.unique(local.weak_components(g))) >= 1


def test_strong_components_against_reachability():
    rng = np.random.default_rng(2)
    for _ in range(20):
        n = 25
        adj = rng.integers(0, n, (n, 1))
        reach = np.eye(n, dtype=bool)
        reach[np.arange(n), adj[:, 0]] = True
        for k in range(n):
            reach |= reach[:, k : k + 1] & reach[k]
        both = reach & reach.T
        assert (local.strong_components(adj) == both.argmax(axis=1)).all()


@pytest.fixture(scope="module")
def data():
    x = local.prepared(np.random.default_rng(7).normal(size=(600, 16)), "l2")
    ids, dist = local.exact_graph(x, 36)
    return x, ids, dist, local.uniform_graph(ids, 12)


def test_searches_agree(data):
    x, ids, dist, g = data
    q = np.arange(0, 600, 7)
    truth = local.exact_knn(x, x[q], 10)[0]
    plain = local.search_solo(x, g, x[q], SearchParams(), q)
    assert local.recall(plain.ids, truth) > 0.95
    assert (np.diff(plain.dist, axis=1) >= 0).all()
    for kw in ({"visited": "forget"}, {"visited": "forget", "every": 3, "bits": 8}, {"visited": "none"}, {"merge": "merge"}, {"merge": "partition"}):
        other = local.search_solo(x, g, x[q], SearchParams(**kw), q)
        assert (other.ids == plain.ids).all(), kw
        assert other.n_dist.sum() >= plain.n_dist.sum()
    for i in (0, 17, 40):  # a single query takes another path to the same walk
        few = local.search_solo(x, g, x[q[i : i + 1]], SearchParams(), q[i : i + 1])
        assert (few.ids[0] == plain.ids[i]).all() and few.n_dist[0] == plain.n_dist[i] and few.rounds[0] == plain.rounds[i]
    one = local.search_team(x, g, x[q], SearchParams(walkers=1), q)
    assert (one.ids == plain.ids).all()
    whole = local.search_solo(x, g, x[q], SearchParams(M=600, p=8, max_iter=200), q)
    assert (whole.ids == truth).all()
    half = local.prepared(x, "l2", "fp16")
    assert abs(local.recall(local.search_solo(half, g, half[q], SearchParams(), q).ids, truth) - local.recall(plain.ids, truth)) <= 0.02
    short = SearchParams(max_iter=6)
    assert local.recall(local.search_team(x, g, x[q], short, q).ids, truth) >= local.recall(local.search_solo(x, g, x[q], short, q).ids, truth)


def test_descent_and_rank_quality(data):
    x, ids, dist, g = data
    found, _, computed = local.descent_graph(x, 36)
    assert local.recall(found, ids) > 0.95 and computed > 0
    q = np.arange(0, 600, 7)
    truth = local.exact_knn(x, x[q], 10)[0]
    by_distance = local.uniform_graph(ids, 12, reorder="distance_table", dist=dist)
    a, b = (local.recall(local.search_solo(x, v, x[q], SearchParams(M=32), q).ids, truth) for v in (g, by_distance))
    assert abs(a - b) <= 0.03


def test_visited_set():
    s = local.VisitedSet(2, 3)
    rows = np.array([0, 1])
    assert s.insert(rows, np.array([5, 5])).all()
    assert not s.insert(rows, np.array([5, 5])).any()
    for v in range(20):
        s.insert(np.array([0]), np.array([v]))
    assert s.overflows[0] > 0 and s.collisions[0] > 0 and s.overflows[1] == 0
    s.reset(np.array([0]), np.array([[7, -1]]))
    assert not s.insert(np.array([0]), np.array([7])).any() and s.insert(np.array([0]), np.array([6])).all()


def test_baselines_find_neighbours(data):
    x, ids, dist, _ = data
    q = np.arange(0, 600, 11)
    truth = local.exact_knn(x, x[q], 10)[0]
    graphs = {
        "flat": base.flat_sw(x, 6, 24),
        "spread": base.monotonic_spread(ids, dist, x, 12)[0],
        "angle": base.angle_spread(ids[:, :18], x, 12),
        "block": base.block_merge(x, 64, 12),
        "batch": base.batch_insert(x, 8, 8, 32),
    }
    for name, g in graphs.items():
        assert local.recall(local.search_solo(x, g, x[q], SearchParams(M=48), q).ids, truth) > 0.85, name
        assert base.reachable_pieces(g) == 1, name
    layered = base.layered_sw(x, 8, 32)
    assert local.recall(base.layered_search(x, layered, x[q], 10, 48), truth) > 0.85
    index = base.IvfPq.build(x, 8, 4)
    assert local.recall(index.search(x[q], 10, 8, x=x), truth) > local.recall(base.hash_search(x, x[q], 10, tables=1, bits=12), truth)
    assert local.recall(base.hash_search(x, x[q], 10, tables=30, bits=3), truth) > 0.85
    assert local.recall(base.tree_search(x, x[q], 10, trees=30), truth) > 0.85
    counts = local.detour_counts(ids)
    assert ((base.detour_prune(ids, counts) >= 0) == (counts == 0)).all()


def test_cosine_of_zero_vector_and_ties():
    x = local.prepared(np.array([[0, 0], [1, 0], [1, 0], [0, 2]], float), "cosine")
    assert np.allclose(local.block_distances(x[:1], x, "cosine"), 1.0)
    ids, _ = local.exact_knn(x, x[1:2], 4, "cosine")
    assert ids.tolist() == [[1, 2, 0, 3]]
