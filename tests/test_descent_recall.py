"""Descent reaches the recall that it states, on vectors without near structure, and holds few pairs at once."""

import numpy as np
import pytest

from neargraph.operators import local


@pytest.fixture(scope="module")
def sphere():
    x = np.random.default_rng(2).normal(size=(2500, 64)).astype(np.float32)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_descent_lengthens_its_lists_until_they_hold_the_neighbours(sphere):
    x = local.prepared(sphere, "l2")
    truth = local.exact_graph(x, 10)[0]
    assert local.recall(local.descent_graph(x, 10)[0], truth) < 0.9
    ids, dist, _ = local.sure_descent(x, 10, least=0.95)
    assert local.recall(ids, truth) >= 0.95
    np.testing.assert_allclose(dist, np.linalg.norm(x[:, None] - x[ids], axis=2))
    assert local.sure_descent(x[:12], 5, least=1.0)[0].tolist() == local.exact_graph(x[:12], 5)[0].tolist()


@pytest.mark.parametrize("metric", ["l2", "ip", "cosine"])
def test_merging_in_parts_leaves_the_lists_as_they_are(sphere, metric, monkeypatch):
    """The first round held a list entry some forty times over before they were merged."""
    x = local.prepared(sphere[:600], metric)
    whole = local.descent_graph(x, 12, metric)
    merged, sizes = local._best_lists, []
    monkeypatch.setattr(local, "LEAST_PAIRS", 2000)
    monkeypatch.setattr(local, "HELD_PAIRS", 0)
    monkeypatch.setattr(local, "_best_lists", lambda owner, *a: sizes.append(len(owner)) or merged(owner, *a))
    parts = local.descent_graph(x, 12, metric)
    assert max(sizes) < 600 * 12 + 2000 + 2 * 64 * 12 * 24 * 2
    assert (parts[0] == whole[0]).all() and (parts[1] == whole[1]).all()


def test_lists_that_would_still_miss_too_much_are_left_out(sphere, monkeypatch):
    """At 51,282 vectors lists of 24, 48 and 96 were all made; those of 48 could not do."""
    x, made, make = local.prepared(sphere, "l2"), [], local.descent_graph
    monkeypatch.setattr(local, "descent_graph", lambda x, width, *a, **o: made.append(width) or make(x, width, *a, **o))
    ids = local.sure_descent(x, 6, least=0.95)[0]
    assert local.recall(ids, local.exact_graph(x, 6)[0]) >= 0.95 and made[:2] == [6, 24]


@pytest.mark.parametrize("metric", ["l2", "sql2", "ip", "cosine"])
def test_descent_measures_each_pair_as_the_metric_does(sphere, metric):
    x = local.prepared(sphere[:300] + np.float32(50), metric)
    ids, dist, computed = local.descent_graph(x, 20, metric)
    truth, far = local.exact_graph(x, 20, metric)
    np.testing.assert_allclose(dist, np.take_along_axis(local.block_distances(x, x, metric), ids, axis=1), atol=1e-5)
    assert local.recall(ids, truth) > 0.9 and (ids != np.arange(300)[:, None]).all() and all(len(set(row)) == 20 for row in ids.tolist())


def test_exact_lists_hold_no_matrix_of_all_vectors(monkeypatch):
    """A block of queries held its distances to all vectors, some 300 MB at 51,282 vectors; equal distances go by id."""
    x = np.random.default_rng(5).integers(0, 3, (5000, 4)).astype(float)
    monkeypatch.setattr(local, "block_distances", None)
    ids, dist = local.exact_knn(x, x[:50], 30, own=np.arange(50))
    whole = np.sqrt(((x[:50, None] - x[None]) ** 2).sum(axis=2))
    whole[np.arange(50), np.arange(50)] = np.inf
    assert (ids == np.argsort(whole, axis=1, kind="stable")[:, :30]).all()
    np.testing.assert_array_equal(dist, np.take_along_axis(whole, ids, axis=1))
