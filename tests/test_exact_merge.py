"""Full lists take a block's few pairs as matrices, without a sort over all pairs."""

import numpy as np

from neargraph.operators import exact


def _side(x, at):
    return exact.Side(np.arange(at, at + len(x)).tobytes(), x.astype("<f8").tobytes(), bytes(len(x)), 8, "l2")


def test_true_places_are_those_of_flatnonzero():
    rng = np.random.default_rng(2)
    for shape in ((7, 5), (16, 8), (3, 1), (40, 33)):
        for share in (0.0, 0.02, 1.0):
            found = rng.random(shape) < share
            assert (exact._true_places(found) == np.flatnonzero(found)).all()


def test_full_lists_are_merged_without_a_sort_of_all_pairs(monkeypatch):
    """Each block of q_indegree sorted all pairs known so far by three keys; ties, copies and infinite distances keep their order."""
    rng = np.random.default_rng(6)
    x = rng.integers(-2, 3, (900, 5)).astype(float)  # many ties
    x[100:130] = x[:30]
    x[700, 2], x[701, 1] = np.inf, np.nan
    near, kept = exact.Nearest(_side(x[:60], 0), 9, "l2", True), []
    merged = exact.Nearest._merged
    monkeypatch.setattr(exact.Nearest, "_merged", lambda *a: kept.append(merged(*a)) or kept[-1])
    for at in range(0, 900, 90):
        near.add(_side(x[at : at + 90], at))
    row, col = (a.ravel() for a in np.indices((60, 900)))
    row, col = row[row != col], col[row != col]
    with np.errstate(all="ignore"):
        dist = exact.measured(_side(x[:60], 0), _side(x, 0), row, col, "l2")
    order = np.lexsort((col, dist, row))
    first = order[np.arange(len(order)) - np.searchsorted(row[order], row[order]) < 9]
    assert (near.row.tolist(), near.id.tolist(), near.dist.tolist()) == (row[first].tolist(), col[first].tolist(), dist[first].tolist())
    assert sum(kept) >= 5
