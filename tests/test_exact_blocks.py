"""Exact search by blocks against the column expressions, pair by pair."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from neargraph.functions.distance import METRICS, distance
from neargraph.operators import exact
from neargraph.operators import relational as rel
from neargraph.runtime import Scratch


@pytest.fixture(scope="module")
def odd(spark):
    """Copies, zero, null and non-finite vectors, and points whose distances tie."""
    rng = np.random.default_rng(5)
    x = rng.integers(-2, 3, (300, 4)).astype(np.float32) * np.float32(0.1)
    x[::7] = x[0]
    x[5] = 0
    x[11, 2], x[13, 1] = np.nan, np.inf
    rows = [(3 * i, None if i in (17, 40) else v.tolist()) for i, v in enumerate(x)]
    return spark.createDataFrame(rows, "id long, vec array<float>").cache()


def _plain(vecs, asked, k, metric, exclude_self):
    pairs = vecs.crossJoin(asked.select("qid", F.col("vec").alias("qvec")))
    pairs = pairs.where("id <> qid") if exclude_self else pairs
    return rel.per_query(pairs.select("qid", F.col("id").alias("nid"), distance(metric, "vec", "qvec").alias("dist")), k)


def _rows(hits):
    return sorted((r.qid, r.rnk, r.nid, "nan" if r.dist is not None and np.isnan(r.dist) else repr(r.dist)) for r in hits.collect())


@pytest.mark.parametrize("metric", METRICS)
def test_blocks_answer_as_the_expressions_do(spark, odd, metric, monkeypatch):
    monkeypatch.setattr(exact, "QUERY_BLOCK", 7)
    monkeypatch.setattr(exact, "VECTOR_BLOCK", 32)
    asked = odd.select(F.col("id").alias("qid"), "vec").where("qid % 2 = 0")
    for k, exclude_self in ((5, False), (40, True), (400, True)):
        assert _rows(rel.exact_knn(odd, asked, k, metric=metric, exclude_self=exclude_self)) == _rows(_plain(odd, asked, k, metric, exclude_self))
    monkeypatch.setattr(exact, "HELD", 60)  # blocks of queries leave before all vectors have come
    monkeypatch.setattr(rel, "BROADCAST_BYTES", 7000)  # queries go out instead of vectors
    assert _rows(rel.exact_knn(odd, asked.where("qid < 90"), 5, metric=metric)) == _rows(_plain(odd, asked.where("qid < 90"), 5, metric, False))


def test_no_plan_pairs_single_vectors(spark, odd, capsys):
    """At 10,256 vectors the base graph took 105 million rows through a join."""
    rel.knn_edges(odd, 6).explain()
    plan = capsys.readouterr().out
    assert "zip_with" not in plan and "MapInArrow" in plan[plan.index("WindowGroupLimit") :]


def test_descent_sends_small_sets_and_joins_large_ones(spark, monkeypatch):
    """The edges are the same; only large sets go through the joins of pairs and vectors."""
    x = np.random.default_rng(8).normal(size=(150, 8)).astype(np.float32)
    vecs = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<float>").cache()
    calls = []
    monkeypatch.setattr(rel, "distance", lambda *a, f=distance: calls.append(a) or f(*a))
    sent = {tuple(r) for r in rel.descent_edges(vecs, 8, Scratch(spark, "test")).collect()}
    assert not calls
    monkeypatch.setattr(rel, "SENT_BYTES", 0)
    assert sent == {tuple(r) for r in rel.descent_edges(vecs, 8, Scratch(spark, "test")).collect()} and calls


def test_vectors_of_unequal_lengths_are_refused(spark):
    rows = spark.createDataFrame([(0, [1.0, 2.0]), (1, [1.0])], "id long, vec array<float>")
    with pytest.raises(Exception, match="differ in length"):
        rel.knn_edges(rows, 1).collect()
    assert rel.exact_knn(rows.where("false"), rows.select(F.col("id").alias("qid"), "vec"), 3).count() == 0


def _nearest(x, y, k, metric, exclude_self):
    """The answer of the kernel in blocks of 50 rows, and what all pairs give."""

    def side(v, at):
        return exact.Side(np.arange(at, at + len(v)).tobytes(), v.astype("<f8").tobytes(), bytes(len(v)), 8, metric)

    near = exact.Nearest(side(y, 0), k, metric, exclude_self)
    for at in range(0, len(x), 50):
        near.add(side(x[at : at + 50], at))
    q, v = side(y, 0), side(x, 0)
    row, col = (a.ravel() for a in np.indices((len(y), len(x))))
    row, col = (row[row != col], col[row != col]) if exclude_self else (row, col)
    with np.errstate(all="ignore"):
        dist = exact.measured(q, v, row, col, metric)
    order = np.lexsort((col, dist, row))
    row, col, dist = row[order], col[order], dist[order]
    first = np.arange(len(row)) - np.searchsorted(row, row) < k
    return near, (near.row.tolist(), near.id.tolist(), near.dist.tolist()), (row[first].tolist(), col[first].tolist(), dist[first].tolist())


@pytest.mark.parametrize("metric", METRICS)
@pytest.mark.parametrize("scale", [1e-170, 1e-42, 1e-25, 1e-12, 1.0, 3e14, 1e17, 1e140])
def test_bounds_hold_at_any_scale(metric, scale):
    rng = np.random.default_rng(3)
    for spread in (np.ones(400), 10.0 ** rng.integers(-6, 7, 400)):
        x = rng.normal(size=(400, 12)) * spread[:, None] * scale
        x[40:60] = x[20:40] * (1 + 1e-9)
        x[60:80] = x[20:40]
        x[7], x[9] = 0, x[8]
        for exclude_self in (False, True):
            _, got, asked = _nearest(x, x[:90], 6, metric, exclude_self)
            assert got == asked


@pytest.mark.parametrize("metric", ["l2", "sql2", "ip"])
def test_single_precision_bounds_plain_vectors_and_double_what_it_cannot_tell(metric, monkeypatch):
    """CPU seconds of q_knn_graph grew as the input to the power 1.43 with bounds in double precision alone."""
    x = np.random.default_rng(4).normal(size=(600, 16))
    double, calls = exact._bounds, []
    monkeypatch.setattr(exact, "_bounds", lambda *a: calls.append(a) or double(*a))
    _, got, asked = _nearest(x, x[:64], 3, metric, True)
    assert got == asked and not calls
    near, got, asked = _nearest(x * 1e-4 + 1e3, x[:64] * 1e-4 + 1e3, 1, metric, True)
    assert got == asked and bool(calls) == (not near.coarse)
    assert metric == "ip" or calls


@pytest.mark.parametrize("metric", METRICS)
def test_bounds_are_looked_through_in_tiles(metric, monkeypatch):
    """A block's matrix of 16 MB in q_detour_prune_baseline left the cache of its core before it was looked through."""
    monkeypatch.setattr(exact, "TILE", 350)
    sizes = []
    for name in ("_coarse", "_bounds"):
        monkeypatch.setattr(exact, name, lambda *a, bounds=getattr(exact, name): sizes.append(bounds(*a)[0].size) or bounds(*a))
    x = np.random.default_rng(7).integers(-3, 4, (330, 4)).astype(float)  # many ties
    for exclude_self in (False, True):
        _, got, asked = _nearest(x, x[:90], 6, metric, exclude_self)
        assert got == asked
    assert sizes and max(sizes) <= 350
