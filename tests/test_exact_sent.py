"""Exact search sends the vectors to tasks once; blocks of them do not go through a join with blocks of queries."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from neargraph.operators import exact
from neargraph.operators import relational as rel


@pytest.mark.parametrize("metric", ["l2", "ip", "cosine"])
def test_sent_vectors_are_in_no_join_and_give_the_same_rows(spark, metric, monkeypatch, capsys):
    monkeypatch.setattr(exact, "VECTOR_BLOCK", 64)
    rng = np.random.default_rng(9)
    x = rng.integers(-2, 3, (260, 4)).astype(np.float32)
    x[5], x[9, 1] = 0, np.nan
    vecs = spark.createDataFrame([(2 * i, None if i in (17, 40) else v.tolist()) for i, v in enumerate(x)], "id long, vec array<float>").cache()
    asked = vecs.select(F.col("id").alias("qid"), "vec").where("qid % 4 = 0")
    asked = asked.union(asked.where("qid < 40"))  # a query may come twice

    def answer():
        hits = rel.exact_knn(vecs, asked, 5, metric=metric, exclude_self=True)
        hits.explain()
        return sorted((r.qid, r.rnk, r.nid, repr(r.dist)) for r in hits.collect()), capsys.readouterr().out

    sent, plan = answer()
    assert "Join" not in plan
    monkeypatch.setattr(rel, "SENT_BYTES", 0)
    joined, plan = answer()
    assert "Join" in plan and sent == joined


def test_a_worker_makes_the_sent_blocks_ready_once(monkeypatch):
    """Each task of q_exact_knn made all vectors ready anew: at 102,564 vectors and 100 partitions, a hundred times."""
    rng = np.random.default_rng(5)

    def block(at, n):
        return np.arange(at, at + n).tobytes(), rng.normal(size=(n, 4)).tobytes(), bytes(n), 8

    class Frame:
        def __init__(self, rows=()):
            self.rows, self.sparkSession, self.sparkContext = rows, self, self

        def collect(self):
            return self.rows

        def broadcast(self, value):
            return type("Sent", (), {"value": value})

        def mapInArrow(self, run, schema):
            return run

    run = exact.nearest_sent(Frame(), Frame([block(0, 30), block(30, 30)]), 3, "l2")
    made, side = [], exact.Side
    monkeypatch.setattr(exact, "Side", lambda *a: made.append(a) or side(*a))
    tasks = [pa.RecordBatch.from_arrays([pa.array([c]) for c in block(at, 5)], names=["a", "b", "c", "d"]) for at in (100, 200, 300)]
    found = [[b.num_rows for b in run(iter([task]))] for task in tasks]
    assert found == [[15], [15], [15]] and len(made) == 2 + 3
