"""Document vectors by a kernel against the plan of 3-gram counts, and the vote over them."""

from collections import Counter

import numpy as np
import pytest

import __spark_entry__ as entry
from neargraph.operators import local
from neargraph.plans import workloads
from neargraph.sources import vectors as src


def test_vectors_hold_the_counted_grams(spark):
    texts = ["", None, "ab", "abc", "ABC abc ÀÉÎ \u0130 \u03a3\u03a3 \u4e2d\u6587\u5b57", "x\0y\0z", "\U0001f600\U0001f601\U0001f602 aaa", "word " * 500]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = {i: np.zeros(64) for i in range(len(texts))}
    for r in src.gram_counts(rows, "doc_id", rows.text, 64).collect():
        want[r.id][r.bucket] = r.n
    for r in src.gram_vectors(rows, "doc_id", "text", 64).collect():
        size = np.sqrt((want[r.id] ** 2).sum())
        assert (np.float32(r.vec) == (want[r.id] / size if size else want[r.id]).astype(np.float32)).all()


def test_vectors_are_made_once_for_a_vote(spark, sf, monkeypatch):
    """Each chunk of queries made all vectors again, from one row for each character."""
    plans = []
    monkeypatch.setattr(workloads.rel, "exact_knn", lambda vecs, *a, f=workloads.rel.exact_knn, **b: plans.append(vecs._jdf.queryExecution().toString()) or f(vecs, *a, **b))
    got = {r.doc_id: (r.predicted, r.actual) for r in entry.queries()["q_label_vote"](spark, sf).collect()}
    assert "MapInArrow" not in plans[0] and "Generate" not in plans[0]
    labels = {r.doc_id: r.quality for r in src.table(spark, sf, "labels").collect()}
    rows = src.gram_vectors(src.table(spark, sf, "documents"), "doc_id", "text", 256).where("id in (%s)" % ",".join(map(str, labels))).orderBy("id").collect()
    ids, x = [r.id for r in rows], local.prepared(np.float32([r.vec for r in rows]), "cosine")
    near = local.exact_graph(x, 5, "cosine")[0]
    same = 0
    for i, row in zip(ids, near, strict=True):
        n = Counter(labels[ids[j]] for j in row)
        same += got[i] == (min(n, key=lambda q: (-n[q], q)), labels[i])
    assert len(got) == len(ids) and same == pytest.approx(len(ids), abs=1)  # a tie of rounded products may fall otherwise
