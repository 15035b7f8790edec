"""Odd rows of the vector operators, the mix and the toxicity fit; small tables with links, ties and missing ids."""

from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from neargraph.llm import embedding_dedup, exact_topk, source_mix, toxicity


def test_vectors_of_unequal_lengths_do_not_link(spark):
    rows = [(0, 1, [1.0, 0.0]), (1, 1, [1.0, 0.0, 0.0]), (2, 1, [2.0, 0.0]), (3, 1, [0.99, 0.01, 0.0]), (4, 2, [1.0, 0.0]), (5, 1, None), (6, 1, [])]
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dedup.embedding_dedup(spark.createDataFrame(rows, "vec_id long, label int, embedding array<float>")).collect()}
    assert got == {0: (1, 0), 1: (1, 1), 2: (1, 0), 3: (1, 1), 4: (0, 4), 5: (0, 5), 6: (0, 6)}


def test_links_of_a_table_that_has_many(spark):
    """Groups of near vectors, some across labels, against brute force; the given tables hold none."""
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(25, 24))
    x = np.concatenate([c + rng.normal(size=(int(rng.integers(2, 30)), 24)) * rng.uniform(0.1, 0.4) for c in centres]).astype(np.float32)
    labels = rng.integers(0, 3, len(x))
    labels[:40] = 0
    unit = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    close = (unit @ unit.T >= 0.93) & (labels[:, None] == labels[None, :])
    np.fill_diagonal(close, False)
    component = np.arange(len(x))
    while True:
        new = np.minimum(component, np.where(close, component[None, :], len(x)).min(axis=1))
        if (new == component).all():
            break
        component = new
    frame = spark.createDataFrame([(i, int(l), v.tolist()) for i, (l, v) in enumerate(zip(labels, x, strict=True))], "vec_id long, label int, embedding array<float>")
    got = sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in embedding_dedup.embedding_dedup(frame, shard_rows=60).collect())
    assert close.sum() > 300
    assert got == [(i, int(close[i].sum()), int(component[i]), bool(component[i] == i)) for i in range(len(x))]


def test_topk_with_repeated_rows_huge_components_and_many_chunks(spark):
    rows = [(0, [1e6, 0.5]), (50, [3e5, -1e6]), (50, [3e5, -1e6]), (7, [2.0, 2.0]), (7, [2.0, 2.0]), (100, [float("nan"), 1.0]), (150, [None, 1.0]), (200, []), (None, [1.0, 1.0]), (8, [-1.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    weights = [(i, [int(np.floor(256 * v)) for v in x]) for i, x in rows if i is not None and all(v is not None and np.isfinite(v) for v in x)]
    want = []
    for q, a in {i: w for i, w in weights if i % 50 == 0}.items():
        scored = sorted((-sum(u * v for u, v in zip(a, b, strict=False)), i) for i, b in weights if i != q)
        want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored[:5])]
    assert sorted(map(tuple, exact_topk.topk_self(frame).collect())) == sorted(want)
    v = spark.range(300).select(F.col("id").alias("vec_id"), F.array(*(F.pmod(F.xxhash64("id", F.lit(j)), F.lit(97)).cast("double") / 50 for j in range(6))).alias("embedding"))
    rows_ = exact_topk.integer_weights(v)
    one, many = (sorted(map(tuple, exact_topk.topk(rows_, rows_, 4, chunk=c).collect())) for c in (4096, 40))
    assert one == many and len(one) == 1200


def test_mix_deals_out_rows_without_an_id(spark):
    """A third of the rows without an id: groups stay small, and each source still meets its target."""
    rows = [(None if i % 3 == 0 else i, f"w{i} " * (1 + i % 9), "ab"[i % 2]) for i in range(600)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = source_mix.mix(frame, group_rows=16)
    got = out.collect()
    assert len(got) == 600 and all(0 <= r.taken <= 2 * r.size for r in got)
    for source_size, target in {(r.source_size, r.target) for r in got}:
        assert abs(sum(r.taken for r in got if (r.source_size, r.target) == (source_size, target)) - target) <= 1
    again = Counter(map(tuple, source_mix.mix(frame.repartition(5), group_rows=16).collect()))
    assert again == Counter(map(tuple, got))


def test_a_partial_document_keeps_its_white_space(spark):
    frame = spark.createDataFrame([(i, " a\n\nb\tc  d" * 5, "x", 55) for i in range(9)], "doc_id long, text string, source string, n_chars long")
    texts = {r.text for r in source_mix.apply_mix(frame).collect()}
    assert all((" a\n\nb\tc  d" * 5).startswith(t) for t in texts)


def test_tables_are_trained_where_texts_use_them():
    rng = np.random.default_rng(8)
    pool = [f"{a}{b}{c}" for a in "bcdfg" for b in ("ana", "elo", "iru") for c in "mnp"]
    texts = [" ".join([*rng.choice(pool, 30), *(["awful", "fools"] if i % 3 == 0 else ["kind", "people"])]) for i in range(120)]
    labels = [int(i % 3 == 0) for i in range(120)]
    model = toxicity.fit(texts[:90], labels[:90], rounds=1)
    fixed = toxicity.fit(texts[:90], labels[:90], rounds=1, table_rate=0.0)
    moved = np.flatnonzero((model.word[:, 1:] != fixed.word[:, 1:]).any(axis=1))
    used = {toxicity.word_bucket(w) for t in texts[:90] for w in toxicity.words_of(t)}
    assert set(moved.tolist()) == used and np.isfinite(model.word).all() and np.isfinite(model.char).all()
    grams = np.flatnonzero((model.char[:, 1:] != fixed.char[:, 1:]).any(axis=1))
    assert set(grams.tolist()) == {g for t in texts[:90] for w in toxicity.words_of(t) for g in toxicity.char_grams(w)}
    score, y = toxicity.Scorer(model).score(texts[90:]), np.array(labels[90:]) == 1
    assert score[y].min() > score[~y].max()
