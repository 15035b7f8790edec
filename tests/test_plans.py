"""Plans against kernels and brute force; shape of the physical plans; sources, store, streams."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from neargraph.operators import linking, local, shard
from neargraph.operators import relational as rel
from neargraph.params import SearchParams
from neargraph.runtime import Scratch
from neargraph.sources import index_store
from neargraph.sources import vectors as src
from neargraph.streaming import online


@pytest.fixture(scope="module")
def points(spark):
    x = np.random.default_rng(3).normal(size=(80, 6)).astype(np.float32)
    return x, spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<float>").cache()


def rows(df, *columns):
    return sorted(tuple(r[c] for c in columns) for r in df.collect())


def test_graph_plan_equals_kernel(spark, points):
    x, df = points
    v = local.prepared(x, "l2")
    ids, dist = local.exact_graph(v, 18)
    edges = rel.knn_edges(df, 18).cache()
    assert rows(edges, "src", "rank", "dst") == sorted((i, r, int(n)) for i in range(80) for r, n in enumerate(ids[i]))
    for reorder, table in (("rank", None), ("distance", dist), ("none", None)):
        want = local.uniform_graph(ids, 6, reorder="distance_table" if reorder == "distance" else reorder, dist=table)
        got = rel.uniform_graph(edges, 6, reorder=reorder)
        assert rows(got, "src", "rank", "dst") == sorted((i, r, int(n)) for i in range(80) for r, n in enumerate(want[i]))
    hops = rel.two_hop(rel.uniform_graph(edges, 6))
    assert [r[1] for r in rows(hops, "src", "reached")] == local.two_hop_counts(local.uniform_graph(ids, 6)).tolist()


def test_walk_in_rounds_equals_kernel(spark, points):
    x, df = points
    v = local.prepared(x, "l2")
    g = local.uniform_graph(local.exact_graph(v, 18)[0], 6)
    adj = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(g)], "id long, nbrs array<long>")
    q = df.where("id < 5").select(F.col("id").alias("qid"), "vec")
    for options in ({}, {"visited": "forget", "bits": 12}):
        params = SearchParams(k=5, M=12, **options)
        hits, stats = rel.search(df, adj, q, params, Scratch(spark, "t"), n=80, d=6)
        found = local.search_solo(v, g, v[:5], params, np.arange(5))
        assert rows(hits, "qid", "rnk", "nid") == sorted((i, r + 1, int(n)) for i in range(5) for r, n in enumerate(found.ids[i]))
        if not options:
            assert [r[1] for r in rows(stats, "qid", "n_dist")] == found.n_dist.tolist()


def test_no_vectors_in_optimisation(spark, points, capsys):
    _, df = points
    edges = Scratch(spark, "t").keep(rel.knn_edges(df, 9).select("src", "rank", "dst"))
    rel.uniform_graph(edges, 4).explain("formatted")
    plan = capsys.readouterr().out
    assert "vec" not in plan and "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_exact_plan_limits_before_shuffle(points, capsys):
    _, df = points
    rel.exact_knn(df, df.where("id < 3").select(F.col("id").alias("qid"), "vec"), 4).explain()
    plan = capsys.readouterr().out
    assert "BroadcastNestedLoopJoin" in plan and plan.count("WindowGroupLimit") == 2


def test_sharded_exact_is_exact_and_empty_queries(spark, points):
    x, df = points
    q = df.where("id % 9 = 0").select(F.col("id").alias("qid"), "vec")
    index = shard.build(shard.assign(df, 3), 4, base="exact")
    a = rel.exact_knn(df, q, 5)
    assert rows(a, "qid", "rnk", "nid") == rows(shard.exact(index, q, 5), "qid", "rnk", "nid") == rows(shard.search_exact(df, q, 5, chunk=4), "qid", "rnk", "nid")
    assert shard.search(index, q.where("false"), SearchParams(k=2, M=4)).count() == 0
    few = shard.search(index, q, SearchParams(k=5, M=40, p=4), mode="solo", chunk=4)
    assert rows(few, "qid", "rnk", "nid") == rows(a, "qid", "rnk", "nid")


def test_one_row_shard_and_routing(spark, points):
    x, df = points
    own = df.withColumn("shard_id", F.when(F.col("id") == 79, 1).otherwise(0))
    index = shard.build(own, 4)
    q = df.where("id = 79").select(F.col("id").alias("qid"), "vec")
    assert shard.search(index, q, SearchParams(k=1, M=8), mode="solo").first().nid == 79
    c = shard.centroids(df, 4)
    routed = shard.assign(df, 4, "centroid", c)
    path = Scratch(spark, "t").base
    index_store.save(shard.build(routed, 4), path, metric="l2")
    stored = index_store.open_index(spark, path)
    assert index_store.about(spark, path)["n"] == 80 and index_store.missing_shards(spark, path, 5) == [4]
    hits = shard.search(stored, q, SearchParams(k=1, M=8), mode="solo", probe=1, centres=c)
    assert hits.first().nid == 79


def test_components(spark):
    rng = np.random.default_rng(1)
    pairs = rng.integers(0, 300, (200, 2)).tolist() + [[400 + i, 401 + i] for i in range(60)] + [[7, 7]]
    df = spark.createDataFrame(pairs, "a long, b long").repartition(4)
    label = {}
    for a, b in pairs:
        label.setdefault(a, a), label.setdefault(b, b)
    changed = True
    while changed:
        changed = False
        for a, b in pairs:
            m = min(label[a], label[b])
            changed |= label[a] != m or label[b] != m
            label[a] = label[b] = m
    got = dict(rows(linking.components(df, Scratch(spark, "t")), "id", "component_id"))
    assert got == {k: v for k, v in label.items() if any(k in p and p[0] != p[1] for p in pairs)}
    assert linking.components(df.where("false"), Scratch(spark, "t")).count() == 0


def test_strong_labels(spark):
    edges = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 3), (5, 0), (6, 6)]
    df = spark.createDataFrame(edges, "src long, dst long")
    assert dict(rows(rel.strong_labels(df, Scratch(spark, "t")), "id", "component")) == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 5}


def test_sources(spark, tmp_path):
    x = np.arange(12, dtype=np.float32).reshape(4, 3)
    src.write_packed(str(tmp_path / "v.bin"), x)
    got = src.read_packed(spark, str(tmp_path / "v.bin")).orderBy("place").collect()
    assert [r.vec for r in got] == x.tolist()
    (tmp_path / "v.csv").write_text('id,vec\n1,"[0.5, 1.5]"\n')
    assert src.read(spark, "csv", str(tmp_path / "v.csv")).first().vec == [0.5, 1.5]
    (tmp_path / "v.json").write_text('{"id": 1, "vec": [0.5, 1.5]}\n')
    assert src.read(spark, "json", str(tmp_path / "v.json")).first().vec == [0.5, 1.5]
    good = spark.createDataFrame([(1, [1.0, 2.0]), (2, [3.0, 4.0])], "id long, vec array<float>")
    assert src.validate(good, 2) == {"n": 2, "dim": 2}
    for bad in ([(1, [1.0])], [(1, None)], [(1, [1.0, float("nan")])], [(2, [0.0, 0.0])], [(None, [0.0, 0.0])]):
        with pytest.raises(ValueError):
            src.validate(good.union(spark.createDataFrame(bad, good.schema)), 2)
    ids = src.dense_ids(spark.createDataFrame([(v,) for v in (5, 3, 9, 1)], "k long"), ["k"])
    assert rows(ids, "k", "id") == [(1, 0), (3, 1), (5, 2), (9, 3)]


def test_text_vectors(spark):
    df = spark.createDataFrame([(1, "Abcab"), (2, "ab"), (3, None)], "doc_id long, text string")
    got = {r.id: r.vec for r in src.gram_vectors(df, "doc_id", "text", 7).collect()}
    want = np.zeros(7)
    for g in ("abc", "bca", "cab"):
        want[(ord(g[0]) * 961 + ord(g[1]) * 31 + ord(g[2])) % 7] += 1
    assert np.allclose(got[1], want / np.linalg.norm(want)) and not any(got[2]) and not any(got[3])


def test_stream_equals_batch(spark, tmp_path, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).orderBy("ts").limit(400)
    folder = str(tmp_path / "in")
    events.coalesce(1).sortWithinPartitions("ts").write.parquet(folder)
    stream = online.event_stream(spark, folder)
    q = online.tumbling(stream).writeStream.outputMode("complete").format("memory").queryName("tumbling").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert rows(spark.table("tumbling"), "start", "event_type", "n") == rows(online.tumbling(events), "start", "event_type", "n")
    v = src.vectors(spark, sf)
    index = Scratch(spark, "t").keep(shard.build(shard.assign(v, 1), 8))
    out = str(tmp_path / "out")
    for _ in range(2):  # the second start has nothing to do
        online.search_stream(online.event_stream(spark, folder), index, v, out, str(tmp_path / "c2"), SearchParams(k=3, M=16)).awaitTermination()
    hits = spark.read.parquet(out)
    assert hits.count() == 3 * 400 and hits.select("qid").distinct().count() == 400
    state = online.recent_queries(online.event_stream(spark, folder)).writeStream.outputMode("update").format("memory").queryName("recent").option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start()
    state.awaitTermination()
    assert spark.table("recent").agg(F.max("n_recent")).first()[0] <= 5


def test_library_runs_without_llm():
    import neargraph

    base = os.path.dirname(neargraph.__file__)
    for folder, _, files in os.walk(base):
        if os.path.basename(folder) != "llm":
            for f in files:
                if f.endswith(".py"):
                    with open(os.path.join(folder, f)) as h:
                        assert "neargraph.llm" not in h.read()


def test_scaling_covers_the_table(spark):
    """The ladder is a hundredth, a tenth and all of the rows, whatever their number, and asks every hundredth id."""
    from neargraph.plans import workloads

    rng = np.random.default_rng(4)
    vecs = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(900, 4)))], "id long, vec array<float>").cache()
    got = {(r[0], r[1]): r[2] for r in workloads.c5_scaling(vecs).collect()}
    assert {name: value for (name, what), value in got.items() if what == "rows"} == {"n=9": 9, "n=90": 90, "n=900": 900}
    assert {name: value for (name, what), value in got.items() if what == "queries"} == {"n=9": 1, "n=90": 1, "n=900": 9}
    assert all(value > 0.95 for (_, what), value in got.items() if what.startswith("recall"))
