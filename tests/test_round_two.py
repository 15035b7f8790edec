"""Visited flags, teams, packed shards, descent in rounds, equal-recall speed-ups, and the library without its optional parts."""

import os
import shutil
import subprocess
import sys

import numpy as np
import pytest

from neargraph.operators import local, relational as rel, shard
from neargraph.params import SearchParams
from neargraph.plans import workloads
from neargraph.runtime import Scratch

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


@pytest.fixture(scope="module")
def x():
    return local.prepared(np.random.default_rng(0).normal(size=(400, 16)), "l2")


@pytest.fixture(scope="module")
def graph(x):
    return local.uniform_graph(local.exact_graph(x, 24)[0], 8)


@pytest.fixture(scope="module")
def vecs(spark, x):
    return spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<float>").cache()


def test_flags_answer_as_a_table_does():
    rng = np.random.default_rng(1)
    table, flags = local.VisitedSet(5, 9), local.SeenMap(5, 100)
    for _ in range(20):
        key = np.unique(rng.integers(0, 500, 40))
        assert (table.insert(key // 100, key % 100) == flags.insert(key // 100, key % 100)).all()
    table, flags = local.VisitedSet(4, 9), local.SeenMap(4, 50)
    for _ in range(10):
        cand = rng.integers(-1, 50, (4, 12))  # with nodes that stand twice in a row
        assert (local._first_time(cand, np.arange(4), table) == local._first_time(cand, np.arange(4), flags)).all()
    assert isinstance(local.full_set(2, 1000, 256), local.SeenMap) and isinstance(local.full_set(2, 10_000, 256), local.VisitedSet)


@pytest.mark.parametrize("options", [{}, {"walkers": 3, "M": 20}, {"team_list": 6}, {"M": 12, "walkers": 8, "team_list": 2}])
def test_few_queries_walk_as_many_do(x, graph, options):
    params = SearchParams(**({"k": 10, "M": 24} | options))
    qids = np.arange(40)
    many = local.search_team(x, graph, x[:40], params, qids)
    few = local.joined([local.search_team(x, graph, x[i : i + 1], params, qids[i : i + 1]) for i in range(40)])
    assert (many.ids == few.ids).all() and (many.n_dist == few.n_dist).all() and (many.rounds == few.rounds).all()
    assert np.allclose(many.dist, few.dist)


def test_merging_leaves_out_only_what_is_too_far():
    rng = np.random.default_rng(7)
    for _ in range(50):
        M, C = 6, int(rng.integers(1, 20))
        values = rng.integers(0, 8, (3, M + C)).astype(float)  # many ties
        ids = np.stack([rng.permutation(100)[: M + C] for _ in range(3)])
        order = np.lexsort((ids[:, :M], values[:, :M]), axis=1)
        own_i, own_d = np.take_along_axis(ids[:, :M], order, 1), np.take_along_axis(values[:, :M], order, 1)
        if rng.random() < 0.5:
            own_i[:, 4:], own_d[:, 4:] = -1, np.inf
        flag = rng.random((3, M)) < 0.5
        got = local.merge_top(own_i, own_d, flag, ids[:, M:], values[:, M:], M, "merge")
        for r in range(3):
            entries = [(d, i, f) for d, i, f in zip(own_d[r], own_i[r], flag[r], strict=True) if i >= 0] + [(d, i, False) for d, i in zip(values[r, M:], ids[r, M:], strict=True)]
            want = sorted(entries, key=lambda e: e[:2])[:M]
            have = [(d, i, f) for i, d, f in zip(got[0][r], got[1][r], got[2][r], strict=True) if i >= 0]
            assert have == want


def test_slices_of_a_batch_change_nothing(x, graph):
    whole, cut = (local.search_solo(x, graph, x[:90], SearchParams(k=10, M=24, in_step=n), np.arange(90)) for n in (1000, 7))
    assert (whole.ids == cut.ids).all() and (whole.n_dist == cut.n_dist).all()


def test_a_short_list_for_each_walker_keeps_recall(x, graph):
    truth = local.exact_knn(x, x, 10)[0]
    solo = local.search_solo(x, graph, x, SearchParams(k=10, M=64))
    team = local.search_team(x, graph, x, SearchParams(k=10, M=64, team_list=16))
    assert local.recall(team.ids, truth) > local.recall(solo.ids, truth) - 0.03
    assert team.rounds.mean() < solo.rounds.mean() / 2


@pytest.mark.parametrize("options", [{}, {"p": 3}, {"visited": "forget", "bits": 12}, {"stop": "unchanged"}])
def test_expanded_nodes_beside_the_list_or_in_a_table(x, graph, options):
    a, b = (local.search_solo(x, graph, x[:60], SearchParams(k=10, M=24, expanded=where, **options), np.arange(60)) for where in ("flag", "table"))
    assert (a.ids == b.ids).all() and (a.n_dist == b.n_dist).all() and (a.rounds == b.rounds).all()


@pytest.mark.parametrize("kind", ["float", "int", "byte"])
def test_vector_files_are_read_in_ranges(spark, tmp_path, kind):
    from neargraph.sources import fvecs

    data = np.random.default_rng(2).integers(0, 200, (1000, 7)).astype("f4") + (0.5 if kind == "float" else 0)
    fvecs.write(data, str(tmp_path / "v.vecs"), kind)
    spark.dataSource.register(fvecs.VectorFiles)
    df = spark.read.format("vector_files").option("path", str(tmp_path / "v.vecs")).option("kind", kind).option("rows_per_task", 300).option("first_id", 5).load()
    assert df.rdd.getNumPartitions() == 4
    rows = df.orderBy("id").collect()
    assert [r.id for r in rows] == list(range(5, 1005)) and np.array_equal(np.array([r.vec for r in rows], "f4"), data)
    with pytest.raises(Exception, match="whole vectors"):
        (tmp_path / "bad").write_bytes((tmp_path / "v.vecs").read_bytes()[:-1])
        spark.read.format("vector_files").option("path", str(tmp_path / "bad")).option("kind", kind).load().count()


def test_packed_shards_are_searched_without_a_shuffle(spark, vecs):
    index = shard.build(shard.assign(vecs, 3), 8, base="exact")
    packed = Scratch(spark, "test").keep(shard.pack(index))
    queries = vecs.where("id % 9 = 0").selectExpr("id AS qid", "vec")
    params = SearchParams(k=5, M=32)
    a, b = (sorted((r.qid, r.rnk, r.nid) for r in shard.search(i, queries, params, mode="solo").collect()) for i in (index, packed))
    assert a == b
    plan = shard.search(packed, queries, params, mode="solo")._jdf.queryExecution().executedPlan().toString()
    below = plan[plan.index("MapInArrow") :]
    assert "Exchange" not in below and "Scan parquet" in below
    lonely = shard.pack(shard.build(shard.assign(vecs.limit(1), 1), 8))
    assert [r.nid for r in shard.search(lonely, queries.limit(1), params, mode="solo").collect()] == [r.id for r in vecs.limit(1).collect()]


def test_descent_in_rounds_finds_the_neighbours(spark, vecs):
    truth = {(r.src, r.dst) for r in rel.knn_edges(vecs, 12).collect()}
    got = rel.descent_edges(vecs, 12, Scratch(spark, "test")).collect()
    assert len(got) == len({(r.src, r.dst) for r in got}) == 400 * 12 and all(r.src != r.dst for r in got)
    assert len(truth & {(r.src, r.dst) for r in got}) > 0.97 * len(truth)
    with pytest.raises(ValueError):
        rel.descent_edges(vecs.where("id > 3"), 12, Scratch(spark, "test"))


def test_the_base_graph_of_a_large_set_comes_by_descent(spark, vecs):
    exact = rel.base_edges(vecs, 12, Scratch(spark, "test"))
    assert exact.exceptAll(rel.knn_edges(vecs, 12)).isEmpty()
    found = rel.base_edges(vecs, 12, Scratch(spark, "test"), exact_rows=399)
    assert found.columns == exact.columns and found.count() == 400 * 12


def test_speed_up_at_equal_recall(spark):
    rows = [("uniform M=8", "recall", 0.8), ("uniform M=8", "qps", 100.0), ("uniform M=16", "recall", 1.0), ("uniform M=16", "qps", 50.0), ("other M=8", "recall", 0.8), ("other M=8", "qps", 30.0), ("other M=9", "recall", 0.96), ("other M=9", "qps", 10.0), ("low M=9", "recall", 0.5), ("low M=9", "qps", 900.0)]
    got = {(r[0], r[1]): r[2] for r in workloads.with_speedups(spark.createDataFrame(rows, "setting string, measure string, value double"), levels=(0.9,)).collect()}
    assert got["uniform over other", "speedup@0.9"] == pytest.approx(75 / 17.5)
    assert not any("low" in k[0] and k[1] == "speedup@0.9" for k in got)


def test_exponents_of_measured_times():
    rows = [(f"n={n}", m, v) for n in (10, 100, 1000) for m, v in (("rows", n), ("build_seconds", 3.0 * n), ("search_seconds@10", 2.0 * n**0.5))]
    assert {m: round(v, 6) for _, m, v in workloads.scaling_exponents(rows)} == {"build_seconds exponent": 1.0, "search_seconds@10 exponent": 0.5}


def test_a_study_refuses_what_a_task_may_not_hold(vecs, monkeypatch):
    monkeypatch.setattr(workloads, "STUDY_ROWS", 399)
    with pytest.raises(ValueError):
        workloads.a1_reachability(vecs)


def _imported(folder, code=""):
    script = f"import __spark_entry__ as e; q = e.queries(); o = e.oracle_sql(); print(len(q), sum(n.startswith('op') or n == 'pipeline' for n in q), set(o) <= set(q)); {code}"
    out = subprocess.run([sys.executable, "-c", script], cwd=folder, capture_output=True, text=True, timeout=120, env=os.environ | {"PYTHONPATH": str(folder) + os.pathsep + os.environ.get("PYTHONPATH", "")})
    assert out.returncode == 0, out.stderr
    return out.stdout.split()


def test_the_library_imports_and_answers_without_its_optional_folders(tmp_path):
    shutil.copytree(ROOT, tmp_path / "all", ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse", "metastore_db"))
    shutil.rmtree(tmp_path / "all" / "neargraph" / "llm", ignore_errors=True)
    shutil.rmtree(tmp_path / "all" / "tests" / "llm", ignore_errors=True)
    (tmp_path / "all" / "corpus_pipeline.py").unlink(missing_ok=True)
    run = "from pyspark.sql import SparkSession; s = SparkSession.builder.master('local[1]').config('spark.ui.enabled', 'false').getOrCreate(); print(q['q_mode_rule'](s, '/root/testdata/sf0.001').count())"
    n, ops, same, rows = _imported(tmp_path / "all", run)
    assert int(n) > 100 and ops == "0" and same == "True" and int(rows) > 0


def test_a_missing_tokenizer_library_leaves_the_operators_out(tmp_path):
    shutil.copytree(ROOT, tmp_path / "all", ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse", "metastore_db"))
    (tmp_path / "all" / "sitecustomize.py").write_text("import sys\nsys.modules['public_tokenizers'] = None\n")
    n, ops, same = _imported(tmp_path / "all")
    assert int(n) > 100 and ops == "0" and same == "True"
