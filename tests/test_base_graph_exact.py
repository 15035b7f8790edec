"""Queries whose SQL has the exact base graph take it at every size: beyond 200,000 vectors it came by neighbour descent, with other edges."""

import pytest
from pyspark.sql import functions as F

from neargraph.operators import relational as rel
from neargraph.plans import workload_queries


@pytest.mark.parametrize("name", ["q_degrees", "q_detour_distance", "q_detour_prune_baseline", "q_detour_rank", "q_distance_pruned", "q_forget_every_third_counts", "q_forget_reset", "q_forget_reset_counts", "q_indegree", "q_rank_family", "q_rank_pruned", "q_reach_pivot"])
def test_the_base_graph_is_exact_whatever_the_size(spark, sf, name, monkeypatch):
    many = spark.range(200_001).select("id", F.array(F.col("id").cast("float")).alias("vec"))
    asked = []

    def exact(vecs, degree, **options):
        asked.append((vecs.count(), degree))
        ring = spark.range(60).select(F.col("id").alias("src"), F.explode(F.sequence(F.lit(0), F.lit(degree - 1))).alias("rank"))
        return ring.withColumn("dst", (F.col("src") + 1 + F.col("rank")) % 60).withColumn("dist", F.col("rank") + 1.0)

    def descent(*_, **__):
        raise AssertionError("an approximate base graph")

    monkeypatch.setattr(workload_queries, "_vecs", lambda *_: many)
    monkeypatch.setattr(rel, "knn_edges", exact)
    monkeypatch.setattr(rel, "descent_edges", descent)
    workload_queries.queries()[name](spark, sf)
    assert asked == [(200_001, workload_queries.BASE)]
