"""A search of several shards reaches the recall that it states, on vectors without near structure."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from neargraph.operators import relational as rel
from neargraph.operators import shard
from neargraph.params import SearchParams


@pytest.fixture(scope="module")
def sphere():
    x = np.random.default_rng(2).normal(size=(2500, 64)).astype(np.float32)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_a_search_of_shards_lengthens_its_list_until_strangers_find_theirs(spark, sphere):
    vecs = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(sphere)], "id long, vec array<float>").cache()
    index = shard.build(shard.assign(vecs, 4), 8, base="exact").cache()
    asked = vecs.where("id % 10 = 0").select(F.col("id").alias("qid"), "vec")
    truth = rel.exact_knn(vecs, asked, 10).cache()

    def recall(hits):
        return rel.recall_join(hits, truth).agg(F.avg("recall")).first()[0]

    params = SearchParams(k=10, M=16)
    assert recall(shard.search(index, asked, params, mode="solo")) < 0.9
    assert recall(shard.sure_search(index, asked, params, least=0.95, mode="solo")) >= 0.95
    assert shard.sure_search(index, asked.where("false"), params, least=0.95, mode="solo").count() == 0
