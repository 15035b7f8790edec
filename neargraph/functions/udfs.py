"""Functions for SQL: vectorised distances and a table function that searches a stored index."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F

from neargraph.runtime import prepare


@F.pandas_udf("double")
def l2_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    if not len(a):
        return pd.Series([], dtype="float64")
    d = np.stack(a.to_numpy()).astype(np.float64) - np.stack(b.to_numpy()).astype(np.float64)
    return pd.Series(np.sqrt((d * d).sum(axis=1)))


@F.pandas_udf("array<double>")
def vector_mean(v: pd.Series) -> list:
    """Grouped mean of vectors of one length."""
    return np.stack(v.to_numpy()).astype(np.float64).mean(axis=0).tolist()


@F.udtf(returnType="qid bigint, rnk int, nid bigint, dist double")
class AnnSearch:
    """ann_search(qid, query, ids, vectors, neighbours, k, M): searches one shard that is given as arrays."""

    def eval(self, qid: int, query: list, ids: list, vectors: list, neighbours: list, k: int, M: int) -> Iterator[Row]:
        from neargraph.operators import local
        from neargraph.operators.baselines import padded
        from neargraph.params import SearchParams

        names = np.asarray(ids, np.int64)
        order = np.argsort(names)
        names = names[order]
        x = local.prepared(np.asarray([vectors[i] for i in order], np.float32), "l2")
        adj = padded([[int(np.searchsorted(names, u)) for u in neighbours[i]] for i in order])
        found = local.search_solo(x, adj, local.prepared(np.asarray([query], np.float32), "l2"), SearchParams(k=k, M=M), np.array([qid]))
        for r, (i, v) in enumerate(zip(found.ids[0].tolist(), found.dist[0].tolist(), strict=True), 1):
            if i >= 0:
                yield qid, r, int(names[i]), float(v)


def register(spark: SparkSession) -> None:
    prepare(spark)
    spark.udf.register("l2_distance", l2_udf)
    spark.udtf.register("ann_search", AnnSearch)
