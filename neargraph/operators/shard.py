"""Sharded index: every shard builds its own graph in one task, is searched by itself, and the best of all shards are merged.

A search reads each shard once for a batch of queries, whatever the number of rounds; only k rows for each query and shard leave
it. An index of rows is brought together by shard in each search; a packed one (``pack``) holds a shard in one row, and
nothing of it is shuffled again.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.operators import local
from neargraph.operators.relational import exact_knn, per_query, recall_join
from neargraph.params import SearchParams, choose_mode, initial_degree
from neargraph.runtime import Scratch, prepare

#: Vectors for each shard and rows of queries for each broadcast.
SHARD_ROWS = 1_000_000
QUERY_CHUNK = 65_536


def assign(vecs: DataFrame, shards: int, how: str = "hash", centroids: np.ndarray | None = None) -> DataFrame:
    """VEC rows with ``shard_id``: by id modulo the number of shards, or by the nearest centroid."""
    if how == "hash":
        return vecs.withColumn("shard_id", F.pmod("id", F.lit(shards)).cast("int"))
    if centroids is None:
        raise ValueError("centroids are needed")
    prepare(vecs.sparkSession)
    c = centroids.astype(np.float64)

    @F.pandas_udf("int")
    def nearest(col: pd.Series) -> pd.Series:
        x = np.stack(col.to_numpy()).astype(np.float64)
        return pd.Series(local.block_distances(x, c, "sql2").argmin(axis=1).astype(np.int32))

    return vecs.withColumn("shard_id", nearest("vec"))


def centroids(vecs: DataFrame, shards: int, *, sample_rows: int = 20_000, seed: int = 1) -> np.ndarray:
    """Cluster centres from a bounded sample, by the order of a hash."""
    from neargraph.operators.baselines import kmeans

    rows = vecs.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(sample_rows).select("vec").toPandas()
    return kmeans(np.stack(rows["vec"].to_numpy()).astype(np.float64), shards, seed=seed)


def build(vecs: DataFrame, d: int, *, factor: int = 3, metric: str = "l2", base: str = "descent", reorder: str = "rank", reverse: bool = True, builder: Callable | None = None, seed: int = 1) -> DataFrame:
    """(shard_id, id, vec, nbrs) from VEC rows with ``shard_id``; neighbours are ids of the same shard.

    ``base``: 'descent' or 'exact'. Small shards get as many neighbours as they can. ``builder(x)`` may give another graph, padded with -1.
    """
    prepare(vecs.sparkSession)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id", kind="stable").reset_index(drop=True)
        ids, x = pdf["id"].to_numpy(), local.prepared(np.stack(pdf["vec"].to_numpy()), metric)
        n = len(ids)
        if n == 1:
            adj = np.zeros((1, 0), np.int64)
        elif builder is not None:
            adj = builder(x)
        else:
            own = min(initial_degree(d, factor), n - 1)
            lists, dist = local.exact_graph(x, own, metric) if base == "exact" or n <= 4 * own else local.descent_graph(x, own, metric, seed=seed)[:2]
            adj = local.uniform_graph(lists, min(d, own), reorder=reorder, reverse=reverse, dist=dist, x=x, metric=metric)
        pdf["nbrs"] = [ids[row[row >= 0]] for row in adj]
        return pdf[["shard_id", "id", "vec", "nbrs"]]

    return vecs.select("shard_id", "id", "vec").groupBy("shard_id").applyInPandas(run, "shard_id int, id long, vec array<float>, nbrs array<long>")


_FOUND = "qid long, nid long, dist double, n_dist long, rounds long"


def _arrays(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of a shard -> (ids in order, vectors, places of neighbours padded with -1)."""
    pdf = pdf.sort_values("id", kind="stable")
    ids, lists = pdf["id"].to_numpy(), pdf["nbrs"].tolist()
    sizes = np.fromiter(map(len, lists), np.int64, len(lists))
    adj = np.full((len(ids), int(sizes.max())), -1, np.int64)
    flat = np.concatenate([np.asarray(own, np.int64) for own in lists])
    adj[np.repeat(np.arange(len(ids)), sizes), np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = np.searchsorted(ids, flat)
    return ids, np.stack(pdf["vec"].to_numpy()), adj


def _search_shard(ids: np.ndarray, vecs: np.ndarray, adj: np.ndarray, shared, params: SearchParams, mode: str) -> pd.DataFrame:
    qids, qvecs = shared.value
    x = local.prepared(vecs, params.metric, params.dtype)
    q = local.prepared(qvecs, params.metric, params.dtype)
    if not adj.shape[1]:
        found = local.Found(np.zeros((len(q), 1), np.int64), local.block_distances(q, x, params.metric), np.ones(len(q), np.int64), np.zeros(len(q), np.int64))
    else:
        search = local.search_team if mode == "team" else local.search_solo
        found = search(x, adj, q, params, qids)
    rows, col = np.nonzero(found.ids >= 0)
    return pd.DataFrame({"qid": qids[rows], "nid": ids[found.ids[rows, col]], "dist": found.dist[rows, col], "n_dist": np.where(col == 0, found.n_dist[rows], 0), "rounds": found.rounds[rows]})


def pack(index: DataFrame) -> DataFrame:
    """An index of rows -> one row for each shard: its ids, vectors (float32) and neighbours (places, padded with -1) as bytes.

    Written once, it is searched as often as wanted without a shuffle: a shard is read, as arrays, by the task that has its row. A row
    must stay below 2 GB: ``SHARD_ROWS`` vectors of 96 dimensions with 32 neighbours each take 520 MB.
    """
    prepare(index.sparkSession)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, vecs, adj = _arrays(pdf)
        return pd.DataFrame({"shard_id": [int(pdf["shard_id"].iloc[0])], "n": [len(ids)], "ids": [ids.astype("<i8").tobytes()], "vectors": [vecs.astype("<f4").tobytes()], "neighbours": [adj.astype("<i4").tobytes()]})

    return index.select("shard_id", "id", "vec", "nbrs").groupBy("shard_id").applyInPandas(run, "shard_id int, n long, ids binary, vectors binary, neighbours binary")


def _packed_searcher(shared, params: SearchParams, mode: str):
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                n = batch.column(0)[i].as_py()
                ids, vecs, adj = (np.frombuffer(batch.column(c)[i].as_buffer(), t) for c, t in ((1, "<i8"), (2, "<f4"), (3, "<i4")))
                found = _search_shard(ids, vecs.reshape(n, -1), adj.astype(np.int64).reshape(n, -1) if len(adj) else np.zeros((n, 0), np.int64), shared, params, mode)
                yield pa.RecordBatch.from_pandas(found, preserve_index=False)

    return run


def _searcher(shared, params: SearchParams, mode: str):
    return lambda pdf: _search_shard(*_arrays(pdf), shared, params, mode)


def search(index: DataFrame, queries: DataFrame, params: SearchParams, *, mode: str = "auto", b_t: int | None = None, chunk: int = QUERY_CHUNK, probe: int | None = None, centres: np.ndarray | None = None, counters: bool = False) -> DataFrame:
    """HIT rows from a built index, of rows or packed. Queries go out in chunks of bounded size, one pass over the shards for each.

    ``mode``: 'solo', 'team', or 'auto' by batch size and list length; a team that the rule chooses divides the list among its walkers. ``probe`` with ``centres`` reads only shards that are among the nearest
    of some query. With ``counters`` each query's distance count and rounds come instead.
    """
    spark = prepare(index.sparkSession)
    hits: DataFrame | None = None
    last = None
    while True:
        part = (queries if last is None else queries.where(F.col("qid") > last)).select("qid", "vec").orderBy("qid").limit(chunk).toPandas()
        if not len(part):
            break
        qids, qvecs = part["qid"].to_numpy(), np.stack(part["vec"].to_numpy()).astype(np.float32)
        use = choose_mode(len(part), params.M, b_t=b_t or spark.sparkContext.defaultParallelism) if mode == "auto" else mode
        own = index
        if probe is not None and centres is not None:
            near = local.smallest(local.block_distances(qvecs.astype(np.float64), centres, "sql2"), probe)[0]
            own = index.where(F.col("shard_id").isin(np.unique(near).tolist()))  # prunes partitions of a stored index
        shared = spark.sparkContext.broadcast((qids, qvecs))
        own_params = replace(params, team_list=-(-max(params.M, params.k) // params.walkers)) if mode == "auto" and use == "team" and params.team_list is None else params
        if "vectors" in own.columns:
            found = own.select("n", "ids", "vectors", "neighbours").mapInArrow(_packed_searcher(shared, own_params, use), _FOUND)
        else:
            found = own.groupBy("shard_id").applyInPandas(_searcher(shared, own_params, use), _FOUND)
        hits = found if hits is None else hits.unionByName(found)
        last = int(qids[-1])
        if len(part) < chunk:
            break
    if hits is None:
        return spark.createDataFrame([], "qid long, n_dist long, rounds long" if counters else "qid long, rnk int, nid long, dist double")
    if counters:
        return hits.groupBy("qid").agg(F.sum("n_dist").alias("n_dist"), F.max("rounds").alias("rounds"))
    return per_query(hits.select("qid", "nid", "dist"), params.k)


def sure_search(index: DataFrame, queries: DataFrame, params: SearchParams, *, least: float, **options) -> DataFrame:
    """``search`` with as long a list as it takes: it is doubled until a sample of queries has ``least`` of its exact neighbours.

    A query that is a row of the index is a node of one shard only and a stranger to the others, whose walks find less of it with a list of one length.
    """
    scratch, rows = Scratch(index.sparkSession, "audit"), index.select("id", "vec")
    asked = scratch.keep(queries.orderBy(F.xxhash64("qid"), "qid").limit(local.AUDITED))
    truth = scratch.keep(exact_knn(rows, asked, params.k, metric=params.metric))
    n = rows.count()
    while params.M < n:
        shares = recall_join(search(index, asked, params, **options), truth).toPandas()["recall"].to_numpy()  # a row for each sampled query
        if not len(shares) or local.surely(shares, least):
            break
        params = replace(params, M=min(2 * params.M, n))
    return search(index, queries, params, **options)


def exact(index: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """HIT rows by comparing every query with every vector, block by block in one pass for each chunk of queries."""
    return search_exact(index.select("id", "vec"), queries, k, metric)


def search_exact(vecs: DataFrame, queries: DataFrame, k: int, metric: str = "l2", *, chunk: int = 8192, exclude_self: bool = False) -> DataFrame:
    import pyarrow as pa

    spark = prepare(vecs.sparkSession)
    hits: DataFrame | None = None
    last = None
    while True:
        part = (queries if last is None else queries.where(F.col("qid") > last)).select("qid", "vec").orderBy("qid").limit(chunk).toPandas()
        if not len(part):
            break
        shared = spark.sparkContext.broadcast((part["qid"].to_numpy(), local.prepared(np.stack(part["vec"].to_numpy()), metric)))

        def run(batches, shared=shared):
            qids, q = shared.value
            top_i, top_d = np.full((len(q), k), -1, np.int64), np.full((len(q), k), np.inf)
            for batch in batches:
                if not batch.num_rows:
                    continue
                ids = batch.column(0).to_numpy()
                vec = batch.column(1)
                x = local.prepared(vec.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1), metric)
                order = np.argsort(ids, kind="stable")
                ids, x = ids[order], x[order]
                for at in range(0, len(q), 256):
                    d = local.block_distances(q[at : at + 256], x, metric)
                    if exclude_self:
                        d[qids[at : at + 256][:, None] == ids[None, :]] = np.inf
                    i, v = local.smallest(d, k)
                    top_i[at : at + 256], top_d[at : at + 256], _ = local.merge_top(top_i[at : at + 256], top_d[at : at + 256], np.zeros((len(d), k), bool), ids[i], v, k, "merge")
            rows, col = np.nonzero((top_i >= 0) & np.isfinite(top_d))
            yield pa.RecordBatch.from_arrays([pa.array(qids[rows]), pa.array(top_i[rows, col]), pa.array(top_d[rows, col])], names=["qid", "nid", "dist"])

        found = vecs.select("id", "vec").mapInArrow(run, "qid long, nid long, dist double")
        hits = found if hits is None else hits.unionByName(found)
        last = int(part["qid"].iloc[-1])
        if len(part) < chunk:
            break
    return per_query(hits, k) if hits is not None else spark.createDataFrame([], "qid long, rnk int, nid long, dist double")
