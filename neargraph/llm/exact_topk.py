"""Exact top-k by inner product: exhaustive term-at-a-time accumulation.

Every partition turns its rows, block by block, into postings: for each term (component) the rows that hold it and their
weights. A query is a sparse row; term by term its weight times the postings is scattered into a dense array of scores.
Partition selection keeps the k best of a block, they are merged over the blocks of a task, and a window merges the tasks.
Queries go to all tasks in chunks of a bounded number of rows, one pass over the data for each chunk, whose hits are written
before the next one begins: neither plan nor broadcasts grow with the number of chunks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neargraph.runtime import Scratch

#: Most queries sent out at a time: a broadcast of at most so many rows.
QUERY_CHUNK = 16_384
BLOCK_ROWS = 8192
_HITS = "query_id long, vec_id long, score long"
_SCHEMA = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def _matrix(column: pa.Array) -> np.ndarray:
    """Rows of one length as a matrix; shorter rows are filled up with zeros."""
    lengths = np.asarray(column.value_lengths().to_numpy(zero_copy_only=False), np.int64)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    width = int(lengths.max(initial=0))
    if len(lengths) and (lengths == width).all():
        return flat.reshape(len(lengths), width)
    out = np.zeros((len(lengths), width), flat.dtype)
    out[np.repeat(np.arange(len(lengths)), lengths), np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)] = flat
    return out


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k best: highest score, then smallest id. Ties at the cut are all looked at."""
    if len(ids) > k:
        cut = np.partition(scores, len(scores) - k)[len(scores) - k]
        pick = np.flatnonzero(scores >= cut)
    else:
        pick = np.arange(len(ids))
    return pick[np.lexsort((ids[pick], -scores[pick]))[:k]]


def postings(weights: np.ndarray) -> list[tuple[np.ndarray | None, np.ndarray]]:
    """For each term the rows with a weight other than 0 (None: all of them) and these weights."""
    out = []
    for term in range(weights.shape[1]):
        column = weights[:, term]
        rows = np.flatnonzero(column)
        out.append((None, np.ascontiguousarray(column)) if len(rows) == len(column) else (rows, column[rows]))
    return out


def accumulate(query: np.ndarray, lists: list[tuple[np.ndarray | None, np.ndarray]], scores: np.ndarray) -> None:
    """Adds a query's products to the dense array of scores, term by term."""
    for term in np.flatnonzero(query[: len(lists)]):
        rows, weights = lists[term]
        if rows is None:
            scores += query[term] * weights
        else:
            scores[rows] += query[term] * weights


def _search(batches: Iterator[pa.RecordBatch], shared, k: int) -> Iterator[pa.RecordBatch]:
    query_ids, queries = shared.value
    kept: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64)) for _ in query_ids]
    for batch in batches:
        ids, weights = batch.column(0).to_numpy(zero_copy_only=False), _matrix(batch.column(1))
        for at in range(0, len(ids), BLOCK_ROWS):
            own, block = ids[at : at + BLOCK_ROWS], weights[at : at + BLOCK_ROWS]
            lists, scores = postings(block), np.empty(len(own), np.int64)
            for q, query in enumerate(queries):
                scores[:] = 0
                accumulate(query, lists, scores)
                allowed = own != query_ids[q]
                these = (own, scores) if allowed.all() else (own[allowed], scores[allowed])
                top = _best(*these, k)
                i, s = np.concatenate([kept[q][0], these[0][top]]), np.concatenate([kept[q][1], these[1][top]])
                best = _best(i, s, k)
                kept[q] = (i[best], s[best])
    counts = [len(i) for i, _ in kept]
    if sum(counts):
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(query_ids, counts), pa.int64()), pa.array(np.concatenate([i for i, _ in kept])), pa.array(np.concatenate([s for _, s in kept]))], schema=_SCHEMA)


def integer_weights(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", factor: float = 256.0) -> DataFrame:
    """``(vec_id, weights array<long>)``: floor(factor * x), x as double; rows that are null or hold null or non-finite components go."""
    v = F.col(vector_col).cast("array<double>")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vectors.where(v.isNotNull() & ~bad & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(v, lambda x: F.floor(x * factor).cast("long")).alias("weights"))


def topk(rows: DataFrame, queries: DataFrame, k: int = 5, *, chunk: int = QUERY_CHUNK) -> DataFrame:
    """``rows`` and ``queries`` as ``(vec_id, weights)`` -> ``(query_id, rank, vec_id, score)``, the k best for each query.

    A row is no candidate for the query of its own id. Ties go to the smaller id; fewer than k candidates give fewer rows.
    Empty vectors score 0. No queries or no rows give no result. A repeated candidate counts once for each of its rows;
    queries of one id and different weights are not supported, repeated equal queries count once.
    """
    spark = rows.sparkSession
    scratch = Scratch(spark, "topk")
    queries = queries.dropDuplicates(["vec_id"])
    chunks = max(1, -(-queries.count() // (chunk // 2)))
    numbered = scratch.keep(queries.withColumn("chunk", F.pmod(F.xxhash64("vec_id"), F.lit(chunks))))
    path = f"{scratch.base}/hits"
    some = False
    for c in range(chunks):
        # about half the limit each; a chunk beyond the limit is taken in slices
        table = numbered.where(F.col("chunk") == c).select("vec_id", "weights").orderBy("vec_id")
        last = None
        while True:
            part = (table if last is None else table.where(F.col("vec_id") > last)).limit(chunk).toArrow()
            if not part.num_rows:
                break
            ids = part.column(0).to_numpy()
            shared = spark.sparkContext.broadcast((ids, _matrix(part.column(1).combine_chunks())))
            rows.mapInArrow(lambda it, s=shared: _search(it, s, k), _HITS).write.mode("append").parquet(path)
            shared.unpersist()
            some = True
            last = int(ids[-1])
            if part.num_rows < chunk:
                break
    if not some:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    hits = spark.read.schema(_HITS).parquet(path)
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return hits.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def topk_self(vectors: DataFrame, *, every: int = 50, k: int = 5) -> DataFrame:
    """Queries are the rows whose id is divisible by ``every``; candidates are all rows.

    Rows without an id, null vectors and vectors with null or non-finite components take no part; empty vectors score 0. Ties go to the
    smaller id. A row is no candidate for any query of its own id. An empty table gives an empty result.
    """
    rows = integer_weights(vectors)
    return topk(rows, rows.where(F.pmod("vec_id", F.lit(every)) == 0), k)
