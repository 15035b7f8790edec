"""Connected components of an undirected graph given as edges, by hooking and contraction.

Every round each vertex takes the smallest label among itself and its neighbours, the labels are chased one step,
and the edges are rewritten onto them; edges inside one label vanish. A vertex that is no local minimum merges in each
round, so the number of labels at least halves and the rounds are logarithmic. Each round costs a partial aggregate and
three joins on one key each; nothing is gathered on the driver but the number of edges left.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.runtime import Scratch


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (member, smallest vertex) of the components of the given edges."""
    ids, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
    label = np.arange(len(ids))
    x, y = inverse[: len(a)], inverse[len(a) :]
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        while True:
            nxt = new[new]
            if np.array_equal(nxt, new):
                break
            new = nxt
        if np.array_equal(new, label):
            break
        label = new
    off = label != np.arange(len(ids))
    return ids[off], ids[label[off]]


def local_forest(batches: Iterator[pa.RecordBatch], limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Arrow kernel: replaces the edges of a partition by a spanning forest of theirs, in bounded pieces."""
    held_a, held_b, n = [], [], 0

    def flush():
        a, b = _forest(np.concatenate(held_a), np.concatenate(held_b))
        return a, b

    for batch in batches:
        held_a.append(batch.column(0).to_numpy(zero_copy_only=False))
        held_b.append(batch.column(1).to_numpy(zero_copy_only=False))
        n += batch.num_rows
        if n >= limit:
            a, b = flush()
            if len(a) > limit // 2:  # the forest itself is large: hand it on
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])
                held_a, held_b, n = [], [], 0
            else:
                held_a, held_b, n = [a], [b], len(a)
    if n:
        a, b = flush()
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def components(edges: DataFrame, scratch: Scratch, *, max_rounds: int = 64, are_forests: bool = False) -> DataFrame:
    """``edges(a long, b long)`` -> ``(id long, component_id long)`` for every vertex that has an edge.

    ``component_id`` is the smallest vertex reachable. Self-edges and repeated edges are harmless; no edge gives no row. ``are_forests``
    says that a kernel has reduced the edges already, so that no second Python worker need stand beside it in each task.
    """
    left = edges.where("a <> b").select("a", "b")
    left = scratch.keep(left if are_forests else left.mapInArrow(local_forest, "a long, b long"))
    labels: DataFrame | None = None
    for _ in range(max_rounds):
        if left.isEmpty():
            break
        both = left.select("a", "b").union(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("up"))
        low = scratch.keep(low)
        # pointer chasing: up(up(id)); the hot side streams, so a skewed join can be split
        chase = scratch.keep(low.alias("x").join(low.alias("y"), F.col("x.up") == F.col("y.id")).select(F.col("x.id"), F.col("y.up").alias("up")))
        if labels is None:
            labels = chase.select("id", F.col("up").alias("component_id"))
        else:
            labels = scratch.keep(labels.alias("l").join(chase.alias("c"), F.col("l.component_id") == F.col("c.id"), "left").select(F.col("l.id"), F.coalesce("c.up", "l.component_id").alias("component_id")))
        one = left.join(chase, left.a == chase.id).select(F.col("up").alias("a"), "b")
        two = one.join(chase, one.b == chase.id).select("a", F.col("up").alias("b")).where("a <> b")
        two = two.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
        left = scratch.keep(two.mapInArrow(local_forest, "a long, b long"))
    else:
        raise RuntimeError("components did not settle")
    if labels is None:
        return scratch.spark.createDataFrame([], "id long, component_id long")
    return labels
