"""Two-edge ways round the edges of a graph that a task holds as arrays: no pair of edges goes through a join."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Most edges that every task holds (at 24 bytes each), and two-edge ways that are looked up at once.
SENT_EDGES, LOOKED_UP = 1 << 22, 1 << 20


class Edges:
    """Edges in the order of (src, dst), nodes as places among all ids; ``length`` of an edge is its rank or distance."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, rank: np.ndarray, length: np.ndarray) -> None:
        self.ids, place = np.unique(np.concatenate([src, dst]), return_inverse=True)
        order = np.lexsort((place[len(src) :], place[: len(src)]))
        own, self.dst = place[: len(src)][order], place[len(src) :][order].astype(np.int32)
        self.starts = np.searchsorted(own, np.arange(len(self.ids) + 1))
        self.rank, self.length = rank[order], length[order]
        self.once = not ((own[1:] == own[:-1]) & (self.dst[1:] == self.dst[:-1])).any()

    def counted(self, low: int, high: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(src, rank, dst, detours) of the edges from the nodes at places ``low`` to ``high``."""
        n, a, b = len(self.ids), self.starts[low], self.starts[high]
        src = np.repeat(np.arange(low, high), np.diff(self.starts[low : high + 1]))
        known = src * n + self.dst[a:b]
        each = np.diff(self.starts)[self.dst[a:b]]
        out, ends = np.zeros(b - a, np.int64), np.cumsum(each)
        at = 0
        while at < b - a:  # first edges whose ways are looked up together
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + LOOKED_UP, "right")))
            first = np.repeat(np.arange(at, to), each[at:to])
            second = np.arange(len(first)) - np.repeat(ends[at:to] - each[at:to] - (ends[at - 1] if at else 0), each[at:to]) + self.starts[self.dst[a + first]]
            wanted = src[first] * n + self.dst[second]
            whole = np.minimum(np.searchsorted(known, wanted), len(known) - 1)
            limit = self.length[a + whole]
            good = (known[whole] == wanted) & (self.length[a + first] < limit) & (self.length[second] < limit)
            out += np.bincount(whole[good], minlength=len(out))
            at = to
        return self.ids[src], self.rank[a:b], self.ids[self.dst[a:b]], out


    def kept(self, low: int, high: int, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(src, rank, dst) of the first ``d`` of ``counted`` of each node by (detours, rank), with their new ranks."""
        src, rank, dst, ways = self.counted(low, high)
        order = np.lexsort((rank, ways, src))
        new = np.arange(len(src)) - np.searchsorted(src, src)  # in the order of nodes before and after
        first = new < d
        return src[first], new[first].astype(np.int32), dst[order[first]]


def detours(edges: DataFrame, by: str, parts: int, keep: int | None = None) -> DataFrame | None:
    """(src, rank, dst, detours) for edges whose number the caller bounds, without null or NaN; None where an edge stands twice.

    With ``keep`` (src, rank, dst) of so many edges of each node, by (detours, rank), come instead: a list is cut in the task that counts it.
    """
    spark = edges.sparkSession
    table = edges.select("src", "dst", "rank", *(["dist"] if by == "dist" else [])).toArrow()
    columns = {c: table.column(c).to_numpy() for c in table.column_names}
    graph = Edges(columns["src"], columns["dst"], columns["rank"], columns[by])
    if not graph.once:
        return None
    types = {f.name: f.dataType for f in edges.schema}
    if keep is None:
        schema = T.StructType([*(T.StructField(c, types[c]) for c in ("src", "rank", "dst")), T.StructField("detours", T.LongType())])
    else:
        schema = T.StructType([T.StructField(c, T.IntegerType() if c == "rank" else types[c]) for c in ("src", "rank", "dst")])
    step, shared = max(1, -(-len(graph.ids) // (4 * parts))), spark.sparkContext.broadcast(graph)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = shared.value
        for batch in batches:
            for low in batch.column(0).to_pylist():
                high = min(low + step, len(graph.ids))
                cells = graph.counted(low, high) if keep is None else graph.kept(low, high, keep)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cells], names=schema.names)

    return spark.range(0, len(graph.ids), step, parts).mapInArrow(run, schema)
