"""Exact search by blocks: matrix products leave out what is surely too far, the rest is measured as the column expressions measure it.

A product of matrices gives each distance up to a bound on its rounding. Only pairs that may be among the k nearest by that bound are measured
again, component after component in double precision, so distances, order and ties are those of ``functions.distance`` to the last bit.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from neargraph.functions.distance import METRICS
from neargraph.runtime import prepare

#: Rows of a block of queries (at most) and of vectors: a matrix of 32 MB.
QUERY_BLOCK, VECTOR_BLOCK = 1024, 4096
#: Entries of a matrix of bounds that are made and looked through together: 2 MB in single precision, so that a core's cache holds them.
TILE = 1 << 19
#: Entries that a task holds for all its blocks of queries together, and pairs that are measured at once.
HELD, MEASURED = 1 << 22, 1 << 17
#: Squared lengths up to which single precision bounds distances, and shortest query of an inner product that it scales to length 1.
LONGEST, SHORTEST = 1e30, 1e-100
#: Pairs to measure, for each neighbour asked, beyond which single precision is given up for a block of queries.
FEW = 32
#: New pairs of one query, for each neighbour asked, up to which a block's pairs are merged as a matrix.
WIDER = 4

_CELLS = ("ids", "vecs", "null", "bytes")
HITS = "qid long, nid long, dist double"


def blocks(rows: DataFrame, size: int, prefix: str) -> DataFrame:
    """(id, vec) -> one row for each ``size`` rows at most: ids and vectors as bytes, and which vectors are null."""
    prepare(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, size):
                part = batch.slice(at, size)
                col = part.column(1)
                null = col.is_null().to_numpy(zero_copy_only=False)
                lengths = np.unique(col.value_lengths().drop_null().to_numpy(zero_copy_only=False))
                if len(lengths) > 1:
                    raise ValueError("vectors differ in length")
                x = np.full((len(null), int(lengths[0]) if len(lengths) else 0), np.nan)
                x[~null] = col.flatten().to_numpy(zero_copy_only=False).reshape(int((~null).sum()), -1) if len(lengths) else 0
                cells = (part.column(0).to_numpy(zero_copy_only=False).astype("<i8"), x.astype("<f4" if col.type.value_type == pa.float32() else "<f8"), null)
                yield pa.RecordBatch.from_arrays([*(pa.array([c.tobytes()], pa.binary()) for c in cells), pa.array([cells[1].itemsize], pa.int32())], names=[f"{prefix}_{c}" for c in _CELLS])

    return rows.mapInArrow(run, f"{prefix}_ids binary, {prefix}_vecs binary, {prefix}_null binary, {prefix}_bytes int")


class Side:
    """A block as a kernel needs it: ids, components by dimension, norms added up in order, and which vectors are null."""

    def __init__(self, ids: bytes, vecs: bytes, null: bytes, width: int, metric: str) -> None:
        self.ids, self.null = np.frombuffer(ids, "<i8"), np.frombuffer(null, bool)
        self.x = np.frombuffer(vecs, f"<f{width}").astype(np.float64).reshape(len(self.ids), -1)
        self.gone = np.zeros_like(self.null)
        if metric == "cosine":  # what is null has no length and is at 1 from all
            self.x[self.null] = 0.0
            self.null, self.gone = self.gone, self.null
        self.metric, self.columns = metric, np.ascontiguousarray(self.x.T)
        self.squares = np.zeros(len(self.ids))
        for c in self.columns:
            self.squares += c * c
        self.norms = np.sqrt(self.squares)
        self.plain = bool((self.squares <= LONGEST).all())
        self._factor: dict[bool, np.ndarray] = {}
        if metric == "cosine":  # at length 1 single precision bounds as well
            with np.errstate(invalid="ignore"):
                self.unit = np.divide(self.x, self.norms[:, None], out=np.zeros_like(self.x), where=self.norms[:, None] != 0).astype(np.float32)

    def factor(self, asked: bool) -> np.ndarray:
        """Rows in single precision, as queries or as vectors: their products are lower bounds (``_coarse``), lengths and slack included."""
        if asked not in self._factor:
            n = self.x.shape[1]
            out = np.ones((len(self.ids), n + 2), np.float32)
            slack, least = _slack(n, np.float32), (n + 8) * 1e-37  # what underflow may take
            if self.metric == "ip":
                out[:, :n] = self.x / -self.norms[:, None] if asked else self.x
                out[:, n], out[:, n + 1] = (0, 1) if asked else (1, -(slack * self.norms + least))
            else:
                out[:, :n] = -2 * self.x if asked else self.x
                out[:, n if asked else n + 1] = self.squares * (1 - slack) - least
            self._factor[asked] = out
        return self._factor[asked]

    def as_wide_as(self, other: Side) -> Side:
        """A block of null vectors alone has no width of its own."""
        if self.x.shape[1] == other.x.shape[1] or not other.x.shape[1]:
            return self
        if self.x.shape[1]:
            raise ValueError("vectors differ in length")
        gaps = np.full((len(self.ids), other.x.shape[1]), np.nan)
        return Side(self.ids.tobytes(), gaps.tobytes(), np.ones(len(self.ids), bool).tobytes(), 8, self.metric)


def measured(q: Side, v: Side, r: np.ndarray, c: np.ndarray, metric: str) -> np.ndarray:
    """Distances of the pairs (q[r], v[c]), summed in the order of the components."""
    out = np.empty(len(r))
    for at in range(0, len(r), MEASURED):
        a, b = r[at : at + MEASURED], c[at : at + MEASURED]
        s = np.zeros(len(a))
        for y, x in zip(q.columns, v.columns, strict=True):
            if metric in ("l2", "sql2"):
                d = x[b] - y[a]
                s += d * d
            else:
                s += x[b] * y[a]
        if metric == "l2":
            s = np.sqrt(s)
        elif metric == "ip":
            s = -s
        elif metric == "cosine":
            size = np.where(v.gone[b] | q.gone[a], 0.0, v.norms[b] * q.norms[a])
            s = 1.0 - np.divide(s, size, out=np.where(size == 0, 0.0, np.nan), where=size > 0)
        out[at : at + MEASURED] = s
    return out


def _slack(dim: int, dtype: type) -> float:
    return 8 * (dim + 8) * float(np.finfo(dtype).eps)


def _coarse(q: Side, v: Side, metric: str, rows: slice) -> tuple[np.ndarray, np.ndarray]:
    """``_bounds`` of finite vectors by one product in single precision; inner products are those of queries of length 1."""
    slack, squares = _slack(q.x.shape[1], np.float32), q.squares[rows]
    room = 2 * slack * (v.norms.max() if metric == "ip" else squares + v.squares.max()) + (q.x.shape[1] + 8) * 4e-37
    return q.factor(True)[rows] @ v.factor(False).T, np.broadcast_to(room, squares.shape)


def _bounds(q: Side, v: Side, metric: str, rows: slice) -> tuple[np.ndarray, np.ndarray]:
    """Lower bounds of all distances (of their squares, if Euclidean) of some queries, NaN as infinity; and how far they may lie below, for each query."""
    slack = _slack(q.x.shape[1], np.float32 if metric == "cosine" else float)
    near = q.unit[rows] @ v.unit.T if metric == "cosine" else q.x[rows] @ v.x.T
    if metric == "cosine":
        np.subtract(np.float32(1 - slack), near, out=near)
        room = np.full(len(near), 2 * slack)
        near[q.gone[rows]] = 1 - slack
        near[:, v.gone] = 1 - slack
    else:
        a, b = q.squares[rows] * slack, v.squares * slack
        if metric == "ip":
            near *= -1
        else:
            near *= -2
            near += q.squares[rows, None]
            near += v.squares
        near -= a[:, None]
        near -= b
        top = b[np.isfinite(b)]
        room = 2 * (a + (top.max() if len(top) else 0.0))
    if np.isnan(near.sum()):
        near[np.isnan(near)] = np.inf
    return near, room


def _true_places(found: np.ndarray) -> np.ndarray:
    """``flatnonzero`` of a matrix with few true entries: eight at a time, and singly only where one of them is true."""
    flat = found.ravel()
    whole = len(flat) // 8 * 8
    some = np.flatnonzero(flat[:whole].view(np.uint64))
    of, place = np.nonzero(flat[:whole].reshape(-1, 8)[some])
    return np.concatenate([some[of] * 8 + place, whole + np.flatnonzero(flat[whole:])])


class Nearest:
    """The k nearest so far to each query of a block, by (distance, id); NaN is farthest."""

    def __init__(self, q: Side, k: int, metric: str, exclude_self: bool) -> None:
        self.q, self.k, self.metric, self.exclude_self = q, k, metric, exclude_self
        self.coarse = metric != "cosine" and (metric != "ip" or bool((q.norms >= SHORTEST).all()))
        self.row, self.id, self.dist, self.null = (np.zeros(0, t) for t in (np.int64, np.int64, np.float64, bool))

    def cuts(self) -> np.ndarray:
        """What a bound must not exceed: the k-th distance, infinite where fewer are known."""
        last = np.full(len(self.q.ids), np.inf)
        ends = np.searchsorted(self.row, np.arange(len(last)), "right")
        full = np.diff(ends, prepend=0) >= self.k
        last[full] = self.dist[ends[full] - 1]
        last[np.isnan(last)] = np.inf
        return last * last * (1 + 1e-14) if self.metric == "l2" else last

    def _near(self, q: Side, v: Side, bounds: Callable) -> tuple[np.ndarray, np.ndarray]:
        """Places (row, col) of the pairs that may be among the k nearest by their bounds, some rows at a time."""
        n, cut = len(q.ids), self.cuts()
        if bounds is _coarse and self.metric == "ip":
            cut = cut / q.norms
        own = np.zeros((2, 0), np.int64)
        if self.exclude_self:
            order = np.argsort(v.ids, kind="stable")
            first, last = (np.searchsorted(v.ids[order], q.ids, side) for side in ("left", "right"))
            place = np.arange((last - first).sum()) - np.repeat(np.cumsum(last - first) - last, last - first)
            own = np.stack([np.repeat(np.arange(n), last - first), order[place]])
        step = max(1, TILE // len(v.ids))
        found = [self._near_rows(q, v, bounds, cut[at : at + step], slice(at, at + step), own[:, slice(*np.searchsorted(own[0], (at, at + step)))]) for at in range(0, n, step)]
        return np.concatenate([row for row, _ in found]), np.concatenate([col for _, col in found])

    def _near_rows(self, q: Side, v: Side, bounds: Callable, cut: np.ndarray, rows: slice, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        k, (near, room) = self.k, bounds(q, v, self.metric, rows)
        own = own[0] - rows.start, own[1]
        near[own] = np.inf

        def places() -> np.ndarray:
            found = near <= np.nextafter(cut.astype(near.dtype), near.dtype.type(np.inf))[:, None]
            found[own] = False
            return _true_places(found)

        at = None if np.isinf(cut).any() else places()
        if len(v.ids) > k and (at is None or len(at) > 8 * k * len(cut)):
            cut, at = np.fmin(cut, np.partition(near, k - 1, axis=1)[:, k - 1] + room), None
        if at is None:
            at = places()
        return rows.start + at // len(v.ids), at % len(v.ids)

    def _merged(self, row: np.ndarray, dist: np.ndarray, ids: np.ndarray) -> bool:
        """Puts a few new pairs, in order of their rows, into lists that are all full, a matrix sorted line by line; False where that does not serve."""
        n, k = len(self.q.ids), self.k
        if len(self.row) != n * k or self.null.any() or not np.isfinite(self.dist[k - 1 :: k]).all():
            return False
        better = dist <= self.dist[k - 1 :: k][row]  # NaN is farthest
        row, dist, ids = row[better], dist[better], ids[better]
        each = np.bincount(row, minlength=n)
        if (more := int(each.max())) > WIDER * k or not np.isfinite(dist).all():
            return False
        own_dist, own_ids = np.full((n, k + more), np.inf), np.zeros((n, k + more), np.int64)
        own_dist[:, :k], own_ids[:, :k] = self.dist.reshape(n, k), self.id.reshape(n, k)
        place = k + np.arange(len(row)) - np.repeat(np.cumsum(each) - each, each)
        own_dist[row, place], own_ids[row, place] = dist, ids
        order = np.argsort(own_dist, axis=1)
        near = np.take_along_axis(own_dist, order, axis=1)
        tied = np.flatnonzero(((near[:, 1:] == near[:, :-1]) & np.isfinite(near[:, 1:])).any(axis=1))
        order[tied] = np.lexsort((own_ids[tied], own_dist[tied]), axis=1)
        order = order[:, :k]
        self.dist, self.id = (np.take_along_axis(a, order, axis=1).ravel() for a in (own_dist, own_ids))
        return True

    def add(self, v: Side) -> None:
        k, q = self.k, self.q
        if not len(q.ids) or not len(v.ids) or k < 1:
            return
        q, v = q.as_wide_as(v), v.as_wide_as(q)
        with np.errstate(invalid="ignore", over="ignore"):
            coarse = self.coarse and q.plain and v.plain
            row, col = self._near(q, v, _coarse if coarse else _bounds)
            if coarse and len(row) > FEW * k * len(q.ids):  # lengths or offsets that single precision cannot tell apart
                self.coarse = False
                row, col = self._near(q, v, _bounds)
            dist = measured(q, v, row, col, self.metric)
        if not len(row) or not (q.null.any() or v.null.any()) and self._merged(row, dist, v.ids[col]):
            return
        row, dist, ids = np.concatenate([self.row, row]), np.concatenate([self.dist, dist]), np.concatenate([self.id, v.ids[col]])
        null = np.concatenate([self.null, q.null[row[len(self.row) :]] | v.null[col]])
        order = np.lexsort((ids, null, dist, row) if null.any() else (ids, dist, row))
        row, dist, ids, null = row[order], dist[order], ids[order], null[order]
        first = np.arange(len(row)) - np.searchsorted(row, row) < k
        self.row, self.dist, self.id, self.null = row[first], dist[first], ids[first], null[first]

    def batch(self) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(self.q.ids[self.row]), pa.array(self.id), pa.array(self.dist, mask=self.null)], names=["qid", "nid", "dist"])


def nearest(pairs: DataFrame, k: int, metric: str, exclude_self: bool = False) -> DataFrame:
    """Pairs of blocks (q_*, v_*) -> (qid, nid, dist) of the k nearest; a block of queries that is met again in a task goes on where it was."""
    if metric not in METRICS:
        raise ValueError(f"unknown metric {metric}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, Nearest] = {}
        side: tuple[bytes, Side] | None = None
        for batch in batches:
            for i in range(batch.num_rows):
                asked, rows = ([batch.column(c)[i].as_py() for c in range(at, at + 4)] for at in (0, 4))
                key = asked[0] + asked[1]
                if key not in held:
                    if sum(len(n.row) for n in held.values()) > HELD:
                        yield from (n.batch() for n in held.values())
                        held.clear()
                    held[key] = Nearest(Side(*asked, metric), k, metric, exclude_self)
                if side is None or side[0] != rows[0] + rows[1]:
                    side = rows[0] + rows[1], Side(*rows, metric)
                held[key].add(side[1])
        yield from (n.batch() for n in held.values())

    return pairs.select(*(f"{p}_{c}" for p in "qv" for c in _CELLS)).mapInArrow(run, HITS)


class Sent:
    """Blocks of vectors that are sent to every worker: the first task there makes them ready, later ones find them so."""

    def __init__(self, rows: list[tuple], metric: str) -> None:
        self.rows, self.metric, self._sides = rows, metric, []

    def sides(self) -> list[Side]:
        if self.rows:
            self._sides, self.rows = [Side(*row, self.metric) for row in self.rows], []
        return self._sides


def nearest_sent(queries: DataFrame, vecs: DataFrame, k: int, metric: str, exclude_self: bool = False) -> DataFrame:
    """``nearest`` of blocks of queries (q_*) to blocks of vectors (v_*) that are sent to every worker once, not with every block of queries."""
    if metric not in METRICS:
        raise ValueError(f"unknown metric {metric}")
    shared = vecs.sparkSession.sparkContext.broadcast(Sent([tuple(map(bytes, row[:3])) + (row[3],) for row in vecs.collect()], metric))  # bounded by the caller

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                near = Nearest(Side(*(batch.column(c)[i].as_py() for c in range(4)), metric), k, metric, exclude_self)
                for side in shared.value.sides():
                    near.add(side)
                yield near.batch()

    return queries.mapInArrow(run, HITS)


def pair_distances(vecs: DataFrame, n: int, metric: str) -> Callable[[DataFrame], DataFrame] | None:
    """(a, b) -> (a, b, dist), the vectors of ids 0..n-1 sent to every task; None if ids repeat."""
    ids, x = [], []
    for row in blocks(vecs, VECTOR_BLOCK, "v").collect():  # bounded by the caller
        ids.append(np.frombuffer(row.v_ids, "<i8")), x.append(np.frombuffer(row.v_vecs, f"<f{row.v_bytes}").reshape(len(ids[-1]), -1))
    at, found = np.concatenate(ids), np.concatenate(x)
    if len(np.unique(at)) != n:
        return None
    shared = vecs.sparkSession.sparkContext.broadcast(found[np.argsort(at)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = shared.value
        side = Side(np.arange(len(x)).tobytes(), x.tobytes(), bytes(len(x)), x.itemsize, metric)
        for batch in batches:
            a, b = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            with np.errstate(invalid="ignore", over="ignore"):
                dist = measured(side, side, b, a, metric)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(dist)], names=["a", "b", "dist"])

    return lambda pairs: pairs.select("a", "b").mapInArrow(run, "a long, b long, dist double")
