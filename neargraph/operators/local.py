"""Shard-local kernels in numpy: base graphs, reordering, reverse edges, reachability and both search modes.

Nodes are numbered 0..N-1 inside a shard, so a graph of fixed degree is a dense matrix; variable degrees are padded with -1.
"""

from __future__ import annotations

from bisect import insort
from dataclasses import dataclass, field
from heapq import heappop, heappush

import numpy as np

from neargraph.operators import exact
from neargraph.params import SEED_FACTOR, SEED_MODULUS, SearchParams, choose_merge, table_size


# ---------------------------------------------------------------- distances
def prepared(x: np.ndarray, metric: str, dtype: str = "fp32") -> np.ndarray:
    """Vectors as a search holds them: unit length for cosine, rounded to half precision on demand, computed in float64."""
    x = np.asarray(x, np.float32)
    if dtype == "fp16":
        x = x.astype(np.float16)
    x = x.astype(np.float64)
    if metric == "cosine":
        norm = np.linalg.norm(x, axis=-1, keepdims=True)
        x = np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)
    return x


def block_distances(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """All distances between prepared queries (Q, n) and vectors (N, n)."""
    dot = q @ x.T
    if metric == "cosine":
        return 1.0 - dot
    if metric == "ip":
        return -dot
    sq = np.maximum((q * q).sum(1)[:, None] + (x * x).sum(1)[None, :] - 2 * dot, 0.0)
    return sq if metric == "sql2" else np.sqrt(sq)


def gathered_distances(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Distances between each query (Q, n) and its own vectors (Q, C, n)."""
    if metric in ("cosine", "ip"):
        dot = np.einsum("qn,qcn->qc", q, x)
        return 1.0 - dot if metric == "cosine" else -dot
    diff = x - q[:, None, :]
    sq = np.einsum("qcn,qcn->qc", diff, diff)
    return sq if metric == "sql2" else np.sqrt(sq)


def smallest(dist: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and values of the k smallest of each row, ties by position."""
    n = dist.shape[1]
    k = min(k, n)
    if n > 4 * k + 64:
        cut = np.partition(dist, k - 1, axis=1)[:, k - 1 : k]
        rows, cols = np.nonzero(dist <= cut)
        order = np.lexsort((cols, dist[rows, cols], rows))
        first = np.searchsorted(rows[order], np.arange(len(dist)))
        pick = cols[order][first[:, None] + np.arange(k)]
    else:
        pick = np.argsort(dist, axis=1, kind="stable")[:, :k]
    return pick, np.take_along_axis(dist, pick, axis=1)


def exact_knn(x: np.ndarray, q: np.ndarray, k: int, metric: str = "l2", *, own: np.ndarray | None = None, block: int = exact.QUERY_BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """The k nearest of prepared vectors to each prepared query, ties by position; ``own`` gives the node that is the query itself and left out.

    Blocks go through ``exact.Nearest``: bounds in single precision leave out what is too far, the rest is measured in double precision.
    """
    k = min(k, len(x) - (own is not None))
    ids, dists = np.empty((len(q), k), np.int64), np.empty((len(q), k))
    sides = [_side(np.arange(at, min(at + exact.VECTOR_BLOCK, len(x))), x[at : at + exact.VECTOR_BLOCK], metric) for at in range(0, len(x), exact.VECTOR_BLOCK)]
    for at in range(0, len(q), block):
        part = slice(at, at + block)
        asked = q[part]
        near = exact.Nearest(_side(np.arange(at, at + len(asked)) if own is None else own[part], asked, metric), k, metric, own is not None)
        for side in sides:
            near.add(side)
        ids[part], dists[part] = near.id.reshape(-1, k), near.dist.reshape(-1, k)
    return ids, dists


def _side(ids: np.ndarray, x: np.ndarray, metric: str) -> exact.Side:
    return exact.Side(ids.astype("<i8").tobytes(), x.astype("<f8").tobytes(), bytes(len(x)), 8, metric)


# ---------------------------------------------------------------- base graph
def exact_graph(x: np.ndarray, degree: int, metric: str = "l2") -> tuple[np.ndarray, np.ndarray]:
    """Exact lists of neighbours, nearest first."""
    if not 0 < degree < len(x):
        raise ValueError("the degree of a base graph lies between 1 and N - 1")
    return exact_knn(x, x, degree, metric, own=np.arange(len(x)))


def _by_owner(owner: np.ndarray, dist: np.ndarray, n: int) -> np.ndarray:
    """``lexsort((dist, owner))`` by one sort of whole numbers that hold owner, rank of the distance and place."""
    size = len(dist)
    if n * size * size >= 1 << 62:
        return np.lexsort((dist, owner))
    order = np.argsort(dist)
    near = dist[order]
    rank = np.empty(size, np.int64)
    rank[order] = np.cumsum(np.r_[False, near[1:] != near[:-1]])
    return np.sort((owner.astype(np.int64) * size + rank) * size + np.arange(size)) % size


def _best_lists(owner, ids, dist, fresh, n, degree):
    """The ``degree`` nearest distinct entries of each owner; every owner has that many."""
    order = np.argsort((owner * (int(ids.max()) + 1) + ids) * 4 + fresh + 1)  # of equal entries the one that is not new
    owner, ids, dist, fresh = owner[order], ids[order], dist[order], fresh[order]
    keep = np.r_[True, (owner[1:] != owner[:-1]) | (ids[1:] != ids[:-1])]
    owner, ids, dist, fresh = owner[keep], ids[keep], dist[keep], fresh[keep]
    order = _by_owner(owner, dist, n)  # by id already
    pick = order[np.searchsorted(owner, np.arange(n))[:, None] + np.arange(degree)]
    return ids[pick], dist[pick], fresh[pick]


def _distinct(lists: np.ndarray) -> np.ndarray:
    """Each row's ids once, -1 last."""
    out = -np.sort(-lists, axis=1)
    out[:, 1:][out[:, 1:] == out[:, :-1]] = -1
    return -np.sort(-out, axis=1)


def _product_sides(x: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """Rows whose products are all distances ('sql2' for Euclidean), and a last one that is far from all."""
    n, dim = x.shape
    left, right = np.zeros((n + 1, dim + 2)), np.zeros((n + 1, dim + 2))
    left[:, dim + 1] = right[:, dim] = 1.0
    if metric == "sql2":
        right[:n, :dim] = x - x.mean(axis=0)
        left[:n, :dim] = -2 * right[:n, :dim]
        left[:n, dim] = right[:n, dim + 1] = (right[:n, :dim] ** 2).sum(axis=1)
    else:
        right[:n, :dim], left[:n, :dim], left[:n, dim] = x, -x, float(metric == "cosine")
    left[n, dim] = right[n, dim + 1] = FAR
    return left, right


#: A distance beyond all others.
FAR = 1e300
#: Pairs that descent holds before it merges them into the lists, for each list entry and at least; entries that a merge sorts at once.
HELD_PAIRS, LEAST_PAIRS, SORTED = 1, 1 << 20, 1 << 20


def descent_graph(x: np.ndarray, degree: int, metric: str = "l2", *, rho: float = 0.5, delta: float = 0.001, max_iter: int = 12, seed: int = 1) -> tuple[np.ndarray, np.ndarray, int]:
    """Approximate lists by neighbour descent: random lists, then neighbours of neighbours until few entries change. Also the distances computed."""
    n = len(x)
    if not 0 < degree < n:
        raise ValueError("the degree of a base graph lies between 1 and N - 1")
    rng = np.random.default_rng(seed)
    if degree > n // 2:
        ids = np.stack([(i + 1 + rng.permutation(n - 1)[:degree]) % n for i in range(n)])
    else:
        ids = (np.arange(n)[:, None] + 1 + np.sort(rng.integers(0, n - 1 - degree, (n, degree)), axis=1) + np.arange(degree)) % n
    compared = "sql2" if metric == "l2" else metric
    dist = np.concatenate([gathered_distances(x[i : i + 512], x[ids[i : i + 512]], compared) for i in range(0, n, 512)])
    sides = _product_sides(x, compared)
    fresh = np.ones((n, degree), bool)
    computed, most = n * degree, max(1, int(np.ceil(rho * degree)))
    for _ in range(max_iter):
        lot = rng.random((n, degree))
        new = np.where(fresh, lot, np.inf)
        place = np.argsort(new, axis=1)[:, :most]
        chosen = np.take_along_axis(fresh, place, axis=1)
        new_ids = np.where(chosen, np.take_along_axis(ids, place, axis=1), -1)
        old = np.where(fresh, np.inf, lot)
        place_old = np.argsort(old, axis=1)[:, :most]
        old_ids = np.where(np.take_along_axis(~fresh, place_old, axis=1), np.take_along_axis(ids, place_old, axis=1), -1)
        picked = np.zeros_like(fresh)
        np.put_along_axis(picked, place, chosen, axis=1)
        fresh &= ~picked
        del lot, new, old, place, place_old, chosen, picked

        def reverse(lists):
            src, col = np.nonzero(lists >= 0)
            dst = lists[src, col]
            order = np.lexsort((rng.random(len(dst)), dst))
            rank = np.arange(len(dst)) - np.searchsorted(dst[order], dst[order])
            keep = rank < most
            out = np.full((n, most), -1, np.int64)
            out[dst[order][keep], rank[keep]] = src[order][keep]
            return out

        a, b = _distinct(np.concatenate([new_ids, reverse(new_ids)], axis=1)), _distinct(np.concatenate([old_ids, reverse(old_ids)], axis=1))
        na, nb = (a >= 0).sum(axis=1), (b >= 0).sum(axis=1)
        order = np.lexsort((nb, na))  # nodes with as many neighbours stand together
        order = order[np.searchsorted(na[order], 1) :]
        flags, room = fresh.astype(np.int8) - 1, max(LEAST_PAIRS, HELD_PAIRS * n * degree)
        worst = np.r_[dist.max(axis=1), -np.inf]  # -1 is the last row and has no distance
        add, held = [[], [], []], 0
        for at in range(0, len(order), 64):
            nodes = order[at : at + 64]
            u, w = a[nodes, : na[nodes].max()], b[nodes, : nb[nodes].max()]
            left = sides[0][u]
            computed += int((na[nodes] * (na[nodes] - 1 + nb[nodes])).sum())
            same, other = (np.matmul(left, sides[1][v].transpose(0, 2, 1)) for v in (u, w))
            ends = np.arange(u.shape[1])
            same[:, ends, ends] = np.inf
            # pairs of two new ones are met from both sides, an old one is met only here
            for d, s, t, limit in ((same, u[:, :, None], u[:, None, :], worst[u][:, :, None]), (other, u[:, :, None], w[:, None, :], worst[u][:, :, None]), (other, w[:, None, :], u[:, :, None], worst[w][:, None, :])):
                place = np.flatnonzero(d < limit)
                s, t = (np.broadcast_to(v, d.shape)[np.unravel_index(place, d.shape)].astype(np.int32) for v in (s, t))
                apart = s != t
                add[0].append(s[apart]), add[1].append(t[apart]), add[2].append(d.ravel()[place[apart]])
                held += len(add[0][-1])
            if held > room or at + 64 >= len(order):  # in parts, as the first round would bring most pairs of the lists together
                owner, met, d = (np.concatenate(v) for v in add)
                add, step = [[], [], []], -(-n // -(-(n * degree + held) // SORTED))
                for low in range(0, n, step):
                    part, size = slice(low, low + step), min(step, n - low)
                    here = np.flatnonzero((owner >= low) & (owner < low + step))
                    known = (np.repeat(np.arange(size), degree), ids[part].ravel(), dist[part].ravel(), flags[part].ravel())
                    ids[part], dist[part], flags[part] = _best_lists(*(np.r_[old, new] for old, new in zip(known, (owner[here] - low, met[here], d[here], np.ones(len(here), np.int8)), strict=True)), size, degree)
                worst, held = np.r_[dist.max(axis=1), -np.inf], 0
        came = flags == 1
        fresh = (flags == 0) | came
        changed = int(came.sum())
        if changed < delta * n * degree:
            break
    # distances of the lists as the metric defines them, nearest first, ties by id
    dist = np.concatenate([gathered_distances(x[i : i + 512], x[ids[i : i + 512]], metric) for i in range(0, n, 512)])
    order = np.lexsort((ids, dist), axis=1)
    return np.take_along_axis(ids, order, axis=1), np.take_along_axis(dist, order, axis=1), computed


#: Nodes or queries whose exact answer an audit knows.
AUDITED = 512


def surely(shares: np.ndarray, least: float) -> bool:
    """Whether the mean of sampled shares is ``least``, twice its standard error taken off."""
    return bool(shares.mean() - 2 * shares.std() / np.sqrt(len(shares)) >= least)


def sure_descent(x: np.ndarray, degree: int, metric: str = "l2", *, least: float = 0.95, seed: int = 1) -> tuple[np.ndarray, np.ndarray, int]:
    """``descent_graph`` with as long lists as it takes: they are doubled until a sample of nodes has ``least`` of its exact neighbours, then cut.

    Lists twice as long miss about the square of the share that is missed; a doubling that would still miss too much is left out.
    Vectors without near structure need it: a node's neighbours of neighbours hold few of its own there.
    """
    n, width, computed = len(x), degree, 0
    sample = np.sort(np.random.default_rng(seed).choice(n, min(n, AUDITED), replace=False))
    truth = exact_knn(x, x[sample], degree, metric, own=sample)[0]
    while True:
        ids, dist, own = descent_graph(x, width, metric, seed=seed)
        ids, dist, computed = ids[:, :degree], dist[:, :degree], computed + own
        shares = (ids[sample][:, :, None] == truth[:, None, :]).any(axis=1).mean(axis=1)
        if width == n - 1 or surely(shares, least):
            return ids, dist, computed
        width = min((4 if (1 - shares.mean()) ** 2 > 1 - least else 2) * width, n - 1)


# ---------------------------------------------------------------- optimisation
def detour_counts(ids: np.ndarray, weight: str = "rank", *, dist: np.ndarray | None = None, x: np.ndarray | None = None, metric: str = "l2") -> np.ndarray:
    """For each list position, the two-edge ways round the edge whose longer edge is shorter than it.

    'rank' takes list positions for lengths and needs neither vectors nor distances; 'distance' takes the distances kept with
    the lists, or, without them, computes them from the vectors.
    """
    n, degree = ids.shape
    out = np.zeros((n, degree), np.int64)
    place = np.full(n, degree, np.int64)
    z = np.arange(degree)[:, None]
    p = np.arange(degree)[None, :]
    for node in range(n):
        own = ids[node]
        place[own] = np.arange(degree)
        y = place[ids[own]]
        if weight == "rank":
            good = (y < degree) & (z < y) & (p < y)
        else:
            safe = np.minimum(y, degree - 1)
            if dist is not None:
                first, second = dist[node][:, None], dist[own]
                whole = dist[node][safe]
            else:
                first = gathered_distances(x[node][None], x[own][None], metric)[0][:, None]
                second = gathered_distances(x[own], x[ids[own]], metric)
                whole = first[:, 0][safe]
            good = (y < degree) & (np.maximum(first, second) < whole)
        out[node] = np.bincount(y[good], minlength=degree)[:degree]
        place[own] = degree
    return out


def prune(ids: np.ndarray, counts: np.ndarray | None, d: int) -> np.ndarray:
    """The first d of each list ordered by (detours, rank); without counts, of the list as it is."""
    if counts is None:
        return ids[:, :d]
    order = np.argsort(counts, axis=1, kind="stable")[:, :d]
    return np.take_along_axis(ids, order, axis=1)


def reversed_lists(pruned: np.ndarray, d: int) -> np.ndarray:
    """Who points at a node, by the position the edge has at its source and then by source; at most d, padded with -1."""
    n, width = pruned.shape
    src = np.repeat(np.arange(n), width)
    rank = np.tile(np.arange(width), n)
    dst = pruned.ravel()
    good = dst >= 0
    src, rank, dst = src[good], rank[good], dst[good]
    order = np.lexsort((src, rank, dst))
    src, dst = src[order], dst[order]
    place = np.arange(len(dst)) - np.searchsorted(dst, dst)
    keep = place < d
    out = np.full((n, d), -1, np.int64)
    out[dst[keep], place[keep]] = src[keep]
    return out


def interleave(pruned: np.ndarray, back: np.ndarray, d: int) -> np.ndarray:
    """Half from the pruned list, half from the reversed one, in turns, a pruned entry first; gaps are filled from the pruned list."""
    forward, rest = -(-d // 2), d // 2
    out = np.empty((len(pruned), d), np.int64)
    for i, (own, other) in enumerate(zip(pruned.tolist(), back.tolist(), strict=True)):
        head = own[:forward]
        taken = set(head)
        tail = [v for v in other if v >= 0 and v not in taken][:rest]
        taken.update(tail)
        mixed = []
        for j in range(forward):
            mixed.append(head[j])
            if j < len(tail):
                mixed.append(tail[j])
        mixed += [v for v in own[forward:] if v not in taken]
        out[i] = mixed[:d]
    return out


def uniform_graph(ids: np.ndarray, d: int, *, reorder: str = "rank", reverse: bool = True, dist=None, x=None, metric: str = "l2") -> np.ndarray:
    """Graph of fixed out-degree d from base lists. ``reorder``: 'rank', 'distance' (from vectors), 'distance_table', 'none'."""
    if reorder == "none":
        counts = None
    elif reorder == "rank":
        counts = detour_counts(ids)
    else:
        counts = detour_counts(ids, "distance", dist=dist if reorder == "distance_table" else None, x=x, metric=metric)
    pruned = prune(ids, counts, d)
    return interleave(pruned, reversed_lists(pruned, d), d) if reverse else pruned


# ---------------------------------------------------------------- reachability
def two_hop_counts(adj: np.ndarray) -> np.ndarray:
    """Distinct nodes within two steps of each node, itself left out."""
    out = np.zeros(len(adj), np.int64)
    for i, own in enumerate(adj):
        own = own[own >= 0]
        near = np.unique(np.concatenate([own, adj[own].ravel()]))
        out[i] = len(near) - int(near[:1].tolist() == [-1]) - int((near == i).any())
    return out


def strong_components(adj: np.ndarray) -> np.ndarray:
    """Component labels (smallest member) by an iterative depth-first walk."""
    n = len(adj)
    lists = [[v for v in row if v >= 0] for row in adj.tolist()]
    index, low, on, label = [-1] * n, [0] * n, [False] * n, [-1] * n
    stack: list[int] = []
    time = 0
    for root in range(n):
        if index[root] >= 0:
            continue
        work = [(root, 0)]
        while work:
            node, at = work.pop()
            if at == 0:
                index[node] = low[node] = time
                time += 1
                stack.append(node)
                on[node] = True
            elif at > 0:
                low[node] = min(low[node], low[lists[node][at - 1]])
            went = False
            for j in range(at, len(lists[node])):
                nxt = lists[node][j]
                if index[nxt] < 0:
                    work += [(node, j + 1), (nxt, 0)]
                    went = True
                    break
                if on[nxt]:
                    low[node] = min(low[node], index[nxt])
            if went:
                continue
            if low[node] == index[node]:
                members = []
                while True:
                    v = stack.pop()
                    on[v] = False
                    members.append(v)
                    if v == node:
                        break
                least = min(members)
                for v in members:
                    label[v] = least
    return np.array(label)


def weak_components(adj: np.ndarray) -> np.ndarray:
    n = len(adj)
    src, col = np.nonzero(adj >= 0)
    dst = adj[src, col]
    label = np.arange(n)
    while True:
        low = np.minimum(label[src], label[dst])
        new = label.copy()
        np.minimum.at(new, src, low)
        np.minimum.at(new, dst, low)
        new = np.minimum(new, new[new])
        if np.array_equal(new, label):
            return label
        label = new


def fresh_distances(q: np.ndarray, x: np.ndarray, rows: np.ndarray, cand: np.ndarray, fresh: np.ndarray, metric: str) -> np.ndarray:
    """Distances of the candidates (rows, C) that are fresh; the others are infinitely far."""
    out = np.full(cand.shape, np.inf)
    r, c = np.nonzero(fresh)
    out[r, c] = gathered_distances(q[rows[r]], x[cand[r, c]][:, None], metric)[:, 0]
    return out


# ---------------------------------------------------------------- visited sets
class VisitedSet:
    """Open-addressing tables of 2**bits slots, one for each query, probed in line; counts collisions, overflows and resets.

    A table that is full says "not seen": a distance may be computed again, the result stays right.
    """

    def __init__(self, queries: int, bits: int) -> None:
        self.bits = bits
        self.table = np.full((queries, 1 << bits), -1, np.int64)
        self.collisions = np.zeros(queries, np.int64)
        self.overflows = np.zeros(queries, np.int64)
        self.resets = np.zeros(queries, np.int64)

    def insert(self, rows: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Registers ids, those of one row distinct; True where an id had not been seen."""
        mask = (1 << self.bits) - 1
        slot = (ids * 2654435761 >> 7) & mask
        new = np.zeros(len(rows), bool)
        todo = np.arange(len(rows))
        for _ in range(2 * mask + 2):
            r, s = rows[todo], slot[todo]
            at = self.table[r, s]
            empty = np.flatnonzero(at < 0)
            if len(empty):
                first = empty[np.unique(r[empty] * (mask + 1) + s[empty], return_index=True)[1]]  # of several for one slot, the first
                self.table[r[first], s[first]] = ids[todo[first]]
                new[todo[first]] = True
                at[first] = ids[todo[first]]
            todo, at = todo[at != ids[todo]], at[at != ids[todo]]
            if not len(todo):
                return new
            taken = todo[at >= 0]  # those that lost a slot just now look at it once more
            np.add.at(self.collisions, rows[taken], 1)
            slot[taken] = (slot[taken] + 1) & mask
        np.add.at(self.overflows, rows[todo], 1)
        new[todo] = True
        return new

    def reset(self, rows: np.ndarray, keep: np.ndarray) -> None:
        """Forgets everything but the given ids (padded with -1)."""
        self.table[rows] = -1
        self.resets[rows] += 1
        r, c = np.nonzero(keep >= 0)
        self.insert(rows[r], keep[r, c])


class SeenMap:
    """A full visited set as one flag for each node of the shard: takes the place of a table that would need more memory."""

    def __init__(self, queries: int, nodes: int) -> None:
        self.seen = np.zeros((queries, nodes), bool)
        self._stamp: np.ndarray | None = None
        self.collisions, self.overflows, self.resets = (np.zeros(queries, np.int64) for _ in range(3))

    def insert(self, rows: np.ndarray, ids: np.ndarray) -> np.ndarray:
        new = ~self.seen[rows, ids]
        self.seen[rows, ids] = True
        return new

    def first_time(self, cand: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Mask of candidates that are new, of equal ones in a row the first: each writes its number where it would go, the first one last."""
        if self._stamp is None:
            self._stamp = np.empty(self.seen.size, np.int32)
        fresh = (cand >= 0) & ~self.seen[rows[:, None], np.maximum(cand, 0)]
        r, c = np.nonzero(fresh)
        spot = rows[r] * self.seen.shape[1] + cand[r, c]
        number = np.arange(len(spot), dtype=np.int32)
        self._stamp[spot[::-1]] = number[::-1]
        again = self._stamp[spot] != number
        fresh[r[again], c[again]] = False
        self.seen.ravel()[spot] = True
        return fresh


def full_set(queries: int, nodes: int, slots: int) -> VisitedSet | SeenMap:
    """The smaller of a table of 8-byte slots and of a flag for each node; both answer alike."""
    return SeenMap(queries, nodes) if nodes <= 8 * slots else VisitedSet(queries, int(np.log2(slots)))


# ---------------------------------------------------------------- search
@dataclass
class Found:
    """Result of a search: ids (-1 where there are fewer than k), distances, and counters for each query."""

    ids: np.ndarray
    dist: np.ndarray
    n_dist: np.ndarray
    rounds: np.ndarray
    extra: dict[str, np.ndarray] = field(default_factory=dict)


def seed_nodes(qids: np.ndarray, count: int, seed: int, n: int) -> np.ndarray:
    j = np.arange(count)[None, :]
    t = (np.asarray(qids, np.int64)[:, None] * 1000003 + j * 7919 + seed * 104729 + 12345) % SEED_MODULUS
    return t * SEED_FACTOR % SEED_MODULUS % n


def _sorted_order(dist: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Order of each row by (distance, id), nodes that are not there (-1, at no finite distance) last."""
    order = np.argsort(dist, axis=1, kind="stable")
    ranked = np.take_along_axis(dist, order, 1)
    row, col = np.nonzero((ranked[:, 1:] == ranked[:, :-1]) & (ranked[:, 1:] < np.inf))
    if len(row) > dist.size // 8:  # many ties: sort these rows again
        tied = np.unique(row)
        order[tied] = np.lexsort((np.where(ids[tied] < 0, np.iinfo(np.int64).max, ids[tied]), dist[tied]), axis=1)
        return order
    quiet = 0 if len(row) else 2
    while quiet < 2:  # a few: neighbours change places, those at even and at odd places in turns, until none has to
        for side in (0, 1):
            r, c = row[col & 1 == side], col[col & 1 == side]
            first, second = order[r, c], order[r, c + 1]
            wrong = ids[r, first] > ids[r, second]
            order[r[wrong], c[wrong]], order[r[wrong], c[wrong] + 1] = second[wrong], first[wrong]
            quiet = 0 if wrong.any() else quiet + 1
    return order


def merge_top(ids, dist, flag, c_ids, c_dist, M, how="auto"):
    """Best M of a sorted list and new candidates. 'merge' leaves out candidates that are beyond the list's end and sorts the rest in;
    'partition' selects, then sorts."""
    if how == "auto":
        how = choose_merge(c_ids.shape[1])
    if how == "merge" and ids.shape[1] == M:
        near = (c_dist <= dist[:, -1:]) & (c_ids >= 0)
        width = max(1, int(near.sum(axis=1).max(initial=0)))
        if width < c_ids.shape[1]:
            place = np.argsort(~near, axis=1, kind="stable")[:, :width]
            c_ids, c_dist = np.take_along_axis(c_ids, place, 1), np.take_along_axis(c_dist, place, 1)
    all_ids, all_dist = np.concatenate([ids, c_ids], 1), np.concatenate([dist, c_dist], 1)
    all_flag = np.concatenate([flag, np.zeros(c_ids.shape, bool)], 1)
    if how == "partition" and all_ids.shape[1] > 2 * M:
        cut = np.partition(all_dist, M - 1, axis=1)[:, M - 1 : M]
        width = max(M, int((all_dist <= cut).sum(axis=1).max()))
        part = np.argsort(all_dist > cut, axis=1, kind="stable")[:, :width]
        all_ids, all_dist, all_flag = (np.take_along_axis(v, part, 1) for v in (all_ids, all_dist, all_flag))
    order = _sorted_order(all_dist, all_ids)
    all_ids, all_dist, all_flag = (np.take_along_axis(v, order, 1) for v in (all_ids, all_dist, all_flag))
    again = np.zeros(all_ids.shape, bool)  # an id that was forgotten and came again stands beside itself
    again[:, 1:] = (all_ids[:, 1:] == all_ids[:, :-1]) & (all_ids[:, 1:] >= 0)
    if again.any():
        first = np.zeros_like(again)
        first[:, :-1] = again[:, 1:]
        carried = all_flag.copy()
        carried[:, :-1] |= first[:, :-1] & all_flag[:, 1:]
        all_flag = carried
        all_dist = np.where(again, np.inf, all_dist)
        all_ids = np.where(again, -1, all_ids)
        order = np.argsort(again, axis=1, kind="stable")
        all_ids, all_dist, all_flag = (np.take_along_axis(v, order, 1) for v in (all_ids, all_dist, all_flag))
    return all_ids[:, :M], all_dist[:, :M], all_flag[:, :M]


def _first_time(cand: np.ndarray, rows: np.ndarray, seen: VisitedSet | None) -> np.ndarray:
    """Mask of candidates (rows, C) not met before, neither in this round nor in the visited set; registers them."""
    if isinstance(seen, SeenMap):
        return seen.first_time(cand, rows)
    fresh = cand >= 0
    order = np.argsort(cand, axis=1, kind="stable")
    ordered = np.take_along_axis(cand, order, 1)
    twin = np.zeros(cand.shape, bool)
    twin[:, 1:] = ordered[:, 1:] == ordered[:, :-1]
    unsorted = np.zeros(cand.shape, bool)
    np.put_along_axis(unsorted, order, twin, 1)
    fresh &= ~unsorted
    if seen is not None:
        r, c = np.nonzero(fresh)
        fresh[r, c] = seen.insert(rows[r], cand[r, c])
    return fresh


#: Batches up to this size are walked query by query: the steps of a batch cost as much for one query as for many.
FEW_QUERIES = 4


def _walk_few(x, adj, q, params: SearchParams, qids) -> Found:
    """The same walk with a sorted list and a heap for each query; same ids, distances and counts as in step."""
    n, d = adj.shape
    k, M = params.k, params.M
    out = Found(np.full((len(q), k), -1, np.int64), np.full((len(q), k), np.inf), np.zeros(len(q), np.int64), np.zeros(len(q), np.int64))
    for i, target in enumerate(q):
        start = list(dict.fromkeys(seed_nodes(qids[i : i + 1], d, params.seed, n)[0].tolist()))
        seen, one = set(start), target[None]
        found = sorted(zip(gathered_distances(one, x[start][None], params.metric)[0].tolist(), start, strict=True))
        top, todo = found[:M], found[:]
        n_dist, rounds = len(start), 0
        while todo and rounds < params.rounds:
            best = heappop(todo)
            if len(top) == M and best > top[-1]:
                break
            rounds += 1
            new = [u for u in adj[best[1]].tolist() if u >= 0 and u not in seen]
            if not new:
                continue
            seen.update(new)
            n_dist += len(new)
            for entry in zip(gathered_distances(one, x[new][None], params.metric)[0].tolist(), new, strict=True):
                if len(top) < M or entry < top[-1]:
                    insort(top, entry)
                    heappush(todo, entry)
                    if len(top) > M:
                        top.pop()
        near = top[:k]
        out.ids[i, : len(near)], out.dist[i, : len(near)] = [u for _, u in near], [v for v, _ in near]
        out.n_dist[i], out.rounds[i] = n_dist, rounds
    zero = np.zeros(len(q), np.int64)
    out.extra.update(collisions=zero, overflows=zero, resets=zero)
    return out


def joined(parts: list[Found]) -> Found:
    """The results of consecutive slices of a batch as one."""
    columns = [np.concatenate([getattr(part, name) for part in parts]) for name in ("ids", "dist", "n_dist", "rounds")]
    return Found(*columns, {name: np.concatenate([part.extra[name] for part in parts]) for name in parts[0].extra})


def search_solo(x: np.ndarray, adj: np.ndarray, q: np.ndarray, params: SearchParams, qids: np.ndarray | None = None) -> Found:
    """One worker walks for each query; all queries of a batch go in step, finished ones drop out.

    ``x`` and ``q`` are prepared vectors. Each round: merge the candidates into the list, forget if due, test the stop rule, expand
    the first ``p`` entries that have not been, and compute distances only for nodes not met before.
    """
    n, d = adj.shape
    k, M, p = params.k, params.M, params.p
    count = len(q)
    qids = np.arange(count) if qids is None else np.asarray(qids)
    if count <= FEW_QUERIES and p == 1 and params.visited == "full" and params.stop == "exhausted" and params.expanded == "flag":
        return _walk_few(x, adj, q, params, qids)
    if count > (most := params.in_step):  # slices, whose lists and gathered vectors stay in a core's cache
        return joined([search_solo(x, adj, q[at : at + most], params, qids[at : at + most]) for at in range(0, count, most)])
    seen = None
    if params.visited == "forget":
        seen = VisitedSet(count, params.bits)
    elif params.visited == "full":
        seen = full_set(count, n, table_size(params.rounds, p, d))
    ids, dist, flag = np.full((count, M), -1, np.int64), np.full((count, M), np.inf), np.zeros((count, M), bool)
    parents = SeenMap(count, n) if params.expanded == "table" else None
    cand = seed_nodes(qids, p * d, params.seed, n)
    n_dist, rounds = np.zeros(count, np.int64), np.zeros(count, np.int64)
    active = np.arange(count)
    for step in range(params.rounds + 1):
        fresh = _first_time(cand, active, seen)
        cd = fresh_distances(q, x, active, cand, fresh, params.metric)
        n_dist[active] += fresh.sum(axis=1)
        before = ids[active]
        ids[active], dist[active], flag[active] = merge_top(ids[active], dist[active], flag[active], np.where(fresh, cand, -1), cd, M, params.merge)
        if parents is not None:  # what has been expanded is looked up, not carried along with the list
            flag[active] = parents.seen[active[:, None], np.maximum(ids[active], 0)] & (ids[active] >= 0)
        rounds[active] = step
        if step == params.rounds:
            break
        if params.visited == "forget" and step and step % params.every == 0:
            seen.reset(active, ids[active])
        if params.stop == "unchanged" and step:
            going = (ids[active] != before).any(axis=1)
            active = active[going]
        open_ = ~flag[active] & (ids[active] >= 0)
        going = open_.any(axis=1)
        active, open_ = active[going], open_[going]
        if not len(active):
            break
        rank = np.cumsum(open_, axis=1)
        chosen = open_ & (rank <= p)
        flag[active] |= chosen
        place = np.argsort(~chosen, axis=1, kind="stable")[:, :p]
        nodes = np.where(np.take_along_axis(chosen, place, 1), np.take_along_axis(ids[active], place, 1), -1)
        if parents is not None:
            row, col = np.nonzero(nodes >= 0)
            parents.insert(active[row], nodes[row, col])
        cand = np.where(nodes[:, :, None] >= 0, adj[np.maximum(nodes, 0)], -1).reshape(len(active), -1)
    extra = {} if seen is None else {"collisions": seen.collisions, "overflows": seen.overflows, "resets": seen.resets}
    return Found(ids[:, :k], dist[:, :k], n_dist, rounds, extra)


def search_team(x: np.ndarray, adj: np.ndarray, q: np.ndarray, params: SearchParams, qids: np.ndarray | None = None) -> Found:
    """Several walkers for each query, each with a list of its own and one node a round, and one visited set between them.

    Of a node that several walkers reach in a round, the walker with the smallest number takes it. ``sharing='private'`` leaves
    each walker its own set. All walkers of a query, and all queries of a slice, go in one step: their candidates meet the visited
    set and the vectors together. The lists, of ``team_list`` entries each, are merged at the end.
    """
    n, d = adj.shape
    k, W = params.k, params.walkers
    M = params.team_list or params.M
    count = len(q)
    qids = np.arange(count) if qids is None else np.asarray(qids)
    if params.sharing == "superstep" and count <= FEW_QUERIES:
        return _team_few(x, adj, q, params, qids)
    if count > (step := max(1, params.in_step // W)):
        return joined([search_team(x, adj, q[at : at + step], params, qids[at : at + step]) for at in range(0, count, step)])
    shared = params.sharing == "superstep"
    slots = table_size(params.rounds, W, d)
    sets = full_set(count if shared else count * W, n, slots)
    # row i * W + w is walker w of query i
    ids, dist, flag = np.full((count * W, M), -1, np.int64), np.full((count * W, M), np.inf), np.zeros((count * W, M), bool)
    active = np.arange(count * W)
    cand = seed_nodes(qids, W * d, params.seed, n).reshape(count * W, d)
    n_dist, rounds = np.zeros(count, np.int64), np.zeros(count, np.int64)
    for step in range(params.rounds + 1):
        owner = active // W
        if shared:  # the candidates of a query's walkers in a row, smaller walkers first
            row, col = np.nonzero(cand >= 0)
            key = owner[row] * n + cand[row, col]
            first = np.unique(key, return_index=True)[1]
            new = sets.insert(owner[row[first]], cand[row[first], col[first]])
            fresh = np.zeros(cand.shape, bool)
            fresh[row[first[new]], col[first[new]]] = True
        else:
            fresh = _first_time(cand, active, sets)
        cd = fresh_distances(q, x, owner, cand, fresh, params.metric)
        np.add.at(n_dist, owner, fresh.sum(axis=1))
        ids[active], dist[active], flag[active] = merge_top(ids[active], dist[active], flag[active], np.where(fresh, cand, -1), cd, M, params.merge)
        np.maximum.at(rounds, owner, step)
        open_ = ~flag[active] & (ids[active] >= 0)
        going = open_.any(axis=1)
        active, open_ = active[going], open_[going]
        if step == params.rounds or not len(active):
            break
        first = open_.argmax(axis=1)
        flag[active, first] = True
        cand = adj[ids[active, first]]
    flat_ids, flat_dist = ids.reshape(count, -1), dist.reshape(count, -1)
    out_ids, out_dist, _ = merge_top(np.full((count, k), -1, np.int64), np.full((count, k), np.inf), np.zeros((count, k), bool), flat_ids, flat_dist, k, "merge")
    collisions = sets.collisions if shared else sets.collisions.reshape(count, W).sum(axis=1)
    return Found(out_ids, out_dist, n_dist, rounds, {"collisions": collisions})


def _team_few(x, adj, q, params: SearchParams, qids) -> Found:
    """The same team with a sorted list and a heap for each walker; the new nodes of all walkers of a round are measured in one go."""
    n, d = adj.shape
    k, W, M = params.k, params.walkers, params.team_list or params.M
    out = Found(np.full((len(q), k), -1, np.int64), np.full((len(q), k), np.inf), np.zeros(len(q), np.int64), np.zeros(len(q), np.int64))
    for i, target in enumerate(q):
        one, seen = target[None], set()
        cand = seed_nodes(qids[i : i + 1], W * d, params.seed, n)[0].reshape(W, d).tolist()
        walkers = list(range(W))
        tops: list[list] = [[] for _ in walkers]
        todos: list[list] = [[] for _ in walkers]
        n_dist = 0
        for step in range(params.rounds + 1):
            out.rounds[i] = step
            new, of = [], []
            for w, own in zip(walkers, cand, strict=True):
                for u in own:
                    if u >= 0 and u not in seen:
                        seen.add(u)
                        new.append(u), of.append(w)
            if new:
                n_dist += len(new)
                for dist, u, w in zip(gathered_distances(one, x[new][None], params.metric)[0].tolist(), new, of, strict=True):
                    top, entry = tops[w], (dist, u)
                    if len(top) < M or entry < top[-1]:
                        insort(top, entry)
                        heappush(todos[w], entry)
                        if len(top) > M:
                            top.pop()
            going, cand = [], []
            for w in walkers:
                best = heappop(todos[w]) if todos[w] else None
                if best is not None and not (len(tops[w]) == M and best > tops[w][-1]):
                    going.append(w), cand.append(adj[best[1]].tolist())
            walkers = going
            if not walkers:
                break
        near = sorted(entry for top in tops for entry in top)[:k]
        out.ids[i, : len(near)], out.dist[i, : len(near)] = [u for _, u in near], [v for v, _ in near]
        out.n_dist[i] = n_dist
    out.extra["collisions"] = np.zeros(len(q), np.int64)
    return out


def recall(found: np.ndarray, truth: np.ndarray) -> float:
    """Mean share of the true ids that were found."""
    return float(np.mean([len(np.intersect1d(a[a >= 0], b)) / len(b) for a, b in zip(found, truth, strict=True)])) if len(truth) else 1.0
