"""Compared methods, as shard-local kernels after their published descriptions.

Graphs come back padded with -1 where degrees vary, so that one searcher serves them all.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np

from neargraph.operators.local import Found, block_distances, exact_knn, gathered_distances, search_solo, smallest, weak_components
from neargraph.params import SearchParams


def padded(lists: list[list[int]]) -> np.ndarray:
    out = np.full((len(lists), max(1, max(map(len, lists), default=1))), -1, np.int64)
    for i, own in enumerate(lists):
        out[i, : len(own)] = own
    return out


def knn_only(ids: np.ndarray, d: int) -> np.ndarray:
    return ids[:, :d]


def detour_prune(ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Every edge that has a detour goes."""
    return np.where(counts == 0, ids, -1)


def single_step(x, adj, q, k: int, M: int, **options) -> Found:
    """The earliest device search: one node a round, a bounded list and a full open-addressing table."""
    return search_solo(x, adj, q, SearchParams(k=k, M=M, p=1, visited="full", **options))


# ---------------------------------------------------------------- small-world graphs
def _beam(x, lists, entry: list[int], target: np.ndarray, ef: int, metric: str) -> list[tuple[float, int]]:
    """Best-first search of one target over growing lists; (distance, node) ascending."""
    seen = set(entry)
    dist = gathered_distances(target[None], x[entry][None], metric)[0]
    near = [(-float(v), -e) for v, e in zip(dist, entry, strict=True)]
    todo = [(float(v), e) for v, e in zip(dist, entry, strict=True)]
    heapq.heapify(near), heapq.heapify(todo)
    while len(near) > ef:
        heapq.heappop(near)
    while todo:
        v, node = heapq.heappop(todo)
        if len(near) >= ef and v > -near[0][0]:
            break
        new = [u for u in lists[node] if u not in seen]
        if not new:
            continue
        seen.update(new)
        for w, u in zip(gathered_distances(target[None], x[new][None], metric)[0].tolist(), new, strict=True):
            if len(near) < ef or w < -near[0][0]:
                heapq.heappush(near, (-w, -u)), heapq.heappush(todo, (w, u))
                if len(near) > ef:
                    heapq.heappop(near)
    return sorted((-v, -u) for v, u in near)


def _diverse(x, cand: list[tuple[float, int]], m: int, metric: str) -> list[int]:
    """Keeps a candidate if no kept one is nearer to it than the node is; fills up with the nearest of the rest."""
    kept: list[int] = []
    left: list[int] = []
    if not cand:
        return kept
    near = x[[u for _, u in cand]]
    between = gathered_distances(near, np.broadcast_to(near, (len(near), *near.shape)), metric).tolist()
    places: list[int] = []
    for i, (v, u) in enumerate(cand):
        if len(kept) >= m:
            break
        own = between[i]
        for j in places:
            if own[j] < v:
                left.append(u)
                break
        else:
            kept.append(u), places.append(i)
    return kept + left[: m - len(kept)]


def flat_sw(x: np.ndarray, m: int, ef: int, metric: str = "l2", seed: int = 1) -> np.ndarray:
    """Flat small world: nodes come in random order and link both ways with their m nearest found; no cap on degrees."""
    n = len(x)
    order = np.random.default_rng(seed).permutation(n).tolist()
    lists: list[list[int]] = [[] for _ in range(n)]
    for at, node in enumerate(order[1:], 1):
        for _, u in _beam(x, lists, [order[(at * 7919) % at]], x[node], max(ef, m), metric)[:m]:
            lists[node].append(u), lists[u].append(node)
    return padded(lists)


@dataclass
class LayeredGraph:
    layers: list[dict[int, list[int]]]
    entry: int

    @property
    def bottom(self) -> np.ndarray:
        return padded([self.layers[0].get(i, []) for i in range(len(self.layers[0]))])


def layered_sw(x: np.ndarray, m: int, ef_build: int, metric: str = "l2", seed: int = 1) -> LayeredGraph:
    """Layered small world: geometric heights, at most m links (2m at the bottom), greedy descent and a beam on each layer."""
    n = len(x)
    rng = np.random.default_rng(seed)
    heights = np.floor(-np.log(rng.random(n)) / np.log(max(2, m))).astype(int)
    layers: list[dict[int, list[int]]] = [{} for _ in range(int(heights.max()) + 1)]
    entry, top = 0, int(heights[0])
    for h in range(top + 1):
        layers[h][0] = []
    for node in range(1, n):
        at, h = [entry], int(heights[node])
        for level in range(top, h, -1):
            at = [_beam(x, layers[level], at, x[node], 1, metric)[0][1]]
        for level in range(min(h, top), -1, -1):
            cand = _beam(x, layers[level], at, x[node], ef_build, metric)
            cap = 2 * m if level == 0 else m
            own = _diverse(x, cand, m, metric)
            layers[level][node] = own
            for u in own:
                theirs = layers[level][u]
                theirs.append(node)
                if len(theirs) > cap:
                    v = gathered_distances(x[u][None], x[theirs][None], metric)[0]
                    layers[level][u] = _diverse(x, sorted(zip(v.tolist(), theirs, strict=True)), cap, metric)
            at = [u for _, u in cand]
        for level in range(top + 1, h + 1):
            layers[level][node] = []
        if h > top:
            entry, top = node, h
    return LayeredGraph(layers, entry)


def layered_search(x, graph: LayeredGraph, q, k: int, ef: int, metric: str = "l2") -> np.ndarray:
    out = np.full((len(q), k), -1, np.int64)
    for i, target in enumerate(q):
        at = [graph.entry]
        for level in range(len(graph.layers) - 1, 0, -1):
            if at[0] in graph.layers[level]:
                at = [_beam(x, graph.layers[level], at, target, 1, metric)[0][1]]
        best = [u for _, u in _beam(x, graph.layers[0], at, target, max(ef, k), metric)[:k]]
        out[i, : len(best)] = best
    return out


# ---------------------------------------------------------------- spreading graphs
def _between(x, cand, metric):
    y = x[cand]
    if metric in ("cosine", "ip"):
        return 1 - np.matmul(y, y.transpose(0, 2, 1))
    s = (y * y).sum(2)
    return np.sqrt(np.maximum(s[:, :, None] + s[:, None, :] - 2 * np.matmul(y, y.transpose(0, 2, 1)), 0))


def monotonic_spread(ids: np.ndarray, dist: np.ndarray, x: np.ndarray, R: int, metric: str = "l2") -> tuple[np.ndarray, int]:
    """Navigating spreading graph: a candidate stays if no kept neighbour is nearer to it; what the medoid cannot reach is hung on. Also the medoid."""
    n, L = ids.shape
    kept = np.full((n, R), -1, np.int64)
    for at in range(0, n, 256):
        cand, d = ids[at : at + 256], dist[at : at + 256]
        between = _between(x, cand, metric)
        alive = np.ones(cand.shape, bool)
        rows = np.arange(len(cand))
        for r in range(R):
            first = alive.argmax(axis=1)
            some = alive[rows, first]
            kept[at + rows[some], r] = cand[some, first[some]]
            alive &= ~(between[rows, first] < d)
            alive[rows, first] = False
            if not alive.any():
                break
    medoid = int(block_distances(x.mean(axis=0)[None], x, "sql2")[0].argmin())
    lists = [[v for v in row if v >= 0] for row in kept.tolist()]
    while True:
        reached = np.zeros(n, bool)
        reached[medoid] = True
        todo = [medoid]
        while todo:
            new = [u for v in todo for u in lists[v] if not reached[u]]
            new = list(dict.fromkeys(new))
            reached[new] = True
            todo = new
        if reached.all():
            return padded(lists), medoid
        lost = int(np.flatnonzero(~reached)[0])
        inside = np.flatnonzero(reached)
        lists[int(inside[block_distances(x[lost][None], x[inside], "sql2")[0].argmin()])].append(lost)


def angle_spread(ids: np.ndarray, x: np.ndarray, R: int, *, angle: float = 60.0, metric: str = "l2") -> np.ndarray:
    """Neighbours and theirs, nearest first, kept while every two of them stand at ``angle`` degrees or more; at most R."""
    n = len(x)
    cosine = np.cos(np.radians(angle))
    lists: list[list[int]] = []
    for node in range(n):
        pool = np.unique(np.concatenate([ids[node], ids[ids[node]].ravel()]))
        pool = pool[pool != node]
        way = x[pool] - x[node]
        size = np.sqrt(np.einsum("cn,cn->c", way, way))
        order = np.lexsort((pool, size if metric == "l2" else gathered_distances(x[node][None], x[pool][None], metric)[0]))
        way = np.divide(way, size[:, None], out=np.zeros_like(way), where=size[:, None] > 0)
        kept: list[int] = []
        free = np.ones(len(pool), bool)
        for i in order.tolist():
            if free[i]:
                kept.append(i)
                if len(kept) == R:
                    break
                free &= way @ way[i] <= cosine
        lists.append(pool[kept].tolist())
    return padded(lists)


# ---------------------------------------------------------------- device builds
def block_merge(x: np.ndarray, block: int, k: int, metric: str = "l2", *, levels: int = 2, share: float = 0.25, M: int = 48, seed: int = 1) -> np.ndarray:
    """Exact lists inside blocks; representatives of the blocks form the level above; its graph leads each node to other blocks; links both ways."""
    n = len(x)
    rng = np.random.default_rng(seed)
    lists: list[dict[int, float]] = [{} for _ in range(n)]

    def link(members: np.ndarray) -> None:
        i, v = exact_knn(x[members], x[members], min(k, len(members) - 1), metric, own=np.arange(len(members)))
        for node, near, far in zip(members.tolist(), members[i].tolist(), v.tolist(), strict=True):
            lists[node].update(zip(near, far, strict=True))

    level = np.arange(n)
    tops = []
    for _ in range(levels):
        mixed = rng.permutation(level)
        parts = np.array_split(mixed, max(1, -(-len(mixed) // block)))
        for part in parts:
            if len(part) > 1:
                link(part)
        level = np.sort(np.concatenate([rng.permutation(p)[: max(1, int(len(p) * share))] for p in parts]))
        tops.append(level)
    if len(level) > 1:
        link(level)
    adj = padded([sorted(own, key=own.get)[: 2 * k] for own in lists])
    entry = tops[0]
    near, _ = exact_knn(x[entry], x, min(4, len(entry)), metric)
    # walk down from the nearest representatives: their lists are searched with each node as the query
    params = SearchParams(k=min(k + 1, M), M=M, p=1, metric=metric)
    found = search_solo(x, np.concatenate([adj, entry[near]], axis=1), x, params)
    for node, (own, v) in enumerate(zip(found.ids.tolist(), found.dist.tolist(), strict=True)):
        for u, w in zip(own, v, strict=True):
            if u >= 0 and u != node:
                lists[node][u] = w
                lists[u][node] = w
    return padded([sorted(own, key=lambda u, o=own: (o[u], u))[:k] for own in lists])


def batch_insert(x: np.ndarray, groups: int, m: int, ef: int, metric: str = "l2") -> np.ndarray:
    """Graphs of groups, merged two by two: the nodes of one are searched in the other in one batch and linked both ways, degrees capped."""
    n = len(x)
    parts = [p for p in np.array_split(np.arange(n), min(groups, n)) if len(p)]
    lists: list[dict[int, float]] = [{} for _ in range(n)]
    for part in parts:
        if len(part) > 1:
            i, v = exact_knn(x[part], x[part], min(m, len(part) - 1), metric, own=np.arange(len(part)))
            for node, near, far in zip(part.tolist(), part[i].tolist(), v.tolist(), strict=True):
                lists[node].update(zip(near, far, strict=True))
                for u, w in zip(near, far, strict=True):
                    lists[u][node] = w
    while len(parts) > 1:
        merged = []
        for a, b in zip(parts[::2], [*parts[1::2], None], strict=False):
            if b is None:
                merged.append(a)
                continue
            for mine, theirs in ((a, b), (b, a)):
                place = np.full(n, -1, np.int64)
                place[theirs] = np.arange(len(theirs))
                adj = padded([[int(place[u]) for u in sorted(lists[v], key=lists[v].get)[: 2 * m] if place[u] >= 0] or [0] for v in theirs.tolist()])
                found = search_solo(x[theirs], adj, x[mine], SearchParams(k=min(m, ef), M=ef, metric=metric), mine)
                for node, near, far in zip(mine.tolist(), found.ids.tolist(), found.dist.tolist(), strict=True):
                    for u, w in zip(near, far, strict=True):
                        if u >= 0:
                            other = int(theirs[u])
                            lists[node][other] = w
                            lists[other][node] = w
            for node in [*a.tolist(), *b.tolist()]:
                own = lists[node]
                lists[node] = {u: own[u] for u in sorted(own, key=lambda u, o=own: (o[u], u))[: 2 * m]}
            merged.append(np.concatenate([a, b]))
        parts = merged
    return padded([sorted(own, key=lambda u, o=own: (o[u], u)) for own in lists])


# ---------------------------------------------------------------- quantisation, hashing, trees
def kmeans(x: np.ndarray, k: int, *, rounds: int = 10, seed: int = 1) -> np.ndarray:
    rng = np.random.default_rng(seed)
    c = x[rng.permutation(len(x))[: min(k, len(x))]].copy()
    for _ in range(rounds):
        near = block_distances(x, c, "sql2").argmin(axis=1)
        sums = np.zeros_like(c)
        np.add.at(sums, near, x)
        count = np.bincount(near, minlength=len(c))
        c = np.where(count[:, None] > 0, sums / np.maximum(count, 1)[:, None], c)
    return c


@dataclass
class ProductQuantiser:
    """Codebooks of m equal parts of the components; a code is m bytes."""

    books: np.ndarray

    @classmethod
    def train(cls, x: np.ndarray, m: int, *, codes: int = 64, seed: int = 1) -> ProductQuantiser:
        if x.shape[1] % m:
            raise ValueError("the dimension is no multiple of the parts")
        parts = x.reshape(len(x), m, -1)
        books = [kmeans(parts[:, j], codes, seed=seed + j) for j in range(m)]
        return cls(np.stack([np.pad(b, ((0, codes - len(b)), (0, 0)), constant_values=np.inf) if len(b) < codes else b for b in books]))

    def encode(self, x: np.ndarray) -> np.ndarray:
        parts = x.reshape(len(x), len(self.books), -1)
        return np.stack([np.nan_to_num(((parts[:, j, None] - np.where(np.isfinite(b), b, 1e18)[None]) ** 2).sum(2), nan=np.inf).argmin(1) for j, b in enumerate(self.books)], axis=1).astype(np.uint8)

    def decode(self, codes: np.ndarray) -> np.ndarray:
        return np.concatenate([b[codes[:, j]] for j, b in enumerate(self.books)], axis=1)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """Squared distances from a query's parts to all codewords."""
        parts = q.reshape(len(self.books), 1, -1)
        return ((parts - np.where(np.isfinite(self.books), self.books, 1e9)) ** 2).sum(2)


@dataclass
class IvfPq:
    centres: np.ndarray
    lists: list[np.ndarray]
    codes: np.ndarray
    pq: ProductQuantiser

    @classmethod
    def build(cls, x: np.ndarray, lists: int, m: int, seed: int = 1) -> IvfPq:
        centres = kmeans(x, lists, seed=seed)
        near = block_distances(x, centres, "sql2").argmin(axis=1)
        pq = ProductQuantiser.train(x - centres[near], m, seed=seed)
        return cls(centres, [np.flatnonzero(near == i) for i in range(len(centres))], pq.encode(x - centres[near]), pq)

    def search(self, q: np.ndarray, k: int, nprobe: int, *, x: np.ndarray | None = None, refine: int = 4) -> np.ndarray:
        """Ids by quantised distance; with vectors, the best ``refine * k`` are ordered again exactly."""
        out = np.full((len(q), k), -1, np.int64)
        probe, _ = smallest(block_distances(q, self.centres, "sql2"), nprobe)
        for i, target in enumerate(q):
            ids, dist = [], []
            for c in probe[i]:
                own = self.lists[c]
                table = self.pq.tables(target - self.centres[c])
                ids.append(own), dist.append(table[np.arange(table.shape[0])[None, :], self.codes[own]].sum(axis=1))
            ids, dist = np.concatenate(ids), np.concatenate(dist)
            best = ids[np.lexsort((ids, dist))[: k * (refine if x is not None else 1)]]
            if x is not None and len(best):
                best = best[np.lexsort((best, block_distances(target[None], x[best], "sql2")[0]))]
            out[i, : len(best[:k])] = best[:k]
        return out


def hash_search(x: np.ndarray, q: np.ndarray, k: int, *, tables: int = 8, bits: int = 8, seed: int = 1) -> np.ndarray:
    """Random-hyperplane buckets; the members of a query's buckets are ranked exactly."""
    rng = np.random.default_rng(seed)
    planes = rng.normal(size=(tables, bits, x.shape[1]))
    power = 1 << np.arange(bits)
    hx, hq = ((np.einsum("tbn,in->tib", planes, v) > 0) @ power for v in (x, q))
    out = np.full((len(q), k), -1, np.int64)
    for i in range(len(q)):
        ids = np.flatnonzero((hx == hq[:, i : i + 1]).any(axis=0))
        if len(ids):
            best = ids[np.lexsort((ids, block_distances(q[i][None], x[ids], "sql2")[0]))[:k]]
            out[i, : len(best)] = best
    return out


def tree_search(x: np.ndarray, q: np.ndarray, k: int, *, trees: int = 8, leaf: int = 32, seed: int = 1) -> np.ndarray:
    """Forest of random projection trees, split at the median; the query's leaves are ranked exactly."""
    rng = np.random.default_rng(seed)
    hits: list[list[np.ndarray]] = [[] for _ in range(len(q))]
    for _ in range(trees):
        todo = [(np.arange(len(x)), np.arange(len(q)))]
        while todo:
            own, asks = todo.pop()
            if len(own) <= leaf or not len(asks):
                for i in asks:
                    hits[i].append(own)
                continue
            plane = rng.normal(size=x.shape[1])
            side, cut = x[own] @ plane, np.median(x[own] @ plane)
            left = side <= cut
            if left.all():
                left = np.arange(len(own)) < len(own) // 2
            goes = q[asks] @ plane <= cut
            todo += [(own[left], asks[goes]), (own[~left], asks[~goes])]
    out = np.full((len(q), k), -1, np.int64)
    for i, own in enumerate(hits):
        ids = np.unique(np.concatenate(own))
        best = ids[np.lexsort((ids, block_distances(q[i][None], x[ids], "sql2")[0]))[:k]]
        out[i, : len(best)] = best
    return out


def reachable_pieces(adj: np.ndarray) -> int:
    return len(np.unique(weak_components(adj)))
