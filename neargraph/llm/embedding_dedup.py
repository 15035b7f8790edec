"""Near-duplicate vectors by a robust-pruned flat graph over overlapping cluster shards.

Pivots are fitted on a bounded sample; every vector goes to the shards of its nearest pivots within its label. Each shard
builds a flat graph: nearest candidates and a few random ones, pruned so that no kept neighbour hides another. The
adjacency lists of a vector's shards are united. In each of its shards a vector is then searched from the medoid: a greedy walk
with a short list of best nodes, which turns into an expansion of everything within range of the threshold. Hits are verified in double
precision. A pair that meets in several shards counts in the first only, links leave a task as counts and a spanning forest, and
a sample of vectors is compared with all rows; the overlap grows until that audit is content. If it is not at the last overlap,
all rows are compared exactly, in blocks by cell of the nearest pivot; a vector visits the cells that the angle to their border lets it link into.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.operators.linking import _forest, components
from neargraph.runtime import Scratch

THRESHOLD = 0.93
SHARD_ROWS = 768
#: Bounds of the fit: sampled vectors and pivots. Every row is indexed.
SAMPLE_ROWS, MAX_PIVOTS = 20_000, 4096
OVERLAP = 4
POOL, RANDOM, DEGREE, ALPHA = 28, 4, 16, 1.2
BEAM, SLACK = 16, 0.04
AUDIT_ROWS, AUDIT_RECALL = 512, 0.995
#: From this overlap on an audit that is not content leads to the exact comparison, in blocks of so many rows.
LAST_OVERLAP, BLOCK_ROWS = 24, 4096
#: Queries that one task searches in a shard; a larger shard goes to several tasks.
SLICE_ROWS = 4096


def _pivots(sample: pd.DataFrame, count: int, seed: int = 3) -> dict[int, np.ndarray]:
    """Unit pivots for each label, in proportion to its share of the sample, by a few rounds of spherical k-means."""
    rng = np.random.default_rng(seed)
    out = {}
    for label, part in sample.groupby("label", sort=True):
        k = min(len(part), max(1, round(count * len(part) / len(sample))))
        if k == 1:
            continue
        x = _matrix(part["vec"])
        c = x[rng.permutation(len(x))[:k]]
        for _ in range(4):
            near = np.concatenate([(x[at : at + 2048] @ c.T).argmax(axis=1) for at in range(0, len(x), 2048)])
            sums = np.zeros_like(c)
            np.add.at(sums, near, x)
            norm = np.linalg.norm(sums, axis=1, keepdims=True)
            c = np.where(norm > 1e-12, sums / np.maximum(norm, 1e-12), c)
        out[int(label)] = c
    return out


def _assign_batches(batches: Iterator[pa.RecordBatch], shared, overlap: int) -> Iterator[pa.RecordBatch]:
    """(label, rep, mult, vec) -> one row for each shard of the vector, with the list of all its shards."""
    pivots = shared.value
    schema = pa.schema([("label", pa.int64()), ("shard", pa.int32()), ("rep", pa.int64()), ("mult", pa.int64()), ("vec", pa.binary()), ("shards", pa.list_(pa.int32()))])
    for batch in batches:
        label, rep, mult, vec = (batch.column(i) for i in range(4))
        labels, vecs = label.to_numpy(), vec.to_pylist()
        lists: list[list[int]] = [[0]] * len(labels)
        for own in np.unique(labels):
            if (c := pivots.get(int(own))) is None:
                continue
            mine = np.flatnonzero(labels == own)
            m = min(overlap, len(c))
            for at in range(0, len(mine), 2048):
                rows = mine[at : at + 2048]
                s = np.frombuffer(b"".join(vecs[i] for i in rows), "<f8").reshape(len(rows), -1) @ -c.T
                near = np.sort(np.argpartition(s, m - 1, axis=1)[:, :m], axis=1) if m < len(c) else np.tile(np.arange(m), (len(rows), 1))
                for i, n in zip(rows.tolist(), near.tolist(), strict=True):
                    lists[i] = n
        take = np.repeat(np.arange(len(labels)), [len(x) for x in lists])
        picked = [c.take(pa.array(take)) for c in (label, rep, mult, vec)]
        yield pa.RecordBatch.from_arrays([picked[0].cast(pa.int64()), pa.array([s for x in lists for s in x], pa.int32()), picked[1], picked[2], picked[3], pa.array([lists[i] for i in take], pa.list_(pa.int32()))], schema=schema)


def _matrix(vecs: pd.Series) -> np.ndarray:
    """Rows of one length as a matrix."""
    return np.frombuffer(b"".join(vecs), "<f8").reshape(len(vecs), -1 if len(vecs) else 0)


def robust_graph(x: np.ndarray, *, pool: int = POOL, random: int = RANDOM, degree: int = DEGREE, alpha: float = ALPHA, seed: int = 0) -> list[np.ndarray]:
    """Flat graph over unit vectors: each node's candidates, pruned by ``alpha``, with the reverse edges, at most twice as many, nearest first."""
    n = len(x)
    if n < 2:
        return [np.zeros(0, np.int64)] * n
    rng = np.random.default_rng(seed + n)
    x = x.astype(np.float32)
    near = min(pool, n - 1)
    far = min(random, n - 1)
    picked = np.full((n, degree), -1, np.int64)
    for at in range(0, n, 256):
        rows = np.arange(at, min(n, at + 256))
        s = x[rows] @ x.T
        s[np.arange(len(rows)), rows] = -2
        cand = np.argpartition(-s, near - 1, axis=1)[:, :near]
        cand = np.concatenate([cand, rng.integers(0, n, (len(rows), far))], axis=1)
        d = 2 - 2 * np.take_along_axis(s, cand, axis=1)
        order = np.argsort(d, axis=1, kind="stable")
        cand, d = np.take_along_axis(cand, order, axis=1), np.take_along_axis(d, order, axis=1)
        between = 2 - 2 * np.matmul(x[cand], x[cand].transpose(0, 2, 1))
        alive = cand != rows[:, None]
        for r in range(degree):
            first = alive.argmax(axis=1)
            some = alive[np.arange(len(rows)), first]
            picked[rows[some], r] = cand[some, first[some]]
            hidden = alpha * alpha * between[np.arange(len(rows)), first] <= d
            alive &= ~hidden
            alive[np.arange(len(rows)), first] = False
            if not alive.any():
                break
    a, rank = np.nonzero(picked >= 0)
    b = picked[a, rank]
    back = np.lexsort((a, rank, b))  # who has a node for its nearest comes first
    starts = np.searchsorted(b[back], np.arange(n + 1))
    return [np.unique(np.r_[picked[i][picked[i] >= 0], a[back[starts[i] : starts[i + 1]]][: 2 * degree]]) for i in range(n)]


def _build(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values("rep", kind="stable").reset_index(drop=True)
    reps = pdf["rep"].to_numpy()
    lists = robust_graph(_matrix(pdf["vec"]))
    return pd.DataFrame({"rep": reps, "nbrs": [reps[x] for x in lists]})


def range_search(x: np.ndarray, adjacency: np.ndarray, queries: np.ndarray, threshold: float, *, beam: int = BEAM, slack: float = SLACK) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (query node, node) with cosine at or over the threshold: a greedy walk from the medoid, then expansion of all that is in range.

    ``adjacency`` is padded with -1. The query's own neighbours join the medoid as entries.
    """
    n = len(x)
    f = x.astype(np.float32)
    centre = f.mean(axis=0)
    medoid = int((f @ centre).argmax())
    found_q, found_x = [], []
    step = max(1, min(512, 64_000_000 // max(1, n)))
    for at in range(0, len(queries), step):
        own = queries[at : at + step]
        q = np.arange(len(own))
        fq = f[own]
        seen = np.zeros((len(own), n), bool)
        score = lambda rows, nodes, fq=fq: np.einsum("pd,pd->p", f[nodes], fq[rows])
        entries = np.concatenate([np.full((len(own), 1), medoid), adjacency[own]], axis=1)
        ids = np.full((len(own), beam), -1, np.int64)
        sims = np.full((len(own), beam), -np.inf, np.float32)
        open_ = np.zeros((len(own), beam), bool)
        pairs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        fresh = entries
        for _ in range(8 * beam):
            rows, col = np.nonzero(fresh >= 0)
            nodes = fresh[rows, col]
            new = ~seen[rows, nodes]
            key = np.unique(rows[new] * n + nodes[new])
            rows, nodes = key // n, key % n
            seen[rows, nodes] = True
            s = score(rows, nodes)
            close = s >= threshold - slack
            pairs.append((rows[close], nodes[close], s[close]))
            if len(rows):
                width = np.bincount(rows, minlength=len(own))
                place = np.arange(len(rows)) - np.repeat(np.cumsum(width) - width, width)
                more_ids = np.full((len(own), width.max()), -1, np.int64)
                more_s = np.full((len(own), width.max()), -np.inf, np.float32)
                more_ids[rows, place], more_s[rows, place] = nodes, s
                all_ids, all_s = np.concatenate([ids, more_ids], axis=1), np.concatenate([sims, more_s], axis=1)
                all_open = np.concatenate([open_, more_ids >= 0], axis=1)
                best = np.argpartition(-all_s, beam - 1, axis=1)[:, :beam]
                ids, sims, open_ = (np.take_along_axis(v, best, axis=1) for v in (all_ids, all_s, all_open))
            waiting = np.where(open_, sims, -np.inf)
            j = waiting.argmax(axis=1)
            go = np.isfinite(waiting[q, j])
            if not go.any():
                break
            open_[q[go], j[go]] = False
            fresh = np.where(go[:, None], adjacency[np.where(go, ids[q, j], 0)], -1)
        # everything in range is expanded, level by level
        rows, nodes, s = (np.concatenate(v) for v in zip(*pairs, strict=True))
        hits = [(rows, nodes)]
        while len(rows):
            next_rows, next_nodes = [], []
            for cut in range(0, len(rows), 200_000):
                r, v = rows[cut : cut + 200_000], adjacency[nodes[cut : cut + 200_000]]
                r, c = np.repeat(r, v.shape[1]), v.ravel()
                good = c >= 0
                r, c = r[good], c[good]
                new = ~seen[r, c]
                key = np.unique(r[new] * n + c[new])
                r, c = key // n, key % n
                seen[r, c] = True
                keep = score(r, c) >= threshold - slack
                next_rows.append(r[keep]), next_nodes.append(c[keep])
            rows, nodes = np.concatenate(next_rows), np.concatenate(next_nodes)
            hits.append((rows, nodes))
        rows, nodes = (np.concatenate(v) for v in zip(*hits, strict=True))
        exact = np.concatenate([np.einsum("pd,pd->p", x[nodes[i : i + 100_000]], x[own[rows[i : i + 100_000]]]) for i in range(0, max(1, len(rows)), 100_000)])
        good = (exact >= threshold) & (nodes != own[rows])
        found_q.append(own[rows[good]]), found_x.append(nodes[good])
    return np.concatenate(found_q) if found_q else np.zeros(0, np.int64), np.concatenate(found_x) if found_x else np.zeros(0, np.int64)


def _search(pdf: pd.DataFrame, threshold: float) -> pd.DataFrame:
    """One slice of a shard: link counts of its queries and a spanning forest of the links."""
    pdf = pdf.sort_values("rep", kind="stable").reset_index(drop=True)
    reps, mult, shard = pdf["rep"].to_numpy(), pdf["mult"].to_numpy(), int(pdf["shard"].iloc[0])
    x = _matrix(pdf["vec"])
    lists = []
    for own in pdf["nbrs"]:
        own = np.asarray(own, np.int64)
        place = np.minimum(np.searchsorted(reps, own), len(reps) - 1)
        lists.append(place[reps[place] == own])  # neighbours that other shards found and that are here too stay
    adjacency = np.full((len(reps), max(1, max(map(len, lists)))), -1, np.int64)
    for i, own in enumerate(lists):
        adjacency[i, : len(own)] = own
    asks = pdf["asks"].to_numpy()
    q, c = range_search(x, adjacency, np.flatnonzero(asks), threshold)
    both = np.unique(np.r_[q * len(reps) + c, (c * len(reps) + q)[asks[c]]])  # what one side has found, the other has too
    q, c = both // len(reps), both % len(reps)
    m = max(map(len, pdf["shards"]))
    shards = np.full((len(reps), m), -1, np.int64)
    for i, own in enumerate(pdf["shards"]):
        shards[i, : len(own)] = own
    common = np.full(len(q), np.iinfo(np.int64).max)
    for i in range(m):
        for j in range(m):
            both = (shards[q, i] == shards[c, j]) & (shards[q, i] >= 0)
            common = np.where(both, np.minimum(common, shards[q, i]), common)
    links = np.bincount(q, weights=np.where(common == shard, mult[c], 0), minlength=len(reps)).astype(np.int64)
    a, b = _forest(reps[q], reps[c])
    some = np.flatnonzero(links)
    return pd.DataFrame({"rep": np.r_[reps[some], a], "links": np.r_[links[some], np.zeros(len(a), np.int64)], "other": np.r_[reps[some], b]})


def _audit_batches(batches: Iterator[pa.RecordBatch], shared, threshold: float) -> Iterator[pa.RecordBatch]:
    labels, reps, x = shared.value
    counts = np.zeros(len(reps), np.int64)
    for batch in batches:
        label, rep, mult = (batch.column(i).to_numpy() for i in range(3))
        vecs = batch.column(3).to_pylist()
        fit = np.flatnonzero([len(v) == 8 * x.shape[1] for v in vecs])  # another length has another label here
        if not len(fit):
            continue
        y = np.frombuffer(b"".join(vecs[i] for i in fit), "<f8").reshape(len(fit), -1)
        hit = (x @ y.T >= threshold) & (labels[:, None] == label[fit][None, :]) & (reps[:, None] != rep[fit][None, :])
        counts += hit @ mult[fit]
    some = np.flatnonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(reps[some], pa.int64()), pa.array(counts[some], pa.int64())], names=["rep", "links"])


def _visit_batches(batches: Iterator[pa.RecordBatch], shared, threshold: float) -> Iterator[pa.RecordBatch]:
    """(label, rep, mult, vec) -> one row for each cell that may hold a link of the vector; ``own`` marks the cell it lives in.

    Who lives in a cell is no nearer to another pivot, so what is further than the threshold's angle from the plane between its own pivot
    and the cell's has no link there. Vectors that fit no pivots share a cell by length.
    """
    pivots = shared.value
    schema = pa.schema([("label", pa.int64()), ("cell", pa.int32()), ("own", pa.bool_()), ("rep", pa.int64()), ("mult", pa.int64()), ("vec", pa.binary())])
    reach = np.sqrt(max(0.0, 1 - threshold * threshold)) if threshold > 0 else 1.0
    for batch in batches:
        label, rep, mult, vec = (batch.column(i) for i in range(4))
        labels, vecs = label.to_numpy(), vec.to_pylist()
        fits = np.array([(c := pivots.get(int(own))) is not None and len(v) == 8 * c.shape[1] for own, v in zip(labels, vecs, strict=True)], bool)
        odd = np.flatnonzero(~fits)
        parts = [(odd, np.array([-len(vecs[i]) for i in odd], np.int64), np.ones(len(odd), bool))]
        for own in np.unique(labels[fits]):
            c = pivots[int(own)]
            gap = np.sqrt(np.maximum(0.0, ((c * c).sum(axis=1)[:, None] + (c * c).sum(axis=1)[None, :]) - 2 * c @ c.T))
            rows = np.flatnonzero(fits & (labels == own))
            s = np.frombuffer(b"".join(vecs[i] for i in rows), "<f8").reshape(len(rows), -1) @ c.T
            home = s.argmax(axis=1)
            r, cell = np.nonzero(s[np.arange(len(rows)), home][:, None] - s <= reach * gap[home] + 1e-7)
            parts.append((rows[r], cell, cell == home[r]))
        take, cell, own = (np.concatenate(x) for x in zip(*parts, strict=True))
        for at in range(0, len(take), 20_000):
            cut = slice(at, at + 20_000)
            picked = [c.take(pa.array(take[cut])) for c in (label, rep, mult, vec)]
            yield pa.RecordBatch.from_arrays([picked[0].cast(pa.int64()), pa.array(cell[cut], pa.int32()), pa.array(own[cut], pa.bool_()), *picked[1:]], schema=schema)


def _compare(pdf: pd.DataFrame, threshold: float) -> pd.DataFrame:
    """One block of a cell's rows against one slice of its visitors: link counts of the visitors and a spanning forest of the links."""
    here, asks = pdf[~pdf["asks"]], pdf[pdf["asks"]]
    a, b, counts = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], np.zeros(len(asks), np.int64)
    reps, own, mult = asks["rep"].to_numpy(), here["rep"].to_numpy(), here["mult"].to_numpy()
    if len(here) and len(asks):
        x, y = _matrix(asks["vec"]), _matrix(here["vec"])
        for at in range(0, len(x), 256):
            hit = (x[at : at + 256] @ y.T >= threshold) & (reps[at : at + 256, None] != own[None, :])
            counts[at : at + 256] = hit @ mult
            i, j = np.nonzero(hit)
            some, root = _forest(reps[at + i], own[j])
            a.append(some), b.append(root)
    a, b = _forest(np.concatenate(a), np.concatenate(b))
    some = np.flatnonzero(counts)
    return pd.DataFrame({"rep": np.r_[reps[some], a], "links": np.r_[counts[some], np.zeros(len(a), np.int64)], "other": np.r_[reps[some], b]})


def exact_links(classes: DataFrame, sample: pd.DataFrame, n: int, threshold: float, scratch: Scratch, *, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """``classes(label, rep, mult, vec)`` -> ``(rep, links, other)`` of all links, as the shard search gives it.

    Every row lives in one cell and meets the rows of each cell that it visits once, so a vector counts each link once. Cells
    have about ``block_rows`` rows, so that at worst a row visits no more cells than a plain comparison in blocks has; large ones are cut.
    """
    pivots = scratch.spark.sparkContext.broadcast(_pivots(sample, min(MAX_PIVOTS, max(1, n // block_rows))))
    visits = classes.select("label", "rep", "mult", "vec").mapInArrow(lambda it: _visit_batches(it, pivots, threshold), "label long, cell int, own boolean, rep long, mult long, vec binary")
    visits = scratch.keep(visits)
    cuts = lambda count: F.ceil(count / block_rows).cast("int")
    sizes = visits.groupBy("label", "cell").agg(cuts(F.count_if("own")).alias("blocks"), cuts(F.count("*")).alias("slices")).where("blocks > 0")
    rows = visits.join(sizes, ["label", "cell"])
    upto = lambda count: F.explode(F.sequence(F.lit(0), F.col(count) - 1))
    live = rows.where("own").select("label", "cell", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int").alias("block"), upto("slices").alias("slice"), F.lit(False).alias("asks"), "rep", "mult", "vec")
    come = rows.select("label", "cell", upto("blocks").alias("block"), F.pmod(F.xxhash64("rep"), F.col("slices")).cast("int").alias("slice"), F.lit(True).alias("asks"), "rep", "mult", "vec")
    pairs = live.unionByName(come).groupBy("label", "cell", "block", "slice")
    return scratch.keep(pairs.applyInPandas(lambda pdf: _compare(pdf, threshold), "rep long, links long, other long"))


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Unit vectors in double precision as bytes; null where a vector takes no part."""
    for batch in batches:
        out = []
        for v in batch.column(2).to_pylist():
            x = None if v is None or any(c is None for c in v) else np.asarray(v, np.float64)
            good = x is not None and len(x) and np.isfinite(x).all() and (norm := np.linalg.norm(x / (np.abs(x).max() or 1.0))) > 0
            out.append((x / (np.abs(x).max() or 1.0) / norm).astype("<f8").tobytes() if good else None)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.binary())], names=["vec_id", "label", "vec"])


def embedding_dedup(vectors: DataFrame, *, threshold: float = THRESHOLD, shard_rows: int = SHARD_ROWS, overlap: int = OVERLAP, slice_rows: int = SLICE_ROWS) -> DataFrame:
    """``embeddings`` -> ``(vec_id, n_links, component_id, kept, audit_recall)``, one row for each input row.

    Two rows link if their labels are equal and not null and their cosine is ``threshold`` or more. Vectors that are null, empty, zero or hold
    null or non-finite components, and rows without a label, have no links and are their own component; vectors of unequal lengths do not link. Rows without an
    id take no part: no links, null component, not kept. Equal vectors of a label count as one until the end. Rows that repeat an id count as
    vectors of their own in ``n_links``. An empty table gives an empty result.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "vectors")
    raw = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
    rows = raw.mapInArrow(_pack, "vec_id long, label long, vec binary")
    rows = scratch.keep(rows.withColumn("h1", F.xxhash64("vec")).withColumn("h2", F.xxhash64("vec", F.lit(1))))
    # a label's vectors of another length are like another label's, as no cosine is defined between them
    valid = rows.where("vec_id is not null and label is not null and vec is not null").withColumn("label", F.xxhash64("label", F.length("vec")))
    classes = scratch.keep(valid.groupBy("label", "h1", "h2").agg(F.min(F.struct("vec_id", "vec")).alias("x"), F.count("*").alias("mult")).select("label", F.col("x.vec_id").alias("rep"), "mult", F.col("x.vec").alias("vec"), "h1", "h2"))
    n = classes.count()
    sample = classes.select("label", "rep", "vec").orderBy(F.xxhash64("rep"), "rep").limit(SAMPLE_ROWS).toPandas()
    audit = sample.head(AUDIT_ROWS)
    sizes = audit["vec"].map(len)
    audit = audit[sizes == sizes.mode().max()] if len(audit) else audit  # of several lengths the most common one
    truth = None

    def audited(links: DataFrame) -> float:
        got = links.join(F.broadcast(spark.createDataFrame([(int(r),) for r in audit["rep"]], "rep long")), "rep").toPandas()
        got = dict(zip(got["rep"], got["links"], strict=True))
        due = sum(truth.values())
        return sum(min(got.get(r, 0), t) for r, t in truth.items()) / due if due else 1.0

    while True:
        pivots = spark.sparkContext.broadcast(_pivots(sample, min(MAX_PIVOTS, max(1, n * overlap // shard_rows))))
        placed = scratch.keep(classes.select("label", "rep", "mult", "vec").mapInArrow(lambda it, p=pivots, m=overlap: _assign_batches(it, p, m), "label long, shard int, rep long, mult long, vec binary, shards array<int>"))
        built = placed.select("label", "shard", "rep", "vec").groupBy("label", "shard").applyInPandas(_build, "rep long, nbrs array<long>")
        graph = scratch.keep(built.groupBy("rep").agg(F.array_distinct(F.flatten(F.collect_list("nbrs"))).alias("nbrs")))
        sizes = placed.groupBy("label", "shard").agg(F.ceil(F.count("*") / slice_rows).cast("int").alias("slices"))
        whole = placed.join(graph, "rep").join(sizes, ["label", "shard"])
        sliced = whole.withColumn("slice", F.explode(F.sequence(F.lit(0), F.col("slices") - 1))).withColumn("asks", F.pmod(F.xxhash64("rep"), F.col("slices")) == F.col("slice"))
        found = scratch.keep(sliced.select("label", "shard", "slice", "rep", "mult", "vec", "shards", "nbrs", "asks").groupBy("label", "shard", "slice").applyInPandas(lambda pdf: _search(pdf, threshold), "rep long, links long, other long"))
        links = scratch.keep(found.groupBy("rep").agg(F.sum("links").alias("links")))
        if not len(audit):
            recall = 1.0
            break
        if truth is None:
            shared = spark.sparkContext.broadcast((audit["label"].to_numpy(), audit["rep"].to_numpy(), np.frombuffer(b"".join(audit["vec"]), "<f8").reshape(len(audit), -1)))
            exact = classes.select("label", "rep", "mult", "vec").mapInArrow(lambda it: _audit_batches(it, shared, threshold), "rep long, links long").groupBy("rep").agg(F.sum("links").alias("links")).toPandas()  # at most AUDIT_ROWS rows
            truth = dict(zip(exact["rep"], exact["links"], strict=True))
        recall = audited(links)
        if recall >= AUDIT_RECALL:
            break
        if overlap >= LAST_OVERLAP:
            found = exact_links(classes, sample, n, threshold, scratch)
            links = scratch.keep(found.groupBy("rep").agg(F.sum("links").alias("links")))
            recall = audited(links)
            break
        overlap *= 2
    forest = found.where("rep <> other").select(F.col("rep").alias("a"), F.col("other").alias("b"))
    joined = components(forest, scratch)
    reps = classes.select("label", "h1", "h2", "rep", "mult").join(links, "rep", "left").join(joined, F.col("rep") == joined.id, "left").select("label", "h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("mult") - 1).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    with_class = valid.select("vec_id", "label", "h1", "h2").join(reps, ["label", "h1", "h2"]).select("vec_id", "n_links", "component_id")
    others = rows.where("vec_id is null or label is null or vec is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return with_class.unionByName(others).select("vec_id", "n_links", "component_id", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)).alias("kept"), F.lit(float(recall)).alias("audit_recall"))
