"""The methods as DataFrame plans: exact search, graph optimisation, reachability and the walk in rounds.

These plans are the executable specification and serve graphs of up to some ten million nodes; larger ones are built and
searched shard by shard with the kernels of ``local``. The optimisation reads lists of ids only: no vector column is in its plan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neargraph.functions import buffer
from neargraph.functions.distance import distance
from neargraph.operators import exact, ways
from neargraph.params import SearchParams
from neargraph.runtime import Scratch, prepare, shuffle_partitions

#: Most bytes of queries that are sent to every task.
BROADCAST_BYTES = 256 << 20
#: Most bytes of vectors (at 4 for a component) that every task of a descent or an exact search holds; larger sets are joined to their pairs or blocks.
SENT_BYTES = 32 << 20


def _small(df: DataFrame, rows: int, dim: int) -> DataFrame:
    """Broadcast behind a check of the size; beyond it the planner chooses."""
    return F.broadcast(df) if rows * (dim * 4 + 16) <= BROADCAST_BYTES else df


# ---------------------------------------------------------------- exact
def exact_knn(vecs: DataFrame, queries: DataFrame, k: int, *, metric: str = "l2", exclude_self: bool = False, n_queries: int | None = None, dim: int | None = None) -> DataFrame:
    """HIT rows of the k nearest vectors: every block of queries against every block of rows, the best k kept before and after the shuffle."""
    spark = vecs.sparkSession
    n, wide = vecs.agg(F.count("*"), F.max(F.size("vec"))).first()
    count, dim = queries.count() if n_queries is None else n_queries, max(wide or 0, dim or 0)
    parts = max(shuffle_partitions(spark), spark.sparkContext.defaultParallelism)
    size = min(exact.QUERY_BLOCK, max(64, -(-count // parts)))
    q, v = exact.blocks(queries.select("qid", "vec"), size, "q"), exact.blocks(vecs.select("id", "vec"), exact.VECTOR_BLOCK, "v")
    if n > exact.VECTOR_BLOCK and n * (dim * 8 + 16) <= BROADCAST_BYTES and n * dim * 4 <= SENT_BYTES:
        return per_query(exact.nearest_sent(q.repartition(parts), v, k, metric, exclude_self), k)
    if n * (dim * 8 + 16) <= BROADCAST_BYTES:
        pairs = q.repartition(parts).crossJoin(F.broadcast(v))
    else:
        pairs = v.repartition(parts).crossJoin(_small(q, count, 2 * dim))
    return per_query(exact.nearest(pairs, k, metric, exclude_self), k)


def per_query(hits: DataFrame, k: int) -> DataFrame:
    """The k smallest of each query, ties by id."""
    place = F.row_number().over(Window.partitionBy("qid").orderBy(F.asc_nulls_last("dist"), "nid"))
    return hits.withColumn("rnk", place).where(F.col("rnk") <= k).select("qid", F.col("rnk").cast("int").alias("rnk"), "nid", "dist")


def knn_edges(vecs: DataFrame, degree: int, *, metric: str = "l2") -> DataFrame:
    """Base graph as edges (src, rank, dst, dist), rank from 0."""
    hits = exact_knn(vecs, vecs.select(F.col("id").alias("qid"), "vec"), degree, metric=metric, exclude_self=True)
    return hits.select(F.col("qid").alias("src"), (F.col("rnk") - 1).alias("rank"), F.col("nid").alias("dst"), "dist")


def descent_edges(vecs: DataFrame, degree: int, scratch: Scratch, *, metric: str = "l2", rho: float = 0.5, delta: float = 0.001, max_iter: int = 12, seed: int = 1) -> DataFrame:
    """Approximate base graph (src, rank, dst, dist) by neighbour descent, one plan a round, for sets that no task holds.

    Ids are dense from 0. A node brings together at most ``2 * ceil(rho * degree)`` neighbours new since the last round, forward and back,
    with as many old ones: pairs in proportion to the number of nodes, whatever the data. Rounds end when few entries change.
    """
    n, last, low, high = vecs.agg(F.count("*"), F.max("id"), F.min(F.coalesce(F.size("vec"), F.lit(-1))), F.max(F.size("vec"))).first()
    if not 0 < degree < n or last != n - 1:
        raise ValueError("dense ids and a degree between 1 and N - 1 are needed")
    most = max(1, int(-(-rho * degree // 1)))
    v = scratch.keep(vecs.select("id", "vec"))
    sent = exact.pair_distances(v, n, metric) if 0 < low == high and n * high * 4 <= SENT_BYTES else None

    def measured(pairs: DataFrame) -> DataFrame:
        """(a, b) -> (src, dst, dist) both ways."""
        x, y = (v.select(F.col("id").alias(c), F.col("vec").alias(f"v{c}")) for c in "ab")
        both = sent(pairs) if sent else pairs.join(x, "a").join(y, "b").select("a", "b", distance(metric, "va", "vb").alias("dist"))
        return both.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "dist"), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "dist"))).alias("e")).select("e.*")

    def ordered(a, b):
        return F.least(a, b).alias("a"), F.greatest(a, b).alias("b")

    def best(rows: DataFrame) -> DataFrame:
        once = rows.groupBy("src", "dst").agg(F.min("dist").alias("dist"), F.min("age").alias("age"))
        place = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
        return once.withColumn("rank", place).where(F.col("rank") <= degree)

    other = (F.col("id") + 1 + F.pmod(F.xxhash64("id", "j", F.lit(seed)), F.lit(n - 1))) % n
    starts = v.select("id", F.explode(F.sequence(F.lit(0), F.lit(degree - 1))).alias("j")).select(*ordered(F.col("id"), other)).distinct()
    # age 0: met and joined before, 1: kept but not yet joined, 2: came in the last round
    lists = scratch.keep(best(measured(starts).withColumn("age", F.lit(2))))
    for turn in range(max_iter):
        lot = F.xxhash64("src", "dst", F.lit(seed + turn))
        young = F.col("age") > 0

        def drawn(by: str, lot=lot, young=young):
            place = F.row_number().over(Window.partitionBy(by, young).orderBy(lot, "src", "dst"))
            return lists.select("src", "dst", young.alias("young"), place.alias("place")).where(F.col("place") <= most)

        ahead = scratch.keep(drawn("src").select("src", "dst", "young"))
        near = ahead.select(F.col("src").alias("node"), F.col("dst").alias("u"), "young").union(drawn("dst").select(F.col("dst").alias("node"), F.col("src").alias("u"), "young"))
        sides = near.groupBy("node").agg(F.collect_set(F.when(F.col("young"), F.col("u"))).alias("fresh"), F.collect_set("u").alias("all"))
        pairs = sides.select(F.explode("fresh").alias("x"), "all").select("x", F.explode("all").alias("y")).where("x <> y").select(*ordered(F.col("x"), F.col("y"))).distinct()
        came = measured(pairs).withColumn("age", F.lit(2))
        joined = ahead.where("young").select("src", "dst", F.lit(True).alias("went"))
        kept = lists.join(joined, ["src", "dst"], "left").select("src", "dst", "dist", F.when(F.col("went") | (F.col("age") == 0), 0).otherwise(1).alias("age"))
        old, lists = lists, scratch.keep(best(kept.unionByName(came)))
        scratch.drop(old, ahead)
        if lists.where("age = 2").count() < delta * n * degree:
            break
    return lists.select("src", (F.col("rank") - 1).alias("rank"), "dst", "dist")


def base_edges(vecs: DataFrame, degree: int, scratch: Scratch, *, metric: str = "l2", exact_rows: int | None = None) -> DataFrame:
    """Base graph (src, rank, dst, dist): all pairs, whatever the size. Only a caller that states ``exact_rows`` gets neighbour descent beyond them."""
    if exact_rows is None or vecs.select("id").limit(exact_rows + 1).count() <= exact_rows:
        return knn_edges(vecs, degree, metric=metric)
    return descent_edges(vecs, degree, scratch, metric=metric)


def radius_join(vecs: DataFrame, queries: DataFrame, r: float, *, metric: str = "l2", n_queries: int | None = None, dim: int = 1024) -> DataFrame:
    """(qid, nid, dist) of all vectors within ``r`` of each query."""
    q = _small(queries.select("qid", F.col("vec").alias("qvec")), queries.count() if n_queries is None else n_queries, dim)
    return vecs.crossJoin(q).select("qid", F.col("id").alias("nid"), distance(metric, "vec", "qvec").alias("dist")).where(F.col("dist") <= r)


# ---------------------------------------------------------------- lists and edges
def to_edges(adj: DataFrame) -> DataFrame:
    return adj.select(F.col("id").alias("src"), F.posexplode("nbrs").alias("rank", "dst"))


def to_lists(edges: DataFrame) -> DataFrame:
    rows = F.array_sort(F.collect_list(F.struct("rank", "dst")))
    return edges.groupBy(F.col("src").alias("id")).agg(F.transform(rows, lambda x: x["dst"]).alias("nbrs"))


# ---------------------------------------------------------------- optimisation
def detours(edges: DataFrame, weight: str = "rank") -> DataFrame:
    """(src, rank, dst, detours): for each edge the two-edge ways whose longer edge is shorter than it.

    An earlier entry Z of the same list is paired with Y, and Z -> Y is looked up with the condition on its length.
    By distance a Z of equal distance may stand earlier; the strict comparison sorts it out. Edges up to ``ways.SENT_EDGES`` are held as arrays
    by the tasks and need no join.
    """
    held = _held_detours(edges, weight)
    return _joined_detours(edges, weight) if held is None else held


def _held_detours(edges: DataFrame, weight: str, keep: int | None = None) -> DataFrame | None:
    by = "rank" if weight == "rank" else "dist"
    w, spark = F.col(by), prepare(edges.sparkSession)
    plain = F.col("src").isNotNull() & F.col("dst").isNotNull() & w.isNotNull() & ~F.isnan(w.cast("double")) & F.col("rank").isNotNull()
    n, good = edges.agg(F.count("*"), F.count(F.when(plain, 1))).first()
    if not n == good <= ways.SENT_EDGES:
        return None
    return ways.detours(edges, by, max(shuffle_partitions(spark), spark.sparkContext.defaultParallelism), keep)


def _joined_detours(edges: DataFrame, weight: str) -> DataFrame:
    e = edges.withColumn("w", F.col("rank" if weight == "rank" else "dist"))
    wedge = e.select("src", F.col("dst").alias("z"), F.col("w").alias("wz")).join(e.select("src", F.col("dst").alias("y"), F.col("w").alias("wy")), "src").where("wz < wy")
    step = e.select(F.col("src").alias("z"), F.col("dst").alias("y"), F.col("w").alias("w2"))
    counted = wedge.join(step, ["z", "y"]).where("w2 < wy").groupBy("src", F.col("y").alias("dst")).agg(F.count("*").alias("detours"))
    return edges.join(counted, ["src", "dst"], "left").select("src", "rank", "dst", F.coalesce("detours", F.lit(0)).cast("long").alias("detours"))


def reordered(edges: DataFrame, d: int, weight: str = "rank") -> DataFrame:
    """``pruned(detours(edges, weight), d)``; edges that the tasks hold are counted and cut in one place, without a shuffle."""
    held = _held_detours(edges, weight, d)
    return pruned(_joined_detours(edges, weight), d) if held is None else held


def pruned(counted: DataFrame, d: int) -> DataFrame:
    """The first d edges of each node by (detours, rank), with their new ranks."""
    place = F.row_number().over(Window.partitionBy("src").orderBy("detours", "rank")) - 1
    return counted.withColumn("new", place).where(F.col("new") < d).select("src", F.col("new").cast("int").alias("rank"), "dst")


def detour_free(counted: DataFrame) -> DataFrame:
    """The older way: every edge with a detour goes, so degrees vary."""
    return counted.where("detours = 0").select("src", "rank", "dst")


def reversed_edges(edges: DataFrame, d: int) -> DataFrame:
    """(node, pos, src): who points at a node, by the rank the edge has there, then by source; at most d.

    The limit is applied before the rows of a node meet, so a hub brings at most d rows from each task.
    """
    place = F.row_number().over(Window.partitionBy("dst").orderBy("rank", "src")) - 1
    return edges.withColumn("pos", place).where(F.col("pos") < d).select(F.col("dst").alias("node"), F.col("pos").cast("int").alias("pos"), "src")


def interleaved(edges: DataFrame, d: int) -> DataFrame:
    """Half of each list from the pruned edges and half from reversed ones, in turns; gaps filled from the pruned list. Edges in, edges out."""
    forward, rest = -(-d // 2), d // 2
    own = to_lists(edges)
    back = to_lists(reversed_edges(edges, d).select(F.col("node").alias("src"), F.col("pos").alias("rank"), F.col("src").alias("dst"))).select("id", F.col("nbrs").alias("back"))
    rows = own.join(back, "id", "left").withColumn("back", F.coalesce("back", F.array().cast("array<long>")))
    head = F.slice("nbrs", 1, forward)
    tail = F.slice(F.array_except("back", head), 1, rest)
    rows = rows.withColumn("head", head).withColumn("tail", tail)
    mixed = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(forward)), lambda i: F.concat(F.slice("head", i, F.lit(1)), F.slice("tail", i, F.lit(1)))))
    filled = F.concat(mixed, F.array_except(F.slice("nbrs", forward + 1, 1 << 20), "tail"))
    return rows.select(F.col("id").alias("src"), F.posexplode(F.slice(filled, 1, d)).alias("rank", "dst"))


def uniform_graph(edges: DataFrame, d: int, *, reorder: str = "rank", reverse: bool = True) -> DataFrame:
    """Edges of the graph of fixed out-degree d from base edges (src, rank, dst[, dist]). ``reorder``: 'rank', 'distance', 'none'."""
    if reorder == "none":
        cut = edges.where(F.col("rank") < d).select("src", "rank", "dst")
    else:
        cut = reordered(edges, d, reorder)
    return interleaved(cut, d) if reverse else cut


# ---------------------------------------------------------------- reachability
def two_hop(edges: DataFrame) -> DataFrame:
    """(src, reached): distinct nodes within two steps, the node itself left out."""
    e = edges.select("src", "dst")
    second = e.select("src", F.col("dst").alias("mid")).join(e.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst")
    return e.union(second).where("src <> dst").distinct().groupBy("src").agg(F.count("*").alias("reached"))


def two_hop_max(d: int) -> int:
    return d + d * d


def degrees(edges: DataFrame) -> DataFrame:
    """One row: smallest, mean and largest out- and in-degree over the nodes that have an edge."""
    out = edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n_out"))
    into = edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n_in"))
    both = out.join(into, "id", "full").select(F.coalesce("n_out", F.lit(0)).alias("n_out"), F.coalesce("n_in", F.lit(0)).alias("n_in"))
    return both.agg(*(f(c).cast(t).alias(f"{f.__name__}_{c[2:]}") for c in ("n_out", "n_in") for f, t in ((F.min, "long"), (F.avg, "double"), (F.max, "long"))))


def _spread(edges: DataFrame, labels: DataFrame, scratch: Scratch, pick) -> DataFrame:
    """Carries labels (id, label) along the edges (src -> dst) until nothing changes; ``pick`` is min or max of a column."""
    while True:
        sent = edges.join(labels, edges.src == labels.id).select(F.col("dst").alias("id"), "label")
        new = scratch.keep(labels.withColumn("old", F.col("label")).unionByName(sent.withColumn("old", F.lit(None).cast("long"))).groupBy("id").agg(pick("label").alias("label"), F.max("old").alias("old")).where("old is not null"))
        changed = new.where("label <> old").limit(1).count()
        labels = new.select("id", "label")
        if not changed:
            return labels


def strong_labels(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(id, component): smallest-member labels of the strong components.

    Nodes without an edge in or out of what is left are components of their own. The largest id is spread forward; a node that keeps its own is a
    root, and what reaches it under its colour is its component. These go, and the rest is done again.
    """
    edges = scratch.keep(edges.select("src", "dst").where("src <> dst"))
    nodes = scratch.keep(edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct())
    done: list[DataFrame] = []
    while True:
        if nodes.isEmpty():
            break
        while True:  # peel
            inner = scratch.keep(edges.select(F.col("src").alias("id")).intersect(edges.select("dst")))
            lone = scratch.keep(nodes.join(inner, "id", "left_anti"))
            if lone.isEmpty():
                break
            done.append(lone.select("id", F.col("id").alias("component")))
            nodes = inner
            edges = scratch.keep(edges.join(inner.withColumnRenamed("id", "src"), "src", "left_semi").join(inner.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst"))
        if nodes.isEmpty():
            break
        colour = _spread(edges, nodes.withColumn("label", F.col("id")), scratch, F.max)
        a, b = colour.select(F.col("id").alias("src"), F.col("label").alias("c1")), colour.select(F.col("id").alias("dst"), F.col("label").alias("c2"))
        same = scratch.keep(edges.join(a, "src").join(b, "dst").where("c1 = c2").select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        reach = _spread(same, colour.select("id", F.when(F.col("id") == F.col("label"), F.col("id")).otherwise(F.lit(-1)).alias("label")), scratch, F.max)
        found = scratch.keep(reach.where("label >= 0").select("id", F.col("label").alias("root")))
        least = found.groupBy("root").agg(F.min("id").alias("component"))
        done.append(scratch.keep(found.join(least, "root").select("id", "component")))
        nodes = scratch.keep(nodes.join(found, "id", "left_anti"))
        edges = scratch.keep(edges.join(nodes.withColumnRenamed("id", "src"), "src", "left_semi").join(nodes.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst"))
    out = done[0]
    for more in done[1:]:
        out = out.union(more)
    return out


# ---------------------------------------------------------------- search in rounds
def seed_rows(queries: DataFrame, d: int, p: int, n: int, seed: int) -> DataFrame:
    """(qid, nid): the distinct random start nodes of each query."""
    return queries.select("qid", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(0), F.lit(p * d - 1)), lambda j: buffer.seed_id(F.col("qid"), j.cast("long"), seed, n)))).alias("nid"))


def search(vecs: DataFrame, adj: DataFrame, queries: DataFrame, params: SearchParams, scratch: Scratch, *, n: int, d: int) -> tuple[DataFrame, DataFrame]:
    """The walk as one plan a round: HIT rows and (qid, n_dist, rounds).

    A frontier of ids is joined to the adjacency lists and to the vectors each round, so a round costs a scan of both; it pays
    for batches about as large as the graph. State is one row for each query; the driver sees the number of open ones.
    """
    entry = "array<struct<dist:double,nid:long,expanded:boolean>>"
    v = vecs.select(F.col("id").alias("nid"), "vec")
    q = queries.select("qid", F.col("vec").alias("qvec"))

    def evaluated(rows: DataFrame) -> DataFrame:
        scored = rows.join(v, "nid").join(q, "qid").select("qid", F.struct(distance(params.metric, "vec", "qvec").alias("dist"), "nid", F.lit(False).alias("expanded")).alias("c"))
        return scored.groupBy("qid").agg(F.collect_list("c").alias("cand"))

    start = evaluated(seed_rows(queries, d, params.p, n, params.seed))
    state = scratch.keep(start.select("qid", F.slice(F.array_sort("cand"), 1, params.M).cast(entry).alias("top"), F.transform("cand", lambda c: c["nid"]).alias("seen"), F.size("cand").cast("long").alias("n_dist"), F.lit(0).alias("rounds"), F.lit(False).alias("done")))
    for step in range(1, params.rounds + 1):
        waiting = F.filter("top", lambda e: ~e["expanded"])
        going = state.where(~F.col("done")).withColumn("front", F.transform(F.slice(waiting, 1, params.p), lambda e: e["nid"]))
        going = going.where(F.size("front") > 0)
        steps = going.select("qid", "seen", F.explode("front").alias("id")).join(adj, "id").groupBy("qid").agg(F.flatten(F.collect_list("nbrs")).alias("next"), F.first("seen").alias("seen"))
        cand = evaluated(steps.select("qid", F.explode(F.array_except("next", "seen")).alias("nid")))
        old = F.transform("top", lambda e: F.struct(e["dist"].alias("dist"), e["nid"].alias("nid"), (e["expanded"] | F.array_contains("front", e["nid"])).alias("expanded")))
        rows = going.join(cand, "qid", "left").withColumn("cand", F.coalesce("cand", F.array().cast(entry)))
        top = buffer.merge_top(old, F.col("cand"), params.M)
        if params.visited == "forget":  # a forgotten entry may come again: the list keeps the expanded one
            kept = F.filter("cand", lambda c: ~F.exists("top", lambda e: e["nid"] == c["nid"]))
            top = buffer.merge_top(old, kept, params.M)
        rows = rows.withColumn("new", top)
        if params.visited == "forget" and step % params.every == 0:
            seen = F.transform("new", lambda e: e["nid"])
        else:
            seen = F.concat("seen", F.transform("cand", lambda c: c["nid"]))
        ids = lambda c: F.transform(c, lambda e: e["nid"])
        ended = ~F.exists("new", lambda e: ~e["expanded"])
        if params.stop == "unchanged":
            ended = ended | (ids("new") == ids("top"))
        rows = rows.select("qid", F.col("new").alias("top"), seen.alias("seen"), (F.col("n_dist") + F.size("cand")).alias("n_dist"), F.lit(step).alias("rounds"), ended.alias("done"))
        left = state.join(rows.select("qid"), "qid", "left_anti").withColumn("done", F.lit(True))
        state = scratch.keep(rows.unionByName(left))
        if state.where("not done").limit(1).count() == 0:
            break
    hits = state.select("qid", F.posexplode(F.slice("top", 1, params.k)).alias("rnk", "e")).select("qid", (F.col("rnk") + 1).alias("rnk"), "e.nid", "e.dist")
    return hits, state.select("qid", "n_dist", "rounds")


# ---------------------------------------------------------------- measures
def recall_join(hits: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, recall): share of the true ids that were found."""
    found = truth.select("qid", "nid").join(hits.select("qid", "nid", F.lit(1).alias("hit")), ["qid", "nid"], "left")
    return found.groupBy("qid").agg((F.count("hit") / F.count("*")).alias("recall"))


def recall_intersect(hits: DataFrame, truth: DataFrame) -> DataFrame:
    both = hits.select("qid", "nid").intersect(truth.select("qid", "nid")).groupBy("qid").agg(F.count("*").alias("n"))
    return truth.groupBy("qid").agg(F.count("*").alias("all")).join(both, "qid", "left").select("qid", (F.coalesce("n", F.lit(0)) / F.col("all")).alias("recall"))


def missed(hits: DataFrame, truth: DataFrame) -> DataFrame:
    return truth.select("qid", "nid").exceptAll(hits.select("qid", "nid"))


