"""Registered queries of the engine: each a plan over the given tables, most with SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from neargraph.functions import buffer
from neargraph.functions.distance import cosine, l2, unit
from neargraph.operators import linking, relational as rel, shard
from neargraph.params import SearchParams, table_size
from neargraph.plans import oracle_text as sql
from neargraph.plans import workloads
from neargraph.runtime import Scratch, prepare
from neargraph.sources import index_store
from neargraph.sources import vectors as src
from neargraph.streaming import online

K, D, BASE = 10, 8, 24

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(oracle: str | None = None):
    def add(f):
        _QUERIES[f.__name__] = f
        if oracle:
            _SQL[f.__name__] = oracle
        return f

    return add


def _vecs(spark, sf_dir) -> DataFrame:
    return src.vectors(spark, sf_dir)


def _asked(vecs: DataFrame, step: int = 10) -> DataFrame:
    return vecs.where(F.pmod("id", F.lit(step)) == 0).select(F.col("id").alias("qid"), "vec")


def _rounded(hits: DataFrame) -> DataFrame:
    return hits.select("qid", "rnk", "nid", F.round("dist", 6).alias("dist"))


def _base(spark, sf_dir, degree: int = BASE) -> DataFrame:
    """Exact base edges, written once, as every later step reads them several times."""
    scratch = Scratch(spark, "base")
    return scratch.keep(rel.base_edges(_vecs(spark, sf_dir), degree, scratch))


def _index(spark, sf_dir, d: int = 16, shards: int = 1, base: str = "exact", **options) -> DataFrame:
    return Scratch(spark, "index").keep(shard.build(shard.assign(_vecs(spark, sf_dir), shards), d, base=base, **options))


# ---------------------------------------------------------------- exact search
@query(sql.hits("l2", 10))
def q_exact_knn(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return _rounded(rel.exact_knn(v, _asked(v), K))


@query(sql.hits("cosine", 10))
def q_exact_knn_cosine(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return _rounded(rel.exact_knn(v, _asked(v), K, metric="cosine"))


@query(sql.hits("ip", 10))
def q_exact_knn_ip(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return _rounded(rel.exact_knn(v, _asked(v), K, metric="ip"))


@query(sql.hits("l2", 10))
def q_exact_knn_blocked(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return _rounded(shard.search_exact(v, _asked(v), K))


@query(sql.knn_graph(BASE))
def q_knn_graph(spark, sf_dir):
    return rel.knn_edges(_vecs(spark, sf_dir), BASE).select("src", "rank", "dst")


@query(sql.filtered())
def q_filtered_knn_pre(spark, sf_dir):
    rows = src.table(spark, sf_dir, "embeddings").where("label = 3").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return _rounded(rel.exact_knn(rows, _asked(_vecs(spark, sf_dir)), K))


@query()
def q_filtered_knn_post(spark, sf_dir):
    """Search for more, filter by label, keep k; and how many queries fell short."""
    labels = src.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("nid"), "label")
    hits = shard.search(_index(spark, sf_dir), _asked(_vecs(spark, sf_dir)), SearchParams(k=128, M=128), mode="solo")
    kept = rel.per_query(hits.join(labels, "nid").where("label = 3").select("qid", "nid", "dist"), 5)
    return kept.groupBy("qid").agg(F.count("*").alias("found"), (F.lit(5) - F.count("*")).alias("short"))


@query(sql.near_pairs(1.25))
def q_near_pairs(spark, sf_dir):
    """Other vectors within a distance of each query."""
    v = _vecs(spark, sf_dir)
    return rel.radius_join(v, _asked(v), 1.25).where("qid <> nid").select("qid", "nid", F.round("dist", 6).alias("dist"))


@query()
def q_descent_rounds(spark, sf_dir):
    """Neighbour descent as one plan a round, over the whole table: share of exact neighbours found by rank."""
    v = _vecs(spark, sf_dir)
    found = rel.descent_edges(v, BASE, Scratch(spark, "descent"))
    hits = found.select(F.col("src").alias("qid"), F.col("dst").alias("nid"))
    truth = rel.knn_edges(v, BASE).select(F.col("src").alias("qid"), "rank", F.col("dst").alias("nid"))
    return truth.join(hits.withColumn("hit", F.lit(1)), ["qid", "nid"], "left").groupBy("rank").agg((F.count("hit") / F.count("*")).alias("recall"))


@query(sql.radius(1.0))
def q_radius_join(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return rel.radius_join(v, _asked(v), 1.0).select("qid", "nid", F.round("dist", 6).alias("dist"))


@query(sql.lateral())
def q_lateral_topk(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    q = _asked(v, 50).select("qid", F.col("vec").alias("qvec"))
    inner = v.select(F.col("id").alias("nid"), l2("vec", F.col("qvec").outer()).alias("dist")).orderBy("dist", "nid").limit(3)
    return q.lateralJoin(inner).select("qid", "nid", F.round("dist", 6).alias("dist"))


@query(sql.hits("l2", 10))
def q_sql_exact_knn(spark, sf_dir):
    _vecs(spark, sf_dir).createOrReplaceTempView("vectors")
    return spark.sql("""
        SELECT qid, CAST(rnk AS INT) AS rnk, nid, round(dist, 6) AS dist FROM (
          SELECT qid, nid, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, nid) AS rnk FROM (
            SELECT q.id AS qid, v.id AS nid, sqrt(aggregate(zip_with(CAST(v.vec AS ARRAY<DOUBLE>), CAST(q.vec AS ARRAY<DOUBLE>), (a, b) -> (a - b) * (a - b)), 0D, (s, x) -> s + x)) AS dist
            FROM vectors v CROSS JOIN (SELECT * FROM vectors WHERE id % 10 = 0) q)) WHERE rnk <= 10""")


@query()
def q_sql_udtf(spark, sf_dir):
    from neargraph.functions import udfs

    udfs.register(spark)
    index = _index(spark, sf_dir)
    lists = index.agg(F.sort_array(F.collect_list(F.struct("id", "vec", "nbrs"))).alias("r")).select(F.col("r.id").alias("ids"), F.col("r.vec").alias("vectors"), F.col("r.nbrs").alias("neighbours"))
    lists.createOrReplaceTempView("one_shard")
    _asked(_vecs(spark, sf_dir), 100).createOrReplaceTempView("asked")
    return spark.sql("SELECT t.qid, t.rnk, t.nid, round(t.dist, 6) AS dist FROM asked a CROSS JOIN one_shard s, LATERAL ann_search(a.qid, a.vec, s.ids, s.vectors, s.neighbours, 5, 64) t")


@query(sql.udf_check())
def q_udf_distance(spark, sf_dir):
    """The vectorised function against the column expression."""
    from neargraph.functions.udfs import l2_udf

    prepare(spark)
    v = _vecs(spark, sf_dir)
    pairs = v.alias("a").join(v.alias("b"), F.col("b.id") == F.col("a.id") + 1)
    return pairs.agg(F.count("*").alias("n"), (F.max(F.abs(l2_udf("a.vec", "b.vec") - l2("a.vec", "b.vec"))) < 1e-6).alias("same"))


# ---------------------------------------------------------------- graph construction
@query(sql.detours("rank", BASE))
def q_detour_rank(spark, sf_dir):
    return rel.detours(_base(spark, sf_dir))


@query(sql.detours("dist", BASE))
def q_detour_distance(spark, sf_dir):
    return rel.detours(_base(spark, sf_dir), "distance")


@query(sql.pruned("rank", BASE, D))
def q_rank_pruned(spark, sf_dir):
    return rel.reordered(_base(spark, sf_dir), D)


@query(sql.pruned("dist", BASE, D))
def q_distance_pruned(spark, sf_dir):
    return rel.reordered(_base(spark, sf_dir), D, "distance")


@query(sql.detour_free(BASE))
def q_detour_prune_baseline(spark, sf_dir):
    return rel.detour_free(rel.detours(_base(spark, sf_dir)))


@query(sql.reversed_edges(BASE, D))
def q_reversed(spark, sf_dir):
    return rel.reversed_edges(rel.reordered(_base(spark, sf_dir), D), D)


@query(sql.interleaved("rank", BASE, D))
def q_uniform_graph(spark, sf_dir):
    return rel.uniform_graph(_base(spark, sf_dir), D)


@query(sql.interleaved("none", BASE, D))
def q_reverse_only(spark, sf_dir):
    return rel.uniform_graph(_base(spark, sf_dir), D, reorder="none")


@query(sql.interleaved("dist", BASE, D))
def q_uniform_graph_distance(spark, sf_dir):
    return rel.uniform_graph(_base(spark, sf_dir), D, reorder="distance")


@query(sql.interleaved("rank", BASE, D))
def q_uniform_graph_kernel(spark, sf_dir):
    """The same graph built by the shard kernel in one task."""
    index = shard.build(shard.assign(_vecs(spark, sf_dir), 1), D, base="exact")
    return rel.to_edges(index.select("id", "nbrs"))


@query(sql.recall_flag())
def q_nn_descent(spark, sf_dir):
    """Share of exact neighbours that neighbour descent finds, against 0.95."""

    def study(_, ids, v):
        from neargraph.operators import local

        x = local.prepared(v, "l2")
        found, _, _ = local.sure_descent(x, 24, least=0.95)
        yield "descent", int(len(x)), bool(local.recall(found, local.exact_graph(x, 24)[0]) >= 0.95)

    return workloads.in_task(_vecs(spark, sf_dir), study, "config string, n long, recall_ok boolean")


# ---------------------------------------------------------------- reachability and measures
def _variant_edges(spark, sf_dir, d: int, base: int) -> dict[str, DataFrame]:
    edges = _base(spark, sf_dir, base)
    scratch = Scratch(spark, "variants")
    cut = scratch.keep(rel.reordered(edges, d))
    plain = scratch.keep(edges.where(F.col("rank") < d).select("src", "rank", "dst"))
    return {"knn": plain, "reorder_only": cut, "reverse_only": scratch.keep(rel.interleaved(plain, d)), "both": scratch.keep(rel.interleaved(cut, d))}


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query(sql.two_hop(BASE, D))
def q_two_hop(spark, sf_dir):
    rows = [rel.two_hop(e).agg(F.round(F.avg("reached"), 6).alias("mean_two_hop")).select(F.lit(name).alias("variant"), "mean_two_hop", F.lit(rel.two_hop_max(D)).cast("int").alias("max_possible")) for name, e in _variant_edges(spark, sf_dir, D, BASE).items()]
    return _union(rows)


@query(sql.weak(12, 4))
def q_weak_cc(spark, sf_dir):
    rows = []
    for name, e in _variant_edges(spark, sf_dir, 4, 12).items():
        labels = linking.components(e.select(F.col("src").alias("a"), F.col("dst").alias("b")), Scratch(spark, "weak"))
        rows.append(labels.agg(F.count_distinct("component_id").alias("components")).select(F.lit(name).alias("variant"), "components"))
    return _union(rows)


@query(sql.strong(12, 4))
def q_strong_cc(spark, sf_dir):
    rows = []
    for name, e in _variant_edges(spark, sf_dir, 4, 12).items():
        if name in ("knn", "both"):
            rows.append(rel.strong_labels(e, Scratch(spark, "strong")).agg(F.count_distinct("component").alias("components")).select(F.lit(name).alias("variant"), "components"))
    return _union(rows)


@query(sql.degrees(BASE, D))
def q_degrees(spark, sf_dir):
    return rel.degrees(rel.uniform_graph(_base(spark, sf_dir), D)).withColumn("avg_in", F.round("avg_in", 6)).withColumn("avg_out", F.round("avg_out", 6))


@query(sql.indegree(BASE))
def q_indegree(spark, sf_dir):
    return _base(spark, sf_dir).groupBy("dst").agg(F.count("*").alias("n_in"))


@query(sql.top_hubs(BASE))
def q_top_hubs(spark, sf_dir):
    return _base(spark, sf_dir).groupBy("dst").agg(F.count("*").alias("n_in")).orderBy(F.desc("n_in"), "dst").limit(10)


# ---------------------------------------------------------------- search
@query(sql.seed_points())
def q_seed_points(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    n = v.count()
    rows = _asked(v).select("qid", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(15)), lambda j: buffer.seed_id(F.col("qid"), j.cast("long"), 1, n))).alias("j", "nid"), "vec")
    return rows.join(v.select(F.col("id").alias("nid"), F.col("vec").alias("x")), "nid").select("qid", "j", "nid", F.round(l2("vec", "x"), 6).alias("dist"))


@query(sql.merge_topm())
def q_merge_topm(spark, sf_dir):
    """Best 8 of two lists of 8: neighbours with even and with odd ids."""
    v = _vecs(spark, sf_dir)
    hits = rel.exact_knn(v, _asked(v), 16)
    entry = F.struct("dist", "nid")
    lists = hits.groupBy("qid").agg(F.array_sort(F.collect_list(F.when(F.col("nid") % 2 == 0, entry))).alias("even"), F.array_sort(F.collect_list(F.when(F.col("nid") % 2 != 0, entry))).alias("odd"))
    top = buffer.merge_top(F.slice("even", 1, 8), F.slice("odd", 1, 8), 8)
    return lists.select("qid", F.posexplode(top).alias("rnk", "e")).select("qid", (F.col("rnk") + 1).alias("rnk"), "e.nid")


def _exhaustive(**options) -> SearchParams:
    return SearchParams(k=K, M=500, p=64, max_iter=40, **options)


@query(sql.hits("l2", 50))
def q_search_relational(spark, sf_dir):
    """A list as long as the graph expands every node: the walk in rounds then gives the exact answer."""
    v = _vecs(spark, sf_dir)
    adj = Scratch(spark, "graph").keep(rel.to_lists(rel.uniform_graph(_base(spark, sf_dir), D)))
    n = v.count()
    params = SearchParams(k=K, M=n, p=64, max_iter=n)
    hits, _ = rel.search(v, adj, _asked(v, 50), params, Scratch(spark, "walk"), n=n, d=D)
    return _rounded(hits)


def _kernel_exact(mode: str, **options):
    def run(spark, sf_dir):
        v = _vecs(spark, sf_dir)
        n = v.count()
        params = SearchParams(k=K, M=n, max_iter=2 * n, **options)
        return _rounded(shard.search(_index(spark, sf_dir), _asked(v, 50), params, mode=mode))

    return run


for _name, _mode, _options in (("q_search_solo_exhaustive", "solo", {"p": 16}), ("q_search_forgetting_exhaustive", "solo", {"p": 16, "visited": "forget", "bits": 13}), ("q_search_team_exhaustive", "team", {"walkers": 4})):
    _QUERIES[_name], _SQL[_name] = _kernel_exact(_mode, **_options), sql.hits("l2", 50)


#: A list much shorter than the graph, so that the walk decides what is found.
TRACE = SearchParams(k=K, M=16)


def _traced(counts: bool = False, **options):
    """The kernel's walk over the relational graph, hits or counters."""

    def run(spark, sf_dir):
        v = _vecs(spark, sf_dir)
        scratch = Scratch(spark, "traced")
        cut = scratch.keep(rel.reordered(_base(spark, sf_dir), D))  # read by both halves of the lists
        lists = rel.to_lists(rel.interleaved(cut, D))
        index = scratch.keep(v.join(lists, "id").select(F.lit(0).alias("shard_id"), "id", "vec", "nbrs"))
        found = shard.search(index, _asked(v, 20), replace(TRACE, **options), mode="solo", counters=counts)
        return found if counts else _rounded(found)

    return run


def _trace_sql(counts: bool = False, **options) -> str:
    return sql.trace(TRACE.M, K, D, BASE, 20, rounds=TRACE.rounds, counts=counts, **options)


_QUERIES |= {
    "q_search_trace": _traced(), "q_search_trace_counts": _traced(True), "q_search_trace_unchanged": _traced(stop="unchanged"), "q_search_trace_table": _traced(expanded="table"), "q_search_trace_table_counts": _traced(True, expanded="table"), "q_forget_reset": _traced(visited="forget", bits=13),
    "q_forget_reset_counts": _traced(True, visited="forget", bits=13), "q_forget_every_third_counts": _traced(True, visited="forget", bits=13, every=3),
}
_SQL |= {
    "q_search_trace": _trace_sql(), "q_search_trace_counts": _trace_sql(True), "q_search_trace_unchanged": _trace_sql(unchanged=True), "q_search_trace_table": _trace_sql(), "q_search_trace_table_counts": _trace_sql(True), "q_forget_reset": _trace_sql(every=1),
    "q_forget_reset_counts": _trace_sql(True, every=1), "q_forget_every_third_counts": _trace_sql(True, every=3),
}


@query(_trace_sql())
def q_search_trace_relational(spark, sf_dir):
    """The same walk as one plan a round."""
    v = _vecs(spark, sf_dir)
    adj = Scratch(spark, "graph").keep(rel.to_lists(rel.uniform_graph(_base(spark, sf_dir), D)))
    hits, _ = rel.search(v, adj, _asked(v, 20), TRACE, Scratch(spark, "walk"), n=v.count(), d=D)
    return _rounded(hits)


@query(_trace_sql())
def q_search_trace_packed(spark, sf_dir):
    """The same walk over an index of one packed row a shard, which a search reads without a shuffle."""
    v = _vecs(spark, sf_dir)
    lists = rel.to_lists(rel.uniform_graph(_base(spark, sf_dir), D))
    index = shard.pack(v.join(lists, "id").select(F.lit(0).alias("shard_id"), "id", "vec", "nbrs"))
    return _rounded(shard.search(Scratch(spark, "packed").keep(index), _asked(v, 20), TRACE, mode="solo"))


@query(sql.angle_spread(BASE, 16))
def q_baseline_angle_spread(spark, sf_dir):
    """Edges of the angle-spread graph on exact lists."""

    def study(_, ids, v):
        from neargraph.operators import baselines, local

        x = local.prepared(v, "l2")
        graph = baselines.angle_spread(local.exact_graph(x, min(BASE, len(x) - 1))[0], x, 16)
        for src, pos in zip(*(graph >= 0).nonzero(), strict=True):
            yield int(ids[src]), int(pos), int(ids[graph[src, pos]])

    return workloads.in_task(_vecs(spark, sf_dir), study, "src long, pos int, dst long")


@query(sql.distance_percentiles())
def q_distance_percentiles(spark, sf_dir):
    """Spread of the distances of the nearest, second, ... neighbour."""
    v = _vecs(spark, sf_dir)
    hits = rel.exact_knn(v, _asked(v), K)
    return hits.groupBy("rnk").agg(*(F.round(F.percentile("dist", F.lit(p / 100)), 6).alias(f"p{p}") for p in (5, 50, 95, 99)))


@query(sql.config_map())
def q_config_map(spark, sf_dir):
    """Settings of the searches that events ask for, each a map with the event's own k, and how many have each value."""
    names = ("M", "k", "merge", "metric", "p", "stop", "visited")
    asked = src.table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").alias("own")).agg(F.count("*").alias("n"))
    usual = {name: F.lit(str(getattr(SearchParams(), name))) for name in names}
    settings = F.create_map(*(x for name, value in usual.items() for x in (F.lit(name), F.coalesce("own", value) if name == "k" else value)))
    return asked.select(F.explode(settings).alias("name", "value"), "n").groupBy("name", "value").agg(F.sum("n").alias("n"))


def _recall_query(mode: str, shards: int = 1, least: float = 0.95, d: int = 16, **options):
    def run(spark, sf_dir):
        v = _vecs(spark, sf_dir)
        q = _asked(v)
        truth = Scratch(spark, "truth").keep(rel.exact_knn(v, q, K))
        index, params = _index(spark, sf_dir, d=d, shards=shards), SearchParams(k=K, **({"M": 64} | options))
        hits = shard.search(index, q, params, mode=mode) if shards == 1 else shard.sure_search(index, q, params, least=least, mode=mode)
        got = rel.recall_join(hits, truth).agg(F.count("*").alias("n_queries"), F.avg("recall").alias("r")).withColumn("k", F.lit(K))
        check = truth.agg(F.sum("nid").alias("truth_checksum"))
        return got.crossJoin(check).select("n_queries", "k", "truth_checksum", (F.col("r") >= least).alias("recall_ok"))

    return run


for _name, _mode, _options in (
    ("q_search_solo", "solo", {}), ("q_search_team", "team", {"M": 32}), ("q_search_forgetting", "solo", {"visited": "forget"}), ("q_search_fp16", "solo", {"dtype": "fp16"}), ("q_search_unchanged", "solo", {"stop": "unchanged", "least": 0.9}),
    ("q_search_sharded", "solo", {"shards": 4}), ("q_search_auto", "auto", {}), ("q_search_team_private", "team", {"M": 32, "sharing": "private"}), ("q_search_partition_merge", "solo", {"merge": "partition"}),
):
    _QUERIES[_name], _SQL[_name] = _recall_query(_mode, **_options), sql.recall_row()


@query(sql.same_hits())
def q_forget_equals_full(spark, sf_dir):
    """Forgetting costs distances and changes no result: hits that differ, and whether distances grew."""
    q, index = _asked(_vecs(spark, sf_dir)), _index(spark, sf_dir)
    full, less = SearchParams(k=K), SearchParams(k=K, visited="forget", bits=10)
    a, b = shard.search(index, q, full, mode="solo").select("qid", "nid"), shard.search(index, q, less, mode="solo").select("qid", "nid")
    n = a.exceptAll(b).agg(F.count("*").alias("differing"))
    c, d = (shard.search(index, q, p, mode="solo", counters=True).agg(F.sum("n_dist").alias(x)) for p, x in ((full, "full"), (less, "forget")))
    return n.crossJoin(c).crossJoin(d).select("differing", (F.col("forget") >= F.col("full")).alias("not_fewer_distances"))


@query(sql.hits("l2", 10))
def q_sharded_exact(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    index = _index(spark, sf_dir, d=8, shards=4)
    return _rounded(shard.exact(index, _asked(v), K))


@query(sql.index_rows())
def q_index_roundtrip(spark, sf_dir):
    """A stored index reads back; the filter on the shard reads one folder."""
    scratch = Scratch(spark, "store")
    index_store.save(_index(spark, sf_dir, d=8, shards=4), scratch.base, metric="l2")
    stored = index_store.open_index(spark, scratch.base)
    return stored.where("shard_id = 2").select("id", "shard_id", F.size("nbrs").alias("degree"))


@query(sql.parent_flag())
def q_parent_flag(spark, sf_dir):
    v = src.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"))
    flagged = buffer.mark(F.col("id"))
    return v.select("id", flagged.alias("flagged"), buffer.is_marked(flagged).alias("marked"), buffer.strip(flagged).alias("stripped"))


# ---------------------------------------------------------------- rules and cost model
@query(sql.MODE_RULE)
def q_mode_rule(spark, sf_dir):
    """Mode of the searches of each minute of events, by how many came in it."""
    minutes = src.table(spark, sf_dir, "events").groupBy(F.date_trunc("minute", "ts")).agg(F.count("*").cast("int").alias("batch"))
    return workloads.d2_mode_rule(minutes)


@query(sql.LOAD_EFFICIENCY)
def q_load_efficiency(spark, sf_dir):
    return workloads.b1_lanes(_vecs(spark, sf_dir))


@query(sql.TABLE_SIZE)
def q_table_size(spark, sf_dir):
    """Slots for walks of as many rounds as line items have pieces."""
    rounds = src.table(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("int").alias("rounds")).where("rounds > 0").distinct()
    grid = rounds.select("rounds", F.explode(F.array(F.lit(1), F.lit(2))).alias("p")).select("rounds", "p", F.explode(F.array(F.lit(16), F.lit(32), F.lit(80))).alias("d"))
    return grid.withColumn("slots", F.udf(lambda i, p, d: table_size(i, p, d), "int")("rounds", "p", "d"))


@query(sql.COST_MODEL)
def q_cost_model(spark, sf_dir):
    """Cost of the graphs of each label's vectors at two degrees."""
    from neargraph.functions.cost import distance_reorder, memory

    def cost(dim, n, d):
        size = memory(n, dim, d, base=3 * d)
        return distance_reorder(n, 3 * d), size["distance_table_entries"], size["vectors"]

    rows = src.table(spark, sf_dir, "embeddings").where("embedding is not null").groupBy("label", F.size("embedding").alias("dim")).agg(F.count("*").alias("n"))
    sets = rows.select("label", "dim", "n", F.explode(F.array(F.lit(32), F.lit(48))).alias("d"))
    costs = F.udf(cost, "distances long, table_entries long, vector_bytes long")("dim", "n", "d")
    return sets.withColumn("cost", costs).select("label", "dim", "n", "d", "cost.*")


@query(sql.DEGREE_PARAMS)
def q_degree_params(spark, sf_dir):
    """Degrees for the graph that leads from suppliers to the parts they shipped, by nation."""
    from neargraph.params import aligned_degree, initial_degree

    edges = src.table(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey").distinct()
    suppliers = src.table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("nation"))
    out = edges.groupBy("l_suppkey").agg(F.count("*").alias("n_out")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    mean = out.groupBy("nation").agg((F.sum("n_out") / F.count("*")).alias("average"))
    return mean.withColumn("aligned", F.udf(lambda a: aligned_degree(a), "int")("average")).withColumn("base", F.udf(lambda a: initial_degree(a), "int")("aligned"))


# ---------------------------------------------------------------- recall reports
def _partial(spark, sf_dir):
    """Exact answers, and those from the first of four shards alone as a fixed approximation."""
    v = _vecs(spark, sf_dir)
    q = _asked(v)
    return rel.exact_knn(v, q, K), rel.exact_knn(v.where("id % 4 = 0"), q, K)


@query(sql.recall_parts("SELECT qid, recall FROM recall"))
def q_recall_join(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    return rel.recall_join(hits, truth)


@query(sql.recall_parts("SELECT qid, recall FROM recall"))
def q_recall_intersect(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    return rel.recall_intersect(hits, truth)


@query(sql.recall_parts("SELECT qid, nid FROM truth EXCEPT ALL SELECT qid, nid FROM hits"))
def q_missed(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    return rel.missed(hits, truth)


@query(sql.recall_parts("SELECT coalesce(t.qid, h.qid) AS qid, coalesce(t.nid, h.nid) AS nid, t.nid IS NOT NULL AS in_truth, h.nid IS NOT NULL AS in_hits FROM truth t FULL JOIN hits h ON t.qid = h.qid AND t.nid = h.nid"))
def q_truth_vs_hits(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    t, h = truth.select("qid", "nid", F.lit(True).alias("t")), hits.select("qid", "nid", F.lit(True).alias("h"))
    return t.join(h, ["qid", "nid"], "full").select("qid", "nid", F.col("t").isNotNull().alias("in_truth"), F.col("h").isNotNull().alias("in_hits"))


def _grouped_recall(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    labels = src.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("qid"), "label")
    return rel.recall_join(hits, truth).join(labels, "qid").select("label", (F.col("qid") % 3).alias("part"), "recall")


@query(sql.grouped_recall("CUBE (label, part)"))
def q_recall_cube(spark, sf_dir):
    return _grouped_recall(spark, sf_dir).cube("label", "part").agg(F.round(F.avg("recall"), 9).alias("recall"))


@query(sql.grouped_recall("ROLLUP (label, part)"))
def q_recall_rollup(spark, sf_dir):
    return _grouped_recall(spark, sf_dir).rollup("label", "part").agg(F.round(F.avg("recall"), 9).alias("recall"))


@query(sql.grouped_recall("GROUPING SETS ((label), (part), ())"))
def q_recall_gsets(spark, sf_dir):
    _grouped_recall(spark, sf_dir).createOrReplaceTempView("graded")
    return spark.sql("SELECT label, part, round(avg(recall), 9) AS recall FROM graded GROUP BY GROUPING SETS ((label), (part), ())")


@query(sql.reach_pivot(BASE, D))
def q_reach_pivot(spark, sf_dir):
    rows = [rel.two_hop(e).select(F.lit(name).alias("variant"), (F.col("src") % 10).alias("part"), "reached") for name, e in _variant_edges(spark, sf_dir, D, BASE).items() if name in ("knn", "both")]
    return _union(rows).groupBy("part").pivot("variant", ["both", "knn"]).agg(F.max("reached"))


@query(sql.running_recall())
def q_running_recall(spark, sf_dir):
    truth, hits = _partial(spark, sf_dir)
    one = Window.orderBy("qid").rowsBetween(Window.unboundedPreceding, Window.currentRow)  # one row for each query of a report
    return rel.recall_join(hits, truth).select("qid", F.round(F.avg("recall").over(one), 9).alias("running"))


@query(sql.gap_lag())
def q_gap_lag(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    w = Window.partitionBy("qid").orderBy("rnk")
    return rel.exact_knn(v, _asked(v), K).withColumn("gap", F.round(F.col("dist") - F.lag("dist").over(w), 6)).select("qid", "rnk", "gap", F.first("nid").over(w).alias("nearest"), F.lead("nid").over(w).alias("following"))


@query(sql.rank_family())
def q_rank_family(spark, sf_dir):
    w = Window.partitionBy("dst_part").orderBy("n_in")
    rows = _base(spark, sf_dir).groupBy("dst").agg(F.count("*").alias("n_in")).withColumn("dst_part", F.col("dst") % 5)
    return rows.select("dst", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("drk"), F.round(F.percent_rank().over(w), 9).alias("prk"))


@query(sql.topk_window())
def q_topk_window(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return rel.exact_knn(v, _asked(v), 3).select("qid", "rnk", "nid")


@query(sql.union_shards())
def q_union_shards(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    q = _asked(v)
    parts = [rel.exact_knn(v.where(F.col("id") % 2 == s), q, K).select("qid", "nid", "dist") for s in (0, 1)]
    return rel.per_query(parts[0].unionByName(parts[1]), K).select("qid", "rnk", "nid")


@query(sql.semi("SEMI"))
def q_semi_hits(spark, sf_dir):
    truth, _ = _partial(spark, sf_dir)
    chosen = src.table(spark, sf_dir, "embeddings").where("label < 3").select(F.col("vec_id").alias("nid"))
    return truth.join(chosen, "nid", "left_semi").select("qid", "nid")


@query(sql.semi("ANTI"))
def q_anti_unseen(spark, sf_dir):
    truth, _ = _partial(spark, sf_dir)
    seen = src.table(spark, sf_dir, "embeddings").where("label < 3").select(F.col("vec_id").alias("nid"))
    return truth.join(seen, "nid", "left_anti").select("qid", "nid")


@query(sql.centroids())
def q_centroids(spark, sf_dir):
    rows = src.table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("place", "x"))
    return rows.groupBy("label", "place").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


# ---------------------------------------------------------------- features and other tables
@query(sql.unit_norm())
def q_unit_norm(spark, sf_dir):
    v = _vecs(spark, sf_dir)
    return v.select("id", F.round(F.element_at(unit("vec"), 1), 6).alias("first"), F.round(cosine("vec", "vec"), 6).alias("to_itself"))


@query(sql.DENSE_IDS)
def q_dense_ids(spark, sf_dir):
    rows = src.lineitem_features(spark, sf_dir)
    return src.dense_ids(rows, ["l_orderkey", "l_linenumber", *src.LINE_FEATURES]).select("id", "l_orderkey", "l_linenumber", "l_quantity")


@query(sql.ZSCORE)
def q_zscore(spark, sf_dir):
    rows = src.zscores(src.lineitem_features(spark, sf_dir), src.LINE_FEATURES)
    return rows.groupBy("l_linenumber").agg(F.count("*").alias("n"), *(F.round(F.sum(f"z_{c}"), 4).alias(f"z_{c}") for c in src.LINE_FEATURES[:3]))


@query(sql.LINEITEM_KNN)
def q_lineitem_knn(spark, sf_dir):
    v = src.lineitem_vectors(spark, sf_dir)
    return shard.search_exact(v, v.where("id % 2000 = 0").select(F.col("id").alias("qid"), "vec"), 5).select("qid", "rnk", F.round("dist", 3).alias("dist"))


@query(sql.DOC_NGRAMS)
def q_doc_ngrams(spark, sf_dir):
    docs = src.table(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id", "text")
    return src.gram_counts(docs, "doc_id", F.col("text"), 64).groupBy("bucket").agg(F.sum("n").alias("n"))


@query(sql.EVENTS_HOURLY)
def q_events_hourly(spark, sf_dir):
    return src.table(spark, sf_dir, "events").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"))


@query(sql.EVENTS_JSON)
def q_events_json_k(spark, sf_dir):
    return src.table(spark, sf_dir, "events").select(F.get_json_object("props", "$.k").cast("long").alias("k")).groupBy("k").agg(F.count("*").alias("n"))


@query(sql.ASOF)
def q_asof_query(spark, sf_dir):
    """Each view with the latest purchase of its user before it: both kinds in one ordered pass."""
    e = src.table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("purchase_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'view'").select("event_id", "user_id", "purchase_id")


@query(sql.INTERVAL)
def q_interval_events(spark, sf_dir):
    return online.views_to_purchases(src.table(spark, sf_dir, "events"), "24 HOURS")


@query(sql.ROLLING)
def q_rolling_events(spark, sf_dir):
    micros = F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts").cast("timestamp_ntz"))
    # the nearest second, halves to the even one
    e = src.table(spark, sf_dir, "events").select("event_id", "user_id", F.rint(micros / 1e6).cast("long").alias("s"))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query(sql.TUMBLING)
def q_stream_tumbling(spark, sf_dir):
    return online.tumbling(src.table(spark, sf_dir, "events"))


@query(sql.SLIDING)
def q_stream_sliding(spark, sf_dir):
    return online.sliding(src.table(spark, sf_dir, "events"))


@query(sql.SESSIONS)
def q_stream_session(spark, sf_dir):
    return online.sessions(src.table(spark, sf_dir, "events")).select("user_id", "start", "n")


@query(sql.SLOPE)
def q_scaling_slope(spark, sf_dir):
    """Power with which the price of an order grows with its line items."""
    line = src.table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n"), F.sum("l_extendedprice").alias("s")).where("s > 0")
    return line.agg(F.round(F.regr_slope(F.log("s"), F.log("n")), 6).alias("slope"))


@query(sql.PAGE_LENGTH)
def q_page_text_len(spark, sf_dir):
    pages = src.table(spark, sf_dir, "pages")
    return pages.select("page_id", F.length(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), r"\s+", " ")).cast("long").alias("n"))


@query()
def q_label_vote(spark, sf_dir):
    return workloads.d3_vote(spark, sf_dir)


@query()
def q_benchmark_docs(spark, sf_dir):
    return workloads.d3_benchmark(spark, sf_dir)


# ---------------------------------------------------------------- experiment workloads
def _study(f, **options):
    return lambda spark, sf_dir: f(_vecs(spark, sf_dir), **options)


def _documents(f, dim: int, **options):
    return lambda spark, sf_dir: f(workloads.sets(spark, sf_dir, (dim,))[f"documents_{dim}"], **options)


_QUERIES |= {
    "q_w_a1_reachability": _study(workloads.a1_reachability),
    "q_w_a1_reachability_d4": _study(workloads.a1_reachability, d=4),
    "q_w_a1_reachability_documents": _documents(workloads.a1_reachability, 200),
    "q_w_a2_reorder_time": _study(workloads.a2_reorder_time),
    "q_w_a2_reorder_time_documents": _documents(workloads.a2_reorder_time, 200),
    "q_w_b1_lanes": _study(workloads.b1_lanes),
    "q_w_b1_team_size": _study(workloads.b1_team_size),
    "q_w_b1_team_size_documents": _documents(workloads.b1_team_size, 960, batch=1024, sizes=(1, 16, 64, 256, 1024)),
    "q_w_a3_reorder_quality": _study(workloads.a3_reorder_quality),
    "q_w_a3_reorder_quality_documents": _documents(workloads.a3_reorder_quality, 200),
    "q_w_b2_visited": _study(workloads.b2_visited),
    "q_w_b2_visited_documents": _documents(workloads.b2_visited, 200),
    "q_w_b3_modes": _study(workloads.b3_modes),
    "q_w_b3_modes_documents": _documents(workloads.b3_modes, 200, batch=1000),
    "q_w_c1_build_time": _study(workloads.c1_build_time),
    "q_w_c1_build_time_documents": _documents(workloads.c1_build_time, 200),
    "q_w_c2_graph_quality": _study(workloads.c2_graph_quality),
    "q_w_c2_graph_quality_documents": _documents(workloads.c2_graph_quality, 256),
    "q_w_c2_graph_quality_documents_960": _documents(workloads.c2_graph_quality, 960),
    "q_w_c3_large_batch": _study(workloads.c3_large_batch),
    "q_w_c4_single_query": _study(workloads.c4_single_query),
    "q_w_c5_scaling": lambda spark, sf_dir: workloads.c5_scaling(Scratch(spark, "line").keep(src.lineitem_vectors(spark, sf_dir))),
    "q_w_best_of_parallelism": _study(workloads.best_of_parallelism),
    "q_w_baselines": _study(workloads.baseline_graphs),
    "q_w_d1_degree": _study(workloads.d1_degree),
    "q_w_d4_compressed": _study(workloads.d4_compressed),
}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Graph of fixed degree over the embeddings, searched for every tenth vector, with recall against the exact answer."""
    prepare(spark)
    v = _vecs(spark, sf_dir)
    q = _asked(v)
    hits = shard.search(shard.build(shard.assign(v, 1), 16), q, SearchParams(k=K), mode="solo")
    return rel.recall_join(hits, rel.exact_knn(v, q, K))


def _prepared(f):
    return lambda spark, sf_dir: f(prepare(spark), sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: _prepared(f) for name, f in _QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


