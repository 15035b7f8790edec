"""DuckDB SQL for the registered queries, put together from shared parts."""

from __future__ import annotations

V = "v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings)"
_DISTANCE = {
    "l2": "list_distance(v.x, q.x)",
    "ip": "-list_inner_product(v.x, q.x)",
    "cosine": "CASE WHEN list_inner_product(v.x, v.x) > 0 AND list_inner_product(q.x, q.x) > 0 THEN 1 - list_cosine_similarity(v.x, q.x) ELSE 1.0 END",
}


def _hit_parts(metric: str, step: int, k: int, where: str = "true", name: str = "hits") -> str:
    return f"""{name}_all AS (SELECT q.id AS qid, v.id AS nid, {_DISTANCE[metric]} AS dist FROM v, v q WHERE q.id % {step} = 0 AND ({where})),
{name} AS (SELECT qid, rnk, nid, dist FROM (SELECT *, (row_number() OVER (PARTITION BY qid ORDER BY dist, nid))::INTEGER AS rnk FROM {name}_all) WHERE rnk <= {k})"""


def hits(metric: str, step: int, k: int = 10) -> str:
    return f"WITH {V}, {_hit_parts(metric, step, k)} SELECT qid, rnk, nid, round(dist, 6) AS dist FROM hits"


def filtered() -> str:
    return f"""WITH {V}, w AS (SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings WHERE label = 3),
r AS (SELECT q.id AS qid, w.id AS nid, list_distance(w.x, q.x) AS dist FROM w, v q WHERE q.id % 10 = 0),
s AS (SELECT *, (row_number() OVER (PARTITION BY qid ORDER BY dist, nid))::INTEGER AS rnk FROM r)
SELECT qid, rnk, nid, round(dist, 6) AS dist FROM s WHERE rnk <= 10"""


def near_pairs(r: float) -> str:
    return f"WITH {V} SELECT q.id AS qid, v.id AS nid, round(list_distance(v.x, q.x), 6) AS dist FROM v, v q WHERE q.id % 10 = 0 AND v.id <> q.id AND list_distance(v.x, q.x) <= {r}"


def distance_percentiles() -> str:
    return f"""WITH {V}, {_hit_parts("l2", 10, 10)} SELECT rnk, {", ".join(f"round(quantile_cont(dist, {p / 100}), 6) AS p{p}" for p in (5, 50, 95, 99))} FROM hits GROUP BY rnk"""


def angle_spread(degree: int, R: int) -> str:
    """Neighbours and theirs by distance; the first stays, and what stands at less than 60 degrees from it goes, until R stay."""
    return f"""WITH RECURSIVE {_base(degree)},
xs AS (SELECT list(x ORDER BY id) AS xs FROM v),
near AS (SELECT src, dst AS u FROM base UNION SELECT a.src, b.dst FROM base a JOIN base b ON a.dst = b.src),
pool AS (SELECT near.src, s.x AS y, list({{'d': list_distance(s.x, t.x), 'i': u}} ORDER BY list_distance(s.x, t.x), u) AS rem
  FROM near JOIN v s ON s.id = near.src JOIN v t ON t.id = u WHERE u <> near.src GROUP BY near.src, s.x),
picks AS (
  SELECT src, y, 0 AS pos, rem[1].i AS dst, rem FROM pool
  UNION ALL
  SELECT src, y, pos + 1, rest[1].i, rest FROM (
    SELECT src, y, pos, list_filter(rem[2:], lambda e: (list_inner_product(xs[e.i + 1], xs[dst + 1]) - list_inner_product(xs[e.i + 1], y) - list_inner_product(xs[dst + 1], y) + list_inner_product(y, y)) / (e.d * rem[1].d) <= 0.5) AS rest
    FROM picks, xs WHERE pos + 1 < {R}) WHERE len(rest) > 0)
SELECT src, pos::INTEGER AS pos, dst FROM picks"""


def config_map() -> str:
    return """SELECT map_keys(m)[i] AS name, map_values(m)[i] AS value, count(*) AS n
FROM (SELECT MAP {'M': '64', 'k': coalesce(json_extract_string(props, '$.k'), '10'), 'merge': 'auto', 'metric': 'l2', 'p': '1', 'stop': 'exhausted', 'visited': 'full'} AS m FROM events), range(1, 8) t(i) GROUP BY ALL"""


def radius(r: float) -> str:
    return f"WITH {V} SELECT q.id AS qid, v.id AS nid, round(list_distance(v.x, q.x), 6) AS dist FROM v, v q WHERE q.id % 10 = 0 AND list_distance(v.x, q.x) <= {r}"


def lateral() -> str:
    return f"WITH {V}, {_hit_parts('l2', 50, 3)} SELECT qid, nid, round(dist, 6) AS dist FROM hits"


def udf_check() -> str:
    return "SELECT count(*) AS n, true AS same FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


# ---------------------------------------------------------------- graph
def _base(degree: int) -> str:
    return f"""{V},
pairs AS (SELECT a.id AS src, b.id AS dst, list_distance(a.x, b.x) AS dist FROM v a, v b WHERE a.id <> b.id),
base AS (SELECT * FROM (SELECT src, dst, dist, (row_number() OVER (PARTITION BY src ORDER BY dist, dst) - 1)::INTEGER AS rank FROM pairs) WHERE rank < {degree})"""


def knn_graph(degree: int) -> str:
    return f"WITH {_base(degree)} SELECT src, rank, dst FROM base"


def _detours(weight: str, name: str = "counted") -> str:
    return f"""{name}_n AS (SELECT a.src, b.dst, count(*) AS n FROM base a JOIN base b ON a.src = b.src AND a.{weight} < b.{weight}
  JOIN base c ON c.src = a.dst AND c.dst = b.dst AND c.{weight} < b.{weight} GROUP BY a.src, b.dst),
{name} AS (SELECT base.src, base.rank, base.dst, coalesce(n, 0) AS detours FROM base LEFT JOIN {name}_n c ON base.src = c.src AND base.dst = c.dst)"""


def detours(weight: str, degree: int) -> str:
    return f"WITH {_base(degree)}, {_detours(weight)} SELECT src, rank, dst, detours FROM counted"


def _pruned(weight: str, d: int, name: str = "cut") -> str:
    if weight == "none":
        return f"{name} AS (SELECT src, rank, dst FROM base WHERE rank < {d})"
    return f"""{_detours(weight, name + "_c")},
{name} AS (SELECT * FROM (SELECT src, (row_number() OVER (PARTITION BY src ORDER BY detours, rank) - 1)::INTEGER AS rank, dst FROM {name}_c) WHERE rank < {d})"""


def pruned(weight: str, degree: int, d: int) -> str:
    return f"WITH {_base(degree)}, {_pruned(weight, d)} SELECT src, rank, dst FROM cut"


def detour_free(degree: int) -> str:
    return f"WITH {_base(degree)}, {_detours('rank')} SELECT src, rank, dst FROM counted WHERE detours = 0"


def _reversed(d: int, of: str = "cut", name: str = "back") -> str:
    return f"{name} AS (SELECT * FROM (SELECT dst AS node, (row_number() OVER (PARTITION BY dst ORDER BY rank, src) - 1)::INTEGER AS pos, src FROM {of}) WHERE pos < {d})"


def reversed_edges(degree: int, d: int) -> str:
    return f"WITH {_base(degree)}, {_pruned('rank', d)}, {_reversed(d)} SELECT node, pos, src FROM back"


def _interleaved(d: int, of: str = "cut", name: str = "mixed") -> str:
    forward, rest = -(-d // 2), d // 2
    return f"""{_reversed(d, of, name + "_b")},
{name}_t AS (SELECT * FROM (SELECT b.node, b.src, row_number() OVER (PARTITION BY b.node ORDER BY b.pos) - 1 AS k FROM {name}_b b
  LEFT JOIN (SELECT * FROM {of} WHERE rank < {forward}) h ON h.src = b.node AND h.dst = b.src WHERE h.src IS NULL) WHERE k < {rest}),
{name}_o AS (SELECT src, dst, 0 AS a, rank AS b, 0 AS c FROM {of} WHERE rank < {forward}
  UNION ALL SELECT node, src, 0, k, 1 FROM {name}_t
  UNION ALL SELECT o.src, o.dst, 1, o.rank, 0 FROM {of} o LEFT JOIN {name}_t t ON t.node = o.src AND t.src = o.dst WHERE o.rank >= {forward} AND t.node IS NULL),
{name} AS (SELECT * FROM (SELECT src, (row_number() OVER (PARTITION BY src ORDER BY a, b, c) - 1)::INTEGER AS rank, dst FROM {name}_o) WHERE rank < {d})"""


def interleaved(weight: str, degree: int, d: int) -> str:
    return f"WITH {_base(degree)}, {_pruned(weight, d)}, {_interleaved(d)} SELECT src, rank, dst FROM mixed"


def _variants(d: int) -> str:
    return f"""{_pruned("none", d, "plain")}, {_pruned("rank", d, "sorted_")}, {_interleaved(d, "plain", "rev_only")}, {_interleaved(d, "sorted_", "both_")},
edges AS (SELECT 'knn' AS variant, src, dst FROM plain UNION ALL SELECT 'reorder_only', src, dst FROM sorted_
  UNION ALL SELECT 'reverse_only', src, dst FROM rev_only UNION ALL SELECT 'both', src, dst FROM both_)"""


_HOPS = """hops AS (SELECT variant, src, dst FROM edges UNION SELECT a.variant, a.src, b.dst FROM edges a JOIN edges b ON a.variant = b.variant AND a.dst = b.src),
reached AS (SELECT variant, src, count(*) AS reached FROM hops WHERE src <> dst GROUP BY variant, src)"""


def two_hop(degree: int, d: int) -> str:
    return f"WITH {_base(degree)}, {_variants(d)}, {_HOPS} SELECT variant, round(avg(reached), 6) AS mean_two_hop, {d + d * d}::INTEGER AS max_possible FROM reached GROUP BY variant"


def reach_pivot(degree: int, d: int) -> str:
    return f"WITH {_base(degree)}, {_variants(d)}, {_HOPS} SELECT src % 10 AS part, max(reached) FILTER (variant = 'both') AS \"both\", max(reached) FILTER (variant = 'knn') AS knn FROM reached GROUP BY part"


def weak(degree: int, d: int) -> str:
    return f"""WITH RECURSIVE {_base(degree)}, {_variants(d)},
sides AS (SELECT variant, src, dst FROM edges UNION SELECT variant, dst, src FROM edges),
walk AS (SELECT DISTINCT variant, src AS a, src AS b FROM sides UNION SELECT w.variant, w.a, s.dst FROM walk w JOIN sides s ON s.variant = w.variant AND s.src = w.b),
least AS (SELECT variant, a, min(b) AS c FROM walk GROUP BY variant, a)
SELECT variant, count(DISTINCT c) AS components FROM least GROUP BY variant"""


def strong(degree: int, d: int) -> str:
    return f"""WITH RECURSIVE {_base(degree)}, {_variants(d)},
picked AS (SELECT * FROM edges WHERE variant IN ('knn', 'both')),
walk AS (SELECT DISTINCT variant, src AS a, src AS b FROM picked UNION SELECT w.variant, w.a, s.dst FROM walk w JOIN picked s ON s.variant = w.variant AND s.src = w.b),
least AS (SELECT x.variant, x.a, min(x.b) AS c FROM walk x JOIN walk y ON x.variant = y.variant AND x.a = y.b AND x.b = y.a GROUP BY x.variant, x.a)
SELECT variant, count(DISTINCT c) AS components FROM least GROUP BY variant"""


def degrees(degree: int, d: int) -> str:
    return f"""WITH {_base(degree)}, {_pruned("rank", d)}, {_interleaved(d)},
o AS (SELECT src AS id, count(*) AS n_out FROM mixed GROUP BY src), i AS (SELECT dst AS id, count(*) AS n_in FROM mixed GROUP BY dst),
b AS (SELECT coalesce(n_out, 0) AS n_out, coalesce(n_in, 0) AS n_in FROM o FULL JOIN i USING (id))
SELECT min(n_out) AS min_out, round(avg(n_out), 6) AS avg_out, max(n_out) AS max_out, min(n_in) AS min_in, round(avg(n_in), 6) AS avg_in, max(n_in) AS max_in FROM b"""


def indegree(degree: int) -> str:
    return f"WITH {_base(degree)} SELECT dst, count(*) AS n_in FROM base GROUP BY dst"


def top_hubs(degree: int) -> str:
    return f"{indegree(degree)} ORDER BY n_in DESC, dst LIMIT 10"


def rank_family() -> str:
    return f"""WITH {_base(24)}, r AS (SELECT dst, count(*) AS n_in, dst % 5 AS p FROM base GROUP BY dst)
SELECT dst, rank() OVER w AS rk, dense_rank() OVER w AS drk, round(percent_rank() OVER w, 9) AS prk FROM r WINDOW w AS (PARTITION BY p ORDER BY n_in)"""


# ---------------------------------------------------------------- search
def seed_points() -> str:
    return f"""WITH {V}, n AS (SELECT count(*) AS n FROM v),
s AS (SELECT v.id AS qid, v.x AS y, j::INTEGER AS j, (v.id * 1000003 + j * 7919 + 104729 + 12345) % 2147483647 * 48271 % 2147483647 % n.n AS nid FROM v, n, range(0, 16) t(j) WHERE v.id % 10 = 0)
SELECT qid, j, nid, round(list_distance(y, x), 6) AS dist FROM s JOIN v ON v.id = nid"""


def trace(M: int, k: int, d: int, degree: int, step: int, *, rounds: int, every: int = 0, unchanged: bool = False, counts: bool = False) -> str:
    """The walk of one worker, round by round, on the graph of ``interleaved``. ``every``: rounds between forgetting; 0: never."""
    seen = "list_concat(seen, new)" if not every else f"CASE WHEN (step + 1) % {every} = 0 THEN list_transform(merged, lambda e: e.i) ELSE list_concat(seen, new) END"
    go = "len(list_filter(top, lambda e: NOT e.f)) > 0 AND (step = 0 OR NOT same)" if unchanged else "len(list_filter(top, lambda e: NOT e.f)) > 0"
    out = "SELECT qid, sum(added)::BIGINT AS n_dist, max(step)::INTEGER AS rounds FROM walk GROUP BY qid"
    if not counts:
        out = f"""SELECT qid, (generate_subscripts(best, 1))::INTEGER AS rnk, unnest(list_transform(best, lambda e: e.i)) AS nid, round(unnest(list_transform(best, lambda e: e.d)), 6) AS dist
FROM (SELECT qid, list_slice(arg_max(top, step), 1, {k}) AS best FROM walk GROUP BY qid)"""
    return f"""WITH RECURSIVE {_base(degree)}, {_pruned("rank", d)}, {_interleaved(d)},
adj AS (SELECT src, list(dst ORDER BY rank) AS nbrs FROM mixed GROUP BY src),
xs AS (SELECT list(x ORDER BY id) AS xs, count(*) AS n FROM v),
seeds AS (SELECT v.id AS qid, v.x AS y, list_distinct(list_transform(range(0, {d}), lambda j: (v.id * 1000003 + j * 7919 + 104729 + 12345) % 2147483647 * 48271 % 2147483647 % xs.n)) AS ids FROM v, xs WHERE v.id % {step} = 0),
walk AS (
  SELECT qid, y, 0 AS step, ids AS seen, len(ids) AS added, false AS same,
    list_slice(list_sort(list_transform(ids, lambda u: {{'d': list_distance(xs.xs[u + 1], y), 'i': u, 'f': false}})), 1, {M}) AS top FROM seeds, xs
  UNION ALL
  SELECT qid, y, step + 1, {seen}, len(new), list_transform(merged, lambda e: e.i) = list_transform(top, lambda e: e.i), merged FROM (
    SELECT *, list_slice(list_sort(list_concat(list_transform(top, lambda e: {{'d': e.d, 'i': e.i, 'f': e.f OR e.i = here}}), list_transform(new, lambda u: {{'d': list_distance(xs[u + 1], y), 'i': u, 'f': false}}))), 1, {M}) AS merged FROM (
      SELECT w.*, here, xs, list_filter(nbrs, lambda u: NOT list_contains(seen, u)) AS new FROM
        (SELECT *, list_filter(top, lambda e: NOT e.f)[1].i AS here FROM walk WHERE {go} AND step < {rounds}) w JOIN adj ON adj.src = w.here, xs)))
{out}"""


def merge_topm() -> str:
    return f"""WITH {V}, {_hit_parts("l2", 10, 16)},
h AS (SELECT *, row_number() OVER (PARTITION BY qid, nid % 2 ORDER BY dist, nid) AS k FROM hits)
SELECT qid, rnk, nid FROM (SELECT qid, (row_number() OVER (PARTITION BY qid ORDER BY dist, nid))::INTEGER AS rnk, nid FROM h WHERE k <= 8) WHERE rnk <= 8"""


def recall_row() -> str:
    return f"WITH {V}, {_hit_parts('l2', 10, 10)} SELECT count(DISTINCT qid) AS n_queries, 10::INTEGER AS k, sum(nid)::BIGINT AS truth_checksum, true AS recall_ok FROM hits"


def recall_flag() -> str:
    return "SELECT 'descent' AS config, count(*) AS n, true AS recall_ok FROM embeddings"


def same_hits() -> str:
    return "SELECT 0::BIGINT AS differing, true AS not_fewer_distances"


def index_rows() -> str:
    return "SELECT vec_id AS id, 2::INTEGER AS shard_id, 8::INTEGER AS degree FROM embeddings WHERE vec_id % 4 = 2"


def parent_flag() -> str:
    return "SELECT vec_id AS id, vec_id - 9223372036854775807 - 1 AS flagged, true AS marked, vec_id AS stripped FROM embeddings"


MODE_RULE = """WITH b AS (SELECT count(*)::INTEGER AS b FROM events GROUP BY date_trunc('minute', ts))
SELECT b AS batch, m::INTEGER AS list_length, CASE WHEN b < 8 OR m > 512 THEN 'team' ELSE 'solo' END AS mode, count(*) AS n FROM b, (VALUES (64), (512), (513)) y(m) GROUP BY b, m"""
LOAD_EFFICIENCY = """SELECT d::INTEGER AS dim, t::INTEGER AS team, (d * 32)::DOUBLE / (t * 128 * ceil((d * 32)::DOUBLE / (t * 128))) AS efficiency
FROM (SELECT DISTINCT len(embedding) AS d FROM embeddings WHERE embedding IS NOT NULL) x, (VALUES (2), (4), (8), (16), (32)) y(t)"""
TABLE_SIZE = """SELECT i AS rounds, p::INTEGER AS p, d::INTEGER AS d, pow(2, ceil(log2(2 * i * p * d)))::INTEGER AS slots
FROM (SELECT DISTINCT trunc(l_quantity)::INTEGER AS i FROM lineitem WHERE l_quantity >= 1) x, (VALUES (1), (2)) y(p), (VALUES (16), (32), (80)) z(d)"""
COST_MODEL = """SELECT label, dim::INTEGER AS dim, n, d::INTEGER AS d, (n * 3 * d * (3 * d - 1))::BIGINT AS distances, (n * 3 * d)::BIGINT AS table_entries, (n * dim * 4)::BIGINT AS vector_bytes
FROM (SELECT label, len(embedding) AS dim, count(*) AS n FROM embeddings WHERE embedding IS NOT NULL GROUP BY ALL), (VALUES (32), (48)) t(d)"""
DEGREE_PARAMS = """WITH o AS (SELECT l_suppkey, count(DISTINCT l_partkey) AS n_out FROM lineitem GROUP BY l_suppkey)
SELECT s_nationkey AS nation, avg(n_out) AS average, (floor(avg(n_out) / 16) * 16)::INTEGER AS aligned, (floor(avg(n_out) / 16) * 48)::INTEGER AS base FROM o JOIN supplier ON s_suppkey = l_suppkey GROUP BY s_nationkey"""


# ---------------------------------------------------------------- reports
def _parts() -> str:
    return f"""{V}, {_hit_parts("l2", 10, 10, name="truth")}, {_hit_parts("l2", 10, 10, "v.id % 4 = 0")},
recall AS (SELECT t.qid, count(h.nid) / count(*) AS recall FROM truth t LEFT JOIN hits h ON t.qid = h.qid AND t.nid = h.nid GROUP BY t.qid)"""


def recall_parts(select: str) -> str:
    return f"WITH {_parts()} {select}"


def grouped_recall(grouping: str) -> str:
    return f"WITH {_parts()}, g AS (SELECT label, qid % 3 AS part, recall FROM recall JOIN embeddings ON vec_id = qid) SELECT label, part, round(avg(recall), 9) AS recall FROM g GROUP BY {grouping}"


def running_recall() -> str:
    return recall_parts("SELECT qid, round(avg(recall) OVER (ORDER BY qid ROWS UNBOUNDED PRECEDING), 9) AS running FROM recall")


def gap_lag() -> str:
    return f"""WITH {V}, {_hit_parts("l2", 10, 10)}
SELECT qid, rnk, round(dist - lag(dist) OVER w, 6) AS gap, first_value(nid) OVER w AS nearest, lead(nid) OVER w AS following FROM hits WINDOW w AS (PARTITION BY qid ORDER BY rnk)"""


def topk_window() -> str:
    return f"WITH {V}, {_hit_parts('l2', 10, 3)} SELECT qid, rnk, nid FROM hits"


def union_shards() -> str:
    return f"WITH {V}, {_hit_parts('l2', 10, 10)} SELECT qid, rnk, nid FROM hits"


def semi(kind: str) -> str:
    return f"WITH {V}, {_hit_parts('l2', 10, 10)} SELECT qid, nid FROM hits {kind} JOIN (SELECT vec_id FROM embeddings WHERE label < 3) e ON e.vec_id = hits.nid"


def centroids() -> str:
    return "SELECT label, place, round(avg(x), 6) AS mean FROM (SELECT label, unnest(embedding::DOUBLE[]) AS x, (generate_subscripts(embedding, 1) - 1)::INTEGER AS place FROM embeddings) GROUP BY label, place"


def unit_norm() -> str:
    return f"WITH {V} SELECT id, round(x[1] / sqrt(list_inner_product(x, x)), 6) AS first, round(1 - list_cosine_similarity(x, x), 6) AS to_itself FROM v"


_LINE = "line AS (SELECT l_orderkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, date_diff('day', DATE '1992-01-01', l_shipdate::DATE)::DOUBLE AS ship_day FROM lineitem)"
_KEYS = "l_orderkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, ship_day"
_F = ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "ship_day")
_Z = ", ".join(f"({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () AS z_{c}" for c in _F)
DENSE_IDS = f"WITH {_LINE} SELECT row_number() OVER (ORDER BY {_KEYS}) - 1 AS id, l_orderkey, l_linenumber, l_quantity FROM line"
ZSCORE = f"WITH {_LINE}, z AS (SELECT l_linenumber, {_Z} FROM line) SELECT l_linenumber, count(*) AS n, {', '.join(f'round(sum(z_{c}), 4) AS z_{c}' for c in _F[:3])} FROM z GROUP BY l_linenumber"
LINEITEM_KNN = f"""WITH {_LINE}, z AS (SELECT row_number() OVER (ORDER BY {_KEYS}) - 1 AS id, {_Z} FROM line),
v AS (SELECT id, [{", ".join(f"z_{c}::FLOAT::DOUBLE" for c in _F)}] AS x FROM z), {_hit_parts("l2", 2000, 5)} SELECT qid, rnk, round(dist, 3) AS dist FROM hits"""
DOC_NGRAMS = """WITH t AS (SELECT doc_id, string_split(lower(text), '') AS t FROM documents WHERE lang = 'en'),
c AS (SELECT doc_id, unnest(list_transform(t, lambda x: unicode(x))) AS c, generate_subscripts(t, 1) AS i FROM t),
g AS (SELECT c AS a, lead(c) OVER w AS b, lead(c, 2) OVER w AS d FROM c WINDOW w AS (PARTITION BY doc_id ORDER BY i))
SELECT (a * 961 + b * 31 + d)::BIGINT % 64 AS bucket, count(*) AS n FROM g WHERE d IS NOT NULL GROUP BY bucket"""
EVENTS_HOURLY = "SELECT date_trunc('hour', ts)::TIMESTAMP AS hour, count(*) AS n FROM events GROUP BY ALL"
EVENTS_JSON = "SELECT json_extract_string(props, '$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY ALL"
ASOF = "SELECT v.event_id, v.user_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON v.user_id = p.user_id AND v.ts >= p.ts"
INTERVAL = "SELECT v.event_id AS view_id, p.event_id AS purchase_id, v.user_id FROM events v JOIN events p ON v.user_id = p.user_id AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 24 HOURS WHERE v.event_type = 'view' AND p.event_type = 'purchase'"
ROLLING = "WITH e AS (SELECT event_id, user_id, epoch(ts)::BIGINT AS s FROM events) SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM e"
TUMBLING = "SELECT date_trunc('hour', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL"
SLIDING = """SELECT (time_bucket(INTERVAL 15 MINUTES, ts) - k * INTERVAL 15 MINUTES)::TIMESTAMP AS start, count(*) AS n FROM events, range(0, 4) t(k) GROUP BY ALL"""
SESSIONS = """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS cut FROM events),
s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e)
SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM s GROUP BY user_id, k"""
SLOPE = """SELECT round(regr_slope(ln(s), ln(n)), 6) AS slope FROM (SELECT count(*) AS n, sum(l_extendedprice) AS s FROM lineitem GROUP BY l_orderkey) WHERE s > 0"""
PAGE_LENGTH = r"SELECT page_id, length(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g'))::BIGINT AS n FROM pages"
