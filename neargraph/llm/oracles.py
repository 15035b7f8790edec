"""DuckDB SQL for the queries of this subpackage that SQL can express.

Left out, and tested otherwise: token counts and byte-level BPE (a vocabulary file; exact against plain merging and a round
trip), HTML extraction (a parser; expected texts), toxicity (a trained network; held-out accuracy), source mixing (random
rounding; its guarantees), importance resampling and SimHash (hash functions SQL lacks; brute force).
"""

from __future__ import annotations

OP1 = """
WITH RECURSIVE good AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS x FROM embeddings
  WHERE vec_id IS NOT NULL AND label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0 AND len(list_filter(embedding, lambda e: e <> 0)) > 0),
link AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE list_cosine_similarity(a.x, b.x) >= 0.93),
reach AS (SELECT vec_id AS a, vec_id AS b FROM embeddings WHERE vec_id IS NOT NULL UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a),
best AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a),
degree AS (SELECT a, count(*) AS n FROM link GROUP BY a)
SELECT e.vec_id, coalesce(d.n, 0)::BIGINT AS n_links, b.component_id, coalesce(e.vec_id = b.component_id, false) AS kept, 1.0::DOUBLE AS audit_recall
FROM embeddings e LEFT JOIN best b ON e.vec_id = b.a LEFT JOIN degree d ON e.vec_id = d.a
"""

OP2 = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS w FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0),
s AS (
  SELECT q.vec_id AS query_id, v.vec_id, list_inner_product(q.w, v.w)::BIGINT AS score
  FROM v q JOIN v ON q.vec_id <> v.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS k FROM s)
SELECT query_id, k::INTEGER AS rank, vec_id, score FROM r WHERE k <= 5
"""

OP6 = r"""
WITH t AS (
  SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS w
  FROM (SELECT DISTINCT doc_id, text FROM documents WHERE doc_id IS NOT NULL AND text IS NOT NULL)),
win AS (
  SELECT doc_id, s, md5(array_to_string(w[s + 1 : s + 50], ' ')) AS k
  FROM (SELECT doc_id, w, unnest(range(0, len(w) - 49)) AS s FROM t WHERE len(w) >= 50)),
twice AS (SELECT k, min({'d': doc_id, 's': s}) AS f FROM win GROUP BY k HAVING count(*) > 1),
judged AS (SELECT doc_id, s, {'d': doc_id, 's': s} > f AS later, f.d AS first_doc FROM win JOIN twice USING (k)),
broken AS (SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY doc_id, later ORDER BY s) <= 50 THEN 0 ELSE 1 END AS cut FROM judged),
runs AS (SELECT *, sum(cut) OVER (PARTITION BY doc_id, later ORDER BY s) AS run FROM broken)
SELECT doc_id, min(s)::INTEGER AS start_word, (max(s) + 50)::INTEGER AS end_word, later,
       CASE WHEN later THEN min(first_doc) ELSE doc_id END AS first_doc_id
FROM runs GROUP BY doc_id, later, run
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_embedding_dedup": OP1, "op2_exact_topk": OP2, "op6_suffix_dedup": OP6}
