"""DuckDB SQL of the queries that SQL can express on whole tables, written from the definitions."""

from __future__ import annotations


TOP_K = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id
), r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
  FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""

QUALITY_RULES = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws, string_split(t, chr(10)) AS ls FROM d
), g AS (
  SELECT doc_id, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS x
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)
), rep AS (
  SELECT doc_id, x FROM g GROUP BY doc_id, x HAVING count(*) > 1
), cov AS (
  SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words
  FROM (SELECT g.doc_id, g.i, unnest([0, 1, 2]) AS k FROM g JOIN rep USING (doc_id, x)) GROUP BY doc_id
), ln AS (
  SELECT doc_id, l, len(lw) AS n, regexp_matches(l, '[^\x20\x09-\x0D]') AS full_line,
    NOT regexp_matches(l, '[.!?…:;。！？]["''”’»)\]]*[\x20\x09-\x0D]*$')
    OR 100 * len(list_filter(lw, lambda x: x LIKE '%!!')) > 50 * len(lw)
    OR 100 * len(list_filter(lw, lambda x: regexp_matches(x, '[#*$%&<>]{2}$'))) > 30 * len(lw)
    OR (regexp_matches(l, '[|»›•·]') AND 100 * len(list_filter(lw, lambda x: regexp_matches(x, '^[|»›•·>/]+$'))) > 20 * len(lw))
    OR regexp_matches(lower(l), 'all rights reserved|cookie policy|privacy policy|terms of use|terms of service|enable javascript|sign in to|subscribe to our|click here|skip to content|lorem ipsum|powered by|share this') AS broken
  FROM (SELECT doc_id, l, regexp_extract_all(l, '[^\x20\x09-\x0D]+') AS lw FROM (SELECT doc_id, unnest(ls) AS l FROM w))
), lines AS (
  SELECT doc_id, count(*) FILTER (full_line) - count(DISTINCT l) FILTER (full_line) AS n_dup_lines,
         count(*) FILTER (full_line AND broken) AS n_failed_lines, coalesce(sum(n) FILTER (full_line AND broken), 0) AS n_lost_words
  FROM ln GROUP BY doc_id
), b AS (
  SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
         CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words,
         CAST(n_failed_lines AS BIGINT) AS n_failed_lines, CAST(n_lost_words AS BIGINT) AS n_lost_words
  FROM w JOIN lines USING (doc_id) LEFT JOIN cov USING (doc_id)
), f AS (
  SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM b
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       (NOT base_failed AND n_words > n_lost_words AND 100 * n_lost_words <= 30 * n_words) AS kept, n_failed_lines, n_lost_words
FROM f
"""


def oracles() -> dict[str, str]:
    return {"op7_ball_tree": TOP_K, "op8_quality_rules": QUALITY_RULES}
