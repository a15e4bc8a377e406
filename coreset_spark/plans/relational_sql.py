"""DuckDB SQL of the queries on operators around the methods."""

from __future__ import annotations


#: Longest common subsequences by a fold over one text's words of the table's last row, a running maximum of which is the next.
ROUGE = """
WITH RECURSIVE p AS (SELECT conv_id, turn, lower(text) AS a, lower(nt) AS b FROM (SELECT conv_id, turn, role, text, lead(role) OVER w AS nr, lead(text) OVER w AS nt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant'),
t AS (SELECT conv_id, turn, list_filter(regexp_split_to_array(a, '\\s+'), lambda x: x <> '') AS a, list_filter(regexp_split_to_array(b, '\\s+'), lambda x: x <> '') AS b FROM p),
f AS (SELECT conv_id, turn, a, b, 0 AS i, list_transform(range(0, len(b) + 1), lambda z: 0) AS r FROM t UNION ALL
SELECT conv_id, turn, a, b, i + 1, list_reduce(list_transform(range(1, len(b) + 1), lambda j: [greatest(r[j + 1], CASE WHEN a[i + 1] = b[j] THEN r[j] + 1 ELSE 0 END)]), lambda x, y: list_append(x, greatest(x[-1], y[1])), [0]) FROM f WHERE i < len(a)),
l AS (SELECT conv_id, turn, len(a) AS n, len(b) AS m, r[-1] AS c FROM f WHERE i = len(a))
SELECT conv_id, turn, CASE WHEN c > 0 THEN round(c / n, 6) ELSE 0.0 END AS precision, CASE WHEN c > 0 THEN round(c / m, 6) ELSE 0.0 END AS recall, CASE WHEN c > 0 THEN round(2 * (c / n) * (c / m) / (c / n + c / m), 6) ELSE 0.0 END AS f1 FROM l"""


def oracles() -> dict[str, str]:
    from .oracles import sql

    picks = lambda turn, n: f"SELECT vec_id AS sample_id FROM embeddings ORDER BY md5('42:{turn}:' || vec_id), vec_id LIMIT {n}"
    mixed = "(SELECT doc_id, source, lang FROM documents WHERE substr(md5('42:0:' || doc_id), 1, 2) < '1a')"
    trip = "(SELECT vec_id FROM embeddings ORDER BY md5('42:0:' || vec_id), vec_id LIMIT 50)"
    order = "PARTITION BY user_id ORDER BY ts, event_id"
    ngrams = (
        "WITH tok AS (SELECT doc_id, list_filter(string_split(lower(text), ' '), lambda x: x <> '') AS w FROM documents), pos AS (SELECT doc_id, unnest(w) AS token, unnest(list_prepend('', w[:-2])) AS before FROM tok WHERE len(w) > 0), "
        "uni AS (SELECT token, (count(*) + 1) / (SELECT count(*) + count(DISTINCT token) FROM pos) AS q FROM pos GROUP BY token), ctx AS (SELECT before, count(*) AS c FROM pos GROUP BY before), "
        "bi AS (SELECT before, token, count(*) / any_value(c) AS b, any_value(q) AS q FROM pos JOIN ctx USING (before) JOIN uni USING (token) GROUP BY before, token), "
        "sq AS (SELECT before, sum(power(0.5 * b + 0.5 * q, 2) - power(0.5 * q, 2)) + (SELECT sum(power(0.5 * q, 2)) FROM uni) AS p2 FROM bi GROUP BY before), "
        "told AS (SELECT doc_id, 0.5 * b + 0.5 * q AS p, p2 FROM pos JOIN bi USING (before, token) JOIN sq USING (before))"
    )
    vectors = (
        "WITH ttok AS (SELECT doc_id, unnest(list_filter(string_split(lower(text), ' '), lambda x: x <> '')) AS w FROM documents), "
        "tbit AS (SELECT w, j, CASE WHEN (CAST(('0x' || substr(md5(w), CAST(1 + j // 4 AS BIGINT), 1)) AS INTEGER) >> CAST(3 - j % 4 AS INTEGER)) & 1 = 1 THEN 1.0 ELSE -1.0 END AS x FROM (SELECT DISTINCT w FROM ttok), (SELECT unnest(range(64)) AS j)), "
        "tvec AS (SELECT doc_id, j, avg(x) AS x FROM ttok JOIN tbit USING (w) GROUP BY doc_id, j)"
    )
    domains = (
        "SELECT doc_id, lang, CASE WHEN s >= 15 THEN CASE WHEN s < 17 THEN 'out_a' WHEN s < 19 THEN 'out_b' ELSE 'out_c' END WHEN held THEN CASE WHEN s < 5 THEN 'in_a' WHEN s < 10 THEN 'in_b' ELSE 'in_c' END ELSE 'train' END AS domain "
        "FROM (SELECT doc_id, lang, CAST(regexp_extract(source, '([0-9]+)$', 1) AS INTEGER) AS s, CAST(('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8)) AS BIGINT) % 10 = 0 AS held FROM documents)"
    )
    out = {
        "corpus_filter": "SELECT doc_id, lang, source, n_chars FROM documents WHERE n_chars BETWEEN 200 AND 20000 AND lang IN ('en', 'de') AND NOT regexp_matches(text, '!!|[|]')",
        "feature_projection": "SELECT id AS vec_id, round(list_dot_product(v, v), 6) AS norm2, round(v[1], 6) AS x0, round(v[2], 6) AS x1, round(v[3], 6) AS x2 FROM v",
        "dedupe_exact": "SELECT md5(text) AS key, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY 1",
        "leak_free_documents": "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))",
        "pages_text_length": "SELECT page_id, length(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', '', 'gs'), '<[^>]*>', '', 'g')) AS n FROM pages",
        "io_roundtrip_count": " UNION ALL ".join(f"SELECT '{k}' AS format, count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids FROM {trip}" for k in ("json", "csv", "orc", "parquet", "text")),
        "events_json_stats": "SELECT event_type, count(k) AS n, min(k) AS least, max(k) AS most, round(avg(k), 6) AS mean FROM (SELECT event_type, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events) GROUP BY event_type",
        "join_broadcast": "SELECT r_name, count(*) AS n, round(avg(c_acctbal), 4) AS mean_balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
        "join_sortmerge": "SELECT o_orderstatus, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
        "join_shufflehash": "SELECT lang, quality, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2",
        "pool_minus_chosen": f"({picks(0, 200)}) EXCEPT ({picks(0, 10)})",
        "theta_pairs": "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 100",
        "score_band_pairs": "SELECT count(*) AS n, CAST(sum(a.p_partkey + b.p_partkey) AS BIGINT) AS ids FROM part a JOIN part b ON a.p_partkey < b.p_partkey AND abs(CAST(round(a.p_retailprice * 100) AS BIGINT) - CAST(round(b.p_retailprice * 100) AS BIGINT)) < 50",
        "history_in_interval": "SELECT h.id AS sample_id, count(*) AS n, round(avg(h.s), 6) AS mean FROM h JOIN hn ON hn.id = h.id AND h.step BETWEEN hn.top - 9 AND hn.top GROUP BY h.id",
        "asof_last_score": "SELECT * FROM (SELECT CAST(d.day AS VARCHAR) AS day, u.user_id, round((SELECT arg_max(e.value, struct_pack(t := e.ts, i := e.event_id)) FROM events e WHERE e.user_id = u.user_id AND CAST(e.ts AS DATE) <= d.day), 6) AS value FROM (SELECT DISTINCT CAST(ts AS DATE) AS day FROM events) d, (SELECT DISTINCT user_id FROM events) u) WHERE value IS NOT NULL",
        "lateral_topk": "SELECT src, dst, round(d, 6) AS dist FROM (SELECT a.id AS src, b.id AS dst, list_distance(a.v, b.v) AS d, row_number() OVER (PARTITION BY a.id ORDER BY list_distance(a.v, b.v), b.id) AS k FROM v a, v b WHERE a.id % 50 = 0 AND a.id <> b.id) WHERE k <= 3",
        "vocab_stats": "SELECT lang, count(DISTINCT w) AS tokens, count(DISTINCT doc_id) AS docs FROM (SELECT doc_id, lang, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> '' GROUP BY lang",
        "loss_percentiles": f"{ngrams} SELECT lang, round(quantile_cont(loss, 0.1), 5) AS p10, round(quantile_cont(loss, 0.5), 5) AS p50, round(quantile_cont(loss, 0.9), 5) AS p90 FROM (SELECT doc_id, -sum(ln(p)) / count(*) AS loss FROM told GROUP BY doc_id) JOIN documents USING (doc_id) GROUP BY lang",
        "ngram_token_probs": f"{ngrams} SELECT doc_id, round(-sum(ln(p)) / count(*), 6) AS loss, count(*) AS n_tokens FROM told GROUP BY doc_id",
        "importance_tokens": f"{ngrams} SELECT doc_id, round(sqrt(greatest(sum(p2 - 2 * p + 1), 0)), 5) AS score FROM told GROUP BY doc_id",
        "importance_tokens_mean": f"{ngrams} SELECT doc_id, round(sqrt(greatest(sum(p2 - 2 * p + 1), 0) / count(*)), 6) AS score FROM told GROUP BY doc_id",
        "w11_noise_by_band": f"{ngrams} SELECT CAST(band AS INTEGER) AS band, count(*) AS n, round(avg(CASE WHEN quality = 0 THEN 1.0 ELSE 0.0 END), 6) AS noise FROM (SELECT quality, ntile(3) OVER (ORDER BY round(s, 6), doc_id) AS band FROM (SELECT doc_id, sqrt(greatest(sum(p2 - 2 * p + 1), 0) / count(*)) AS s FROM told GROUP BY doc_id) JOIN labels USING (doc_id)) GROUP BY band",
        "join_null_safe": "WITH s AS (SELECT doc_id, CASE WHEN doc_id % 7 <> 0 THEN source END AS source FROM documents) SELECT source, count(*) AS n, count(l.doc_id) AS labelled FROM s LEFT JOIN (SELECT DISTINCT doc_id FROM labels) l USING (doc_id) GROUP BY source",
        "join_salted": "SELECT o_orderstatus, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 1) AS revenue FROM lineitem JOIN orders ON o_orderkey = CASE WHEN l_orderkey % 2 = 0 THEN 1 ELSE l_orderkey END GROUP BY 1",
        "sketch_errors": "SELECT * FROM (VALUES ('distinct', true), ('median', true), ('median_kll', true), ('most_frequent', true)) t(sketch, holds)",
        "sample_by_lang": "SELECT doc_id, lang FROM documents WHERE CAST(('0x' || substr(md5('7:' || doc_id), 1, 8)) AS BIGINT) / 4294967296.0 < CASE lang WHEN 'en' THEN 0.5 WHEN 'de' THEN 0.25 ELSE 0.0 END",
        "observed_counts": "SELECT count(*) AS observed, max(n_chars) AS most, count(*) AS n FROM documents WHERE n_chars > 1000",
        "paged_candidates": picks(0, 100),
        "sinks_roundtrip": "SELECT source, count(*) AS n FROM documents WHERE lang = 'en' GROUP BY source",
        "plan_counters": "SELECT count(*) AS joined, true AS shuffled FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
        "udf_rouge": ROUGE,
        "exact_match_by_domain": f"{vectors}, dom AS ({domains}), m AS (SELECT lang, j, avg(x) AS m FROM tvec JOIN dom USING (doc_id) WHERE domain = 'train' GROUP BY lang, j), d AS (SELECT doc_id, domain, dom.lang, m.lang AS guess, round(sum(power(x - m, 2)), 9) AS d2 FROM tvec JOIN dom USING (doc_id) JOIN m USING (j) WHERE domain <> 'train' GROUP BY doc_id, domain, dom.lang, m.lang), g AS (SELECT doc_id, domain, substr(domain, 1, 2) AS side, any_value(lang) AS lang, arg_min(guess, struct_pack(d := d2, g := guess)) AS guess FROM d GROUP BY doc_id, domain) SELECT side, domain, round(avg(CASE WHEN lang = guess THEN 1.0 ELSE 0.0 END), 6) AS accuracy, count(*) AS n FROM g GROUP BY ROLLUP (side, domain)",
        "w1_split": f"SELECT domain, count(*) AS n FROM ({domains}) GROUP BY domain",
        "mix_rollup": f"SELECT source, lang, count(*) AS n, CAST(grouping(source, lang) AS BIGINT) AS level FROM {mixed} GROUP BY ROLLUP (source, lang)",
        "mix_cube": f"SELECT source, lang, count(*) AS n, CAST(grouping(source, lang) AS BIGINT) AS level FROM {mixed} GROUP BY CUBE (source, lang)",
        "mix_grouping_sets": f"SELECT source, lang, count(*) AS n FROM {mixed} GROUP BY GROUPING SETS ((source), (lang))",
        "mix_pivot": f"SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM {mixed} GROUP BY source",
        "score_deltas": f"SELECT event_id, round(value - lag(value) OVER q, 6) AS back, round(lead(value) OVER q - value, 6) AS ahead FROM events WINDOW q AS ({order})",
        "moving_score": f"SELECT event_id, round(avg(value) OVER ({order} ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 5) AS mean FROM events",
        "range_frame_score": "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW), 4) AS total FROM events",
        "topk_global": "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 50",
        "topk_per_source": "SELECT source, doc_id, CAST(rank AS INTEGER) AS rank FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS rank FROM documents) WHERE rank <= 3",
        "stratified_quota": "WITH c AS (SELECT lang, 100.0 * count(*) / (SELECT count(*) FROM documents) AS q FROM documents GROUP BY lang), f AS (SELECT lang, floor(round(q, 9)) + CASE WHEN row_number() OVER (ORDER BY round(q - floor(round(q, 9)), 9) DESC, lang) <= 100 - sum(floor(round(q, 9))) OVER () THEN 1 ELSE 0 END AS quota FROM c) SELECT doc_id, lang FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY md5('42:0:' || doc_id)) AS k FROM documents) JOIN f USING (lang) WHERE k <= quota",
        "picks_union": f"({picks(0, 100)}) UNION ({picks(1, 100)})", "picks_intersect": f"({picks(0, 100)}) INTERSECT ({picks(1, 100)})", "picks_except": f"({picks(0, 100)}) EXCEPT ({picks(1, 100)})",
        "fn_string": "SELECT doc_id, length(trim(text)) AS n, upper(substr(md5(text), 1, 5)) AS head, md5(text) AS hash, levenshtein(substr(md5(text), 1, 8), substr(md5(text), 2, 8)) AS lev, translate(substr(text, 1, 10), 'aeiou', 'AEIOU') AS tr FROM documents",
        "fn_date": "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, datediff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') AS days, year(o_orderdate) AS year, dayofyear(o_orderdate) AS doy FROM orders",
        "fn_math": "SELECT event_id, round(ln(1 + value), 6) AS ln, round(sqrt(value), 6) AS root, round(power(value / 100, 1.5), 6) AS power, round(lgamma(value / 50 + 1), 6) AS lgamma, greatest(value, 50.0) AS most FROM events",
        "fn_array": "SELECT id AS vec_id, round(list_max(v), 6) AS most, len(list_filter(v, lambda x: x > 0)) AS positive, round(v[1] + v[2] + v[3] + v[4], 6) AS four, round(list_min(v), 6) AS least FROM v",
        "fn_map": "SELECT source, CAST(coalesce(sum(n) FILTER (lang = 'en'), 0) AS BIGINT) AS en, count(*) FILTER (n > 5) AS common FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2) GROUP BY source",
        "fn_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS INTEGER) AS v FROM events",
        "vector_functions": "SELECT a.id AS sample_id, round(list_dot_product(a.v, b.v), 6) AS dot, round(list_cosine_similarity(a.v, b.v), 6) AS cosine, round(list_distance(a.v, b.v), 6) AS l2 FROM v a JOIN v b ON b.id = a.id + 1",
        "weighted_sample": "SELECT c_custkey FROM (SELECT c_custkey, round(ln((CAST(('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 12)) AS BIGINT) + 1) / CAST(281474976710657 AS DOUBLE)) / c_acctbal, 15) AS k FROM customer WHERE c_acctbal > 0) ORDER BY k DESC, c_custkey LIMIT 50",
        "udaf_vector_mean": "SELECT label, CAST(j AS INTEGER) AS dim, round(avg(x), 6) AS value FROM e GROUP BY label, j",
        "udtf_tokens": "SELECT lang, CAST(sum(len(w)) AS BIGINT) AS tokens, CAST(max(len(w)) - 1 AS INTEGER) AS last FROM (SELECT lang, list_filter(string_split(lower(text), ' '), lambda x: x <> '') AS w FROM documents) GROUP BY lang",
        "answer_fallback": "SELECT p_partkey, CASE WHEN p_partkey % 2 = 0 THEN CAST(p_size AS VARCHAR) ELSE p_name END AS answer FROM part",
        "win_tumbling": "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n, round(avg(value), 5) AS mean FROM events GROUP BY 1",
        "stream_history_counts": "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n, round(avg(value), 5) AS mean FROM events GROUP BY 1",
        "doc_mean_vectors": "WITH ttok AS (SELECT doc_id, unnest(list_filter(string_split(lower(text), ' '), lambda x: x <> '')) AS w FROM documents), tbits AS (SELECT w, list_transform(range(64), lambda i: CASE WHEN (CAST(('0x' || substr(md5(w), CAST(i // 8 * 2 + 1 AS BIGINT), 2)) AS INTEGER) >> CAST(7 - i % 8 AS INTEGER)) & 1 = 1 THEN 1.0 ELSE -1.0 END) AS s FROM (SELECT DISTINCT w FROM ttok)) SELECT doc_id AS sample_id, round(avg(list_sum(s)), 6) AS total, round(avg(s[1]), 6) AS x0, round(avg(s[64]), 6) AS x63 FROM ttok JOIN tbits USING (w) GROUP BY doc_id",
        "w2_pairs": "SELECT count(*) AS n, count(DISTINCT conv_id) AS dialogues FROM pairs",
        "win_sliding": "SELECT CAST(CAST(ts AS DATE) - CAST(b AS INTEGER) AS VARCHAR) AS day, count(*) AS n, round(avg(value), 5) AS mean FROM events, (SELECT unnest(range(3)) AS b) GROUP BY 1",
        "win_session": f"SELECT user_id, count(*) AS sessions, max(n) AS longest, round(sum(t), 4) AS total FROM (SELECT user_id, s, count(*) AS n, sum(value) AS t FROM (SELECT *, sum(g) OVER ({order}) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER ({order}) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS g FROM events)) GROUP BY user_id, s) GROUP BY user_id",
        "sql_surface": "SELECT n.id AS sample_id, count(e.dst) AS degree, 40 - max(n.last) AS staleness FROM nodes n LEFT JOIN edges e ON e.src = n.id GROUP BY n.id",
    }
    return {k: x if x.lstrip().startswith("WITH") else sql(x) for k, x in out.items()}
