"""DuckDB SQL for the queries that SQL can express in full.

The others hold XXH64 values, tokenizer ids, MinHash components or learned models; tests/llm compares them with brute force.
"""

from __future__ import annotations

_URLS = r"""
WITH parts AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), cut AS (
  SELECT page_id, regexp_extract(rest, '^[^/?#]*') AS raw, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts
), named AS (
  SELECT page_id, path, translate(coalesce(raw, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host FROM cut
), rules(rule, r_host, r_path, verdict) AS (
  VALUES ('net/', 'net', '/', 'block'), ('example.net/en/', 'example.net', '/en/', 'allow'),
         ('example.com/de/', 'example.com', '/de/', 'block'), ('org/fr/', 'org', '/fr/', 'allow')
)
SELECT page_id, host, coalesce(path, '') AS path,
  (SELECT r.rule FROM rules r WHERE (host = r.r_host OR suffix(host, '.' || r.r_host)) AND starts_with(path, r.r_path) ORDER BY length(r.rule) DESC LIMIT 1) AS rule,
  coalesce((SELECT r.verdict FROM rules r WHERE (host = r.r_host OR suffix(host, '.' || r.r_host)) AND starts_with(path, r.r_path) ORDER BY length(r.rule) DESC LIMIT 1), 'allow') AS verdict
FROM named
"""

_QUALITY = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text FROM documents
), w AS (
  SELECT rid, doc_id, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words,
    list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM d
), windows AS (
  SELECT rid, i AS pos, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS win
  FROM w, LATERAL (SELECT unnest(generate_series(1, len(words) - 2)) AS i) WHERE len(words) >= 3
), twice AS (
  SELECT rid, pos FROM (SELECT rid, pos, count(*) OVER (PARTITION BY rid, win) AS n FROM windows) WHERE n > 1
), covered AS (
  SELECT rid, count(DISTINCT pos + step) AS n FROM twice, (VALUES (0), (1), (2)) AS s(step) GROUP BY rid
), counts AS (
  SELECT w.rid, doc_id, text, lines, len(words)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(covered.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN covered USING (rid)
), judged AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
    length(regexp_replace(text, '[^\pL]', '', 'g')) AS letters, length(regexp_replace(text, '[^\p{Lu}]', '', 'g')) AS capitals,
    length(regexp_replace(text, '[^!?]', '', 'g')) AS shouts
  FROM counts
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT (base_failed OR 4 * n_symbols > n_words OR word_chars < 2 * n_words OR word_chars > 15 * n_words OR 2 * n_dup_lines > len(lines)
    OR 5 * shouts > n_words OR 10 * letters < 6 * word_chars OR 2 * capitals > letters) AS kept
FROM judged
"""

_TOPK = r"""
WITH v AS (
  SELECT row_number() OVER () AS rid, vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS vec FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), s AS (
  SELECT q.rid, q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.vec, c.vec), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.rid <> c.rid WHERE q.vec_id % 50 = 0
), r AS (
  SELECT *, row_number() OVER (PARTITION BY rid ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""

SQL = {"op1_url_filter": _URLS, "op4_quality": _QUALITY, "op5_topk": _TOPK}
