"""DuckDB SQL for the operator queries that SQL can express, written apart from the operators."""

_WORD = r"[^\x20\x09-\x0D]+"

OP1 = r"""
WITH rules(verdict, h, p) AS (VALUES ('allow','com','/'), ('block','example.com','/en/'), ('allow','www.example.com','/en/'), ('block','net','/es/'), ('block','net','/fr/')),
parts AS (SELECT row_number() OVER () AS i, page_id, CASE WHEN contains(coalesce(url, ''), '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
urls AS (SELECT i, page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts),
fits AS (SELECT i, h || p AS rule, verdict, row_number() OVER (PARTITION BY i ORDER BY length(h || p) DESC, length(h) DESC, verdict DESC) AS k
  FROM urls JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM urls LEFT JOIN (SELECT * FROM fits WHERE k = 1) USING (i)
"""

OP3 = rf"""
WITH docs AS (SELECT row_number() OVER () AS i, doc_id, coalesce(text, '') AS text FROM documents),
words AS (SELECT i, doc_id, text, regexp_extract_all(text, '{_WORD}') AS w FROM docs),
lines AS (SELECT i, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM docs),
lw AS (SELECT i, pos, line, regexp_extract_all(line, '{_WORD}') AS w FROM lines),
judged AS (SELECT i, len(w) AS n, row_number() OVER (PARTITION BY i, line ORDER BY pos) > 1 AS dup,
  regexp_matches(line, '(?i)licensed under|license, version|all rights reserved|privacy policy|terms of (use|service)|cookie policy|enable javascript|subscribe to our|lorem ipsum')
  OR len(regexp_extract_all(line, '[|»•]')) >= 3
  OR len(regexp_extract_all(line, '[#*$%&|<>]')) > 0.2 * len(w)
  OR len(list_filter(w, lambda x: ends_with(x, '!!'))) > 0.3 * len(w)
  OR (len(w) >= 8 AND len(list_distinct(w)) < 0.25 * len(w))
  OR (len(w) < 3 AND NOT regexp_matches(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '[.!?…。！？:;"''”’»)\]]$')) AS bad
  FROM lw WHERE len(w) > 0),
by_line AS (SELECT i, count(*) FILTER (dup) AS n_dup_lines, coalesce(sum(n) FILTER (bad), 0)::BIGINT AS lost_words FROM judged GROUP BY i),
places AS (SELECT i, unnest(generate_series(1, len(w) - 7)) AS pos, w FROM words WHERE len(w) >= 8),
win AS (SELECT i, pos, count(*) OVER (PARTITION BY i, array_to_string(w[pos:pos + 7], ' ')) AS n FROM places),
again AS (SELECT i, count(DISTINCT p) AS n_repeat_words FROM (SELECT i, unnest(generate_series(pos, pos + 7)) AS p FROM win WHERE n > 1) GROUP BY i),
base AS (SELECT i, doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
  len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols FROM words)
SELECT doc_id, n_words, word_chars, n_symbols, coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
  n_words < 20 OR 100 * coalesce(n_repeat_words, 0) > 30 * n_words AS base_failed, coalesce(lost_words, 0)::BIGINT AS lost_words,
  NOT (n_words < 20 OR 100 * coalesce(n_repeat_words, 0) > 30 * n_words) AND coalesce(lost_words, 0) <= 0.5 * n_words AS kept
FROM base LEFT JOIN by_line USING (i) LEFT JOIN again USING (i)
"""

OP8 = r"""
WITH lowered AS (SELECT row_number() OVER () AS i, doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
docs AS (SELECT i, doc_id, regexp_extract_all(t, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM lowered),
items AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE text IS NOT NULL),
wins AS (SELECT DISTINCT item_id, n, array_to_string(w[pos:pos + n - 1], ' ') AS win FROM
  (SELECT item_id, w, least(10, len(w)) AS n, unnest(generate_series(1, greatest(1, len(w) - 9))) AS pos FROM items WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM wins),
places AS (SELECT i, n, unnest(generate_series(1, len(w) - n + 1)) AS pos, w FROM docs, sizes WHERE len(w) >= n),
hits AS (SELECT i, p.n, pos, item_id FROM (SELECT i, n, pos, array_to_string(w[pos:pos + n - 1], ' ') AS win FROM places) p JOIN wins USING (n, win)),
covered AS (SELECT i, count(DISTINCT p) AS n_hit FROM (SELECT i, unnest(generate_series(pos, pos + n - 1)) AS p FROM hits) GROUP BY i),
named AS (SELECT i, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS names FROM (SELECT DISTINCT i, item_id::VARCHAR AS x FROM hits) GROUP BY i)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM docs LEFT JOIN covered USING (i) LEFT JOIN named USING (i)
"""

ORACLES = {"op1_url_filters": OP1, "op3_quality_rules": OP3, "op8_decontamination": OP8}
