"""DuckDB SQL for the queries of this subpackage that SQL can express."""

HOST_RULES = r"""
WITH word AS (
  SELECT doc_id, w, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS i
  FROM (SELECT doc_id, unnest(ws) AS w, unnest(range(len(ws))) AS i
        FROM (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents))
), per_word AS (
  SELECT doc_id, count(*) AS n_words, sum(length(w)) AS word_chars FROM word GROUP BY doc_id
), win AS (
  SELECT doc_id, i, concat_ws(' ', w, lead(w, 1) OVER p, lead(w, 2) OVER p, lead(w, 3) OVER p, lead(w, 4) OVER p) AS g,
         lead(w, 4) OVER p IS NOT NULL AS whole
  FROM word WINDOW p AS (PARTITION BY doc_id ORDER BY i)
), twice AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win WHERE whole) WHERE c >= 2
), rep AS (
  SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM twice, range(5) AS r(k) GROUP BY doc_id
), line AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS l FROM documents
), dup AS (
  SELECT doc_id, sum(c - 1) AS n_dup_lines
  FROM (SELECT doc_id, l, count(*) AS c FROM line WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY doc_id, l) GROUP BY doc_id
), m AS (
  SELECT d.doc_id, d.source, coalesce(n_words, 0) AS n_words, coalesce(word_chars, 0) AS word_chars,
         length(regexp_replace(coalesce(text, ''), '[^#*$%&|<>]', '', 'g')) AS n_symbols,
         coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words
  FROM documents d LEFT JOIN per_word USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN dup USING (doc_id)
), f AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m
), h AS (
  SELECT source, count(*) AS n, sum(base_failed::INT) AS k FROM f WHERE source IS NOT NULL GROUP BY source
), t AS (
  SELECT coalesce(sum(k) / sum(n)::DOUBLE, 0) AS mu, coalesce(sum(k * k / n::DOUBLE) / sum(n), 0) AS q, coalesce(count(*) / sum(n)::DOUBLE, 0) AS e FROM h
), p AS (
  SELECT mu, CASE WHEN q - mu * mu - e * mu * (1 - mu) > 0
    THEN least(1e6, greatest(1.0, mu * (1 - mu) / (q - mu * mu - e * mu * (1 - mu)) - 1)) ELSE 1e6 END AS s FROM t
), v AS (
  SELECT source, (k + mu * s) / (n + s) AS host_rate FROM h, p
)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
       n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed,
       NOT base_failed AND coalesce(host_rate, 0) <= 0.5 AS kept
FROM f LEFT JOIN v USING (source)
"""

NEAR_DUPLICATES = r"""
WITH RECURSIVE seq AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws
  FROM documents
), shingle AS (
  SELECT DISTINCT doc_id, array_to_string(ws[i : least(i + 4, len(ws))], ' ') AS s
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM seq WHERE len(ws) > 0)
), size AS (
  SELECT doc_id, count(*) AS n FROM shingle GROUP BY doc_id
), common AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM shingle a JOIN shingle b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2
), edge AS (
  SELECT x, y FROM common JOIN size p ON p.doc_id = x JOIN size q ON q.doc_id = y WHERE 100 * c >= 75 * (p.n + q.n - c)
), reach AS (
  SELECT doc_id AS d, doc_id AS r FROM documents
  UNION
  SELECT d, y FROM reach JOIN edge ON r = x
), comp AS (
  SELECT d, min(r) AS component_id FROM reach GROUP BY d
)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept
FROM documents LEFT JOIN size USING (doc_id) LEFT JOIN comp ON d = documents.doc_id
"""
