"""DuckDB SQL for the queries of this subpackage that SQL can express.  Written from the contracts, not from the operators."""

from __future__ import annotations

WORD = r"[^\x20\x09-\x0D]+"

SUBSTRING = rf"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents
), g AS (
  SELECT doc_id, p, array_to_string(list_slice(ws, p, p + 34), ' ') AS s
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS p FROM w WHERE len(ws) >= 35)
), hit AS (
  SELECT doc_id, p FROM g WHERE s IN (SELECT s FROM g GROUP BY s HAVING count(*) > 1)
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(p, p + 35)) AS i FROM hit
), one AS (
  SELECT doc_id, i, word FROM (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS i FROM w)
), kept AS (
  SELECT o.doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY o.i) AS t
  FROM one o LEFT JOIN gone USING (doc_id, i) WHERE gone.i IS NULL GROUP BY o.doc_id
)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(ws) - coalesce(n, 0) AS BIGINT) AS n_removed,
       sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
"""

HOST_RULES = rf"""
WITH w AS (
  SELECT doc_id, source AS host, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents
), three AS (
  SELECT doc_id, p, ws[p] || ' ' || ws[p + 1] || ' ' || ws[p + 2] AS s
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS p FROM w WHERE len(ws) >= 3)
), twice AS (
  SELECT doc_id, p FROM three JOIN (SELECT doc_id, s FROM three GROUP BY doc_id, s HAVING count(*) > 1) USING (doc_id, s)
), rep AS (
  SELECT doc_id, count(*) AS n FROM (SELECT DISTINCT doc_id, unnest(range(p, p + 3)) AS i FROM twice) GROUP BY doc_id
), dup AS (
  SELECT doc_id, sum(n - 1) AS n, sum(n) AS lines FROM (
    SELECT doc_id, line, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM w)
    WHERE regexp_matches(line, '{WORD}') GROUP BY doc_id, line) GROUP BY doc_id
), m AS (
  SELECT doc_id, host, CAST(len(ws) AS BIGINT) AS n_words,
         CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
         CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(coalesce(dup.n, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words,
         CAST(coalesce(dup.lines, 0) AS BIGINT) AS n_lines
  FROM w LEFT JOIN dup USING (doc_id) LEFT JOIN rep USING (doc_id)
), f AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m
), rule AS (
  SELECT host, 'few' AS name, (n_words < 50)::INT AS bad FROM f
  UNION ALL SELECT host, 'repeated', (100 * n_repeat_words > 50 * n_words)::INT FROM f
  UNION ALL SELECT host, 'length', (n_words > 0 AND word_chars / n_words NOT BETWEEN 2 AND 15)::INT FROM f
  UNION ALL SELECT host, 'symbols', (n_symbols > n_words / 10)::INT FROM f
  UNION ALL SELECT host, 'lines', (n_lines > 0 AND n_dup_lines / n_lines > 0.3)::INT FROM f
), h AS (
  SELECT host, name, count(*) AS n, sum(bad) AS bad, sum(bad) / count(*) AS rate FROM rule GROUP BY host, name
), prior AS (
  SELECT name, avg(rate) AS m, CASE WHEN var_pop(rate) > 0 THEN greatest(1.0, least(1000.0, avg(rate) * (1 - avg(rate)) / var_pop(rate) - 1))
         ELSE 1000.0 END AS wt FROM h GROUP BY name
), s AS (
  SELECT host, max((bad + wt * m) / (n + wt)) AS shrunk FROM h JOIN prior USING (name) GROUP BY host
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed, NOT base_failed AND shrunk < 0.5 AS kept,
       f.host, CAST((n_words < 50)::INT + (100 * n_repeat_words > 50 * n_words)::INT + (n_words > 0 AND word_chars / n_words NOT BETWEEN 2 AND 15)::INT
       + (n_symbols > n_words / 10)::INT + (n_lines > 0 AND n_dup_lines / n_lines > 0.3)::INT AS BIGINT) AS n_failed, round(shrunk, 9) AS shrunk
FROM f JOIN s ON f.host IS NOT DISTINCT FROM s.host
"""

CHAT = """
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), e AS (
  SELECT *, replace(replace(replace(role || text, '&', '&amp;'), '<', '&lt;'), '[', '&lbr;') AS safe FROM c
)
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(length(safe) + length('<|turn|>') + length('<|body|>') + length('<|end|>')) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""

# The base columns of the license scan; labels and score of the rules have no SQL.
LICENSE_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
LICENSE_BASE = rf"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{LICENSE_WORD}') AS ws FROM documents
), i AS (
  SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS p FROM w WHERE len(ws) > 0
), hit AS (
  SELECT doc_id, p - 1 AS p, 'mit' AS label FROM i WHERE ws[p] = 'under' AND ws[p + 1] = 'the' AND ws[p + 2] = 'mit' AND ws[p + 3] = 'license'
  UNION ALL SELECT doc_id, p - 1, 'apache-2' FROM i WHERE ws[p] = 'apache' AND ws[p + 1] = 'license' AND ws[p + 2] = 'version' AND ws[p + 3] = '2'
  UNION ALL SELECT doc_id, p - 1, 'cc-by-nc' FROM i WHERE ws[p] = 'cc' AND ws[p + 1] = 'by' AND ws[p + 2] = 'nc'
)
SELECT w.doc_id, CAST(any_value(len(ws)) AS BIGINT) AS n_words, count(hit.p) AS n_base, CAST(min(p) AS BIGINT) AS first_word,
       CAST(max(p) AS BIGINT) AS last_word, coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS base_labels
FROM w LEFT JOIN hit USING (doc_id) GROUP BY w.doc_id
"""

# All pairs within a label; exact on small tables.
EMBEDDINGS = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, x, sqrt(list_sum(list_transform(x, lambda a: a * a))) AS n FROM (
    SELECT vec_id, label, list_transform(embedding::DOUBLE[], lambda a: a / nullif(list_max(list_transform(embedding::DOUBLE[], lambda b: abs(b))), 0)) AS x FROM embeddings)
), ok AS (
  SELECT * FROM v WHERE label IS NOT NULL AND n > 0 AND isfinite(n) AND len(list_filter(x, lambda a: a IS NULL)) = 0
), link AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.x) = len(b.x)
  WHERE list_dot_product(a.x, b.x) / (a.n * b.n) >= 0.93
), reach(a, b) AS (
  SELECT a, b FROM link UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a
)
SELECT vec_id, (SELECT count(*) FROM link WHERE a = vec_id) AS n_links,
       least(vec_id, coalesce((SELECT min(b) FROM reach WHERE a = vec_id), vec_id)) AS component_id,
       vec_id = least(vec_id, coalesce((SELECT min(b) FROM reach WHERE a = vec_id), vec_id)) AS kept
FROM v
"""
