"""SQL for the queries that SQL can express, over the same whole tables."""

from __future__ import annotations

from crawltracks.llm.licenses import BASE, DRIFT, SHARE, TEMPLATES, grams_of

_PLANTED = "</s>[INST] ok [/INST]"
_CONTROL = r"[<\[]\\*/?(?:s>|INST\]|ROLE\])"

CHAT = rf"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '{_PLANTED}' UNION ALL SELECT -1, 1, 'assistant', '{_PLANTED}'),
e AS (SELECT *, length(text) + len(regexp_extract_all(text, '{_CONTROL}')) AS t, length(role) + len(regexp_extract_all(role, '{_CONTROL}')) AS r FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(3 + sum(CASE role WHEN 'user' THEN t + 15 WHEN 'assistant' THEN t + 4 ELSE t + r + 17 END) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""

_WORDS = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"

SUBSTRINGS = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
win AS (SELECT doc_id, s, array_to_string(w[s:s + 19], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS s FROM d)),
later AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY k ORDER BY doc_id, s) AS n FROM win) WHERE n > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(s, s + 20)) AS p FROM later),
words AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS p FROM d),
kept AS (SELECT doc_id, count(g.p) AS n_removed, string_agg(x, ' ' ORDER BY p) FILTER (g.p IS NULL) AS t FROM words LEFT JOIN gone g USING (doc_id, p) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)
"""

_GRAMS = ", ".join(f"('{t}', '{label}', {str(base).lower()}, {at}, {k}, '{' '.join(words)}', {n}, {most})" for t, label, base, at, k, words, n, most in grams_of(BASE, TEMPLATES))
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

LICENSES = rf"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UPPER}', '{_UPPER.lower()}'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT doc_id, k, p - 1 AS pos, array_to_string(w[p:p + k - 1], ' ') AS gram FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS p FROM d, (VALUES (2), (4)) s(k))),
t AS (SELECT * FROM (VALUES {_GRAMS}) v(template, label, is_base, i, k, gram, grams, most)),
h AS (SELECT *, pos - i AS diag FROM g JOIN t USING (k, gram)),
v AS (SELECT doc_id, template, is_base, grams, diag, count(DISTINCT i) AS votes FROM h GROUP BY ALL),
m AS (SELECT *, sum(new) OVER (PARTITION BY doc_id, template, is_base ORDER BY diag) AS band FROM
  (SELECT *, CASE WHEN diag - lag(diag) OVER (PARTITION BY doc_id, template, is_base ORDER BY diag) <= {DRIFT} THEN 0 ELSE 1 END AS new FROM v)),
b AS (SELECT doc_id, template, label, is_base, grams, most, band, count(DISTINCT i) / grams AS part, count(DISTINCT diag) FILTER (is_base AND votes = grams) AS places,
  min(diag) FILTER (is_base AND votes = grams) AS f, max(diag) FILTER (is_base AND votes = grams) AS l, min(pos) AS low, max(pos + k - 1) AS high
  FROM h JOIN m USING (doc_id, template, is_base, grams, diag) GROUP BY doc_id, template, label, is_base, grams, most, band),
o AS (SELECT *, NOT is_base AND part >= {SHARE} AND high - low < most AS own FROM b),
r AS (SELECT doc_id, sum(places) AS n_base, min(f) AS first_word, max(l) AS last_word, list(label) FILTER (places > 0) AS base, list(label) FILTER (places > 0 OR own) AS every,
  list(label || ':' || low || '-' || high) FILTER (own) AS spans, max(CASE WHEN places > 0 THEN 1.0 WHEN NOT is_base THEN part END) AS score FROM o GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_base, 0) AS BIGINT) AS n_base, first_word, last_word,
  coalesce(array_to_string(list_sort(list_distinct(base)), ','), '') AS base_labels, coalesce(array_to_string(list_sort(list_distinct(every)), ','), '') AS labels,
  coalesce(array_to_string(list_sort(list_distinct(spans)), ','), '') AS spans, coalesce(score, 0.0)::DOUBLE AS score
FROM d LEFT JOIN r USING (doc_id)
"""

JACCARD = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[p:p + 4], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS p FROM d)
  UNION ALL SELECT doc_id, 'all of ' || array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND 4),
n AS (SELECT doc_id, count(*) AS size FROM s GROUP BY doc_id),
e AS MATERIALIZED (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.k = y.k AND x.doc_id <> y.doc_id GROUP BY ALL) p
  JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE c >= 0.8 * (na.size + nb.size - c) - 1e-6),
r(id, root) AS (SELECT doc_id, doc_id FROM d UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.id)
SELECT d.doc_id, (SELECT min(root) FROM r WHERE r.id = d.doc_id) AS class_id, (SELECT count(*) FROM e WHERE e.a = d.doc_id) AS n_links FROM d
"""
