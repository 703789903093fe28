"""DuckDB equivalents of the queries that SQL can state."""

from __future__ import annotations

_WORDS = r"[x FOR x IN regexp_split_to_array(coalesce(text, ''), '[ \t\n\x0B\f\r]+') IF x <> '']"
_TRIM = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_LINES = "string_split(coalesce(text, ''), chr(10))"

OP3 = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS text, {_WORDS} AS w, [x FOR x IN {_LINES} IF regexp_matches(x, '[^ \t\n\x0B\f\r]')] AS ls FROM documents),
grams AS (SELECT r, i, w[i+1] AS a, w[i+2] AS b, w[i+3] AS c FROM (SELECT r, w, unnest(range(0, greatest(len(w) - 2, 0))) AS i FROM d)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, a, b, c) AS n FROM grams) WHERE n > 1),
covered AS (SELECT r, count(DISTINCT p)::BIGINT AS n FROM (SELECT r, i + unnest([0, 1, 2]) AS p FROM twice) GROUP BY r),
norm AS (SELECT r, source, trim(unnest(string_split(regexp_replace(lower(text), '[0-9]', '0', 'g'), chr(10))), {_TRIM}) AS line FROM d),
hosts AS (SELECT source, count(*) AS docs FROM d GROUP BY source),
above AS (SELECT n.source, n.line FROM (SELECT source, line, count(DISTINCT r) AS n FROM norm WHERE line <> '' GROUP BY source, line) n JOIN hosts h ON n.source IS NOT DISTINCT FROM h.source WHERE n.n >= 10 AND n.n > 0.1 * h.docs),
lost AS (SELECT n.r, sum(length(n.line)) AS total, sum(CASE WHEN a.line IS NOT NULL THEN length(n.line) ELSE 0 END) AS lost FROM norm n LEFT JOIN above a ON n.source IS NOT DISTINCT FROM a.source AND n.line = a.line GROUP BY n.r),
base AS (SELECT d.r, doc_id, len(w)::BIGINT AS n_words, list_sum([length(x) FOR x IN w]) AS word_chars, (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
 (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words FROM d LEFT JOIN covered c USING (r))
SELECT doc_id, n_words, coalesce(word_chars, 0)::BIGINT AS word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
 NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND lost <= 0.5 * total AS kept FROM base JOIN lost USING (r)
"""

OP5 = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, text, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT r, source, i, ls[i] AS line, trim(ls[i], {_TRIM}) AS t FROM (SELECT r, source, ls, unnest(range(1, len(ls) + 1)) AS i FROM d)),
hosts AS (SELECT source, count(*) AS pages FROM d GROUP BY source),
bad AS (SELECT c.source, c.t FROM (SELECT source, t, count(DISTINCT r) AS n FROM l WHERE t <> '' GROUP BY source, t) c JOIN hosts h ON c.source IS NOT DISTINCT FROM h.source WHERE c.n >= 5 AND c.n / h.pages > 0.1),
kept AS (SELECT l.r, coalesce(string_agg(l.line, chr(10) ORDER BY l.i) FILTER (WHERE b.t IS NULL), '') AS text, count(*) FILTER (WHERE b.t IS NOT NULL) AS n_dropped FROM l LEFT JOIN bad b ON l.source IS NOT DISTINCT FROM b.source AND l.t = b.t GROUP BY l.r)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE k.text END AS text, coalesce(len(d.ls), 0)::BIGINT AS n_lines, coalesce(k.n_dropped, 0)::BIGINT AS n_dropped FROM d LEFT JOIN kept k USING (r)
"""

OP7 = """
WITH v AS (SELECT row_number() OVER () AS r, vec_id, [floor(256 * e::DOUBLE)::DOUBLE FOR e IN embedding] AS x FROM embeddings
 WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len([e FOR e IN embedding IF e IS NULL OR NOT isfinite(e)]) = 0),
s AS (SELECT q.r, q.vec_id AS query_id, c.vec_id, list_dot_product(q.x, c.x)::BIGINT AS score FROM v q JOIN v c ON q.r <> c.r WHERE q.vec_id % 50 = 0)
SELECT query_id, rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id NULLS LAST)::INTEGER AS rank FROM s) WHERE rank <= 5
"""

ORACLES = {"op3_quality_rules": OP3, "op5_line_dedup": OP5, "op7_exact_top_k": OP7}
