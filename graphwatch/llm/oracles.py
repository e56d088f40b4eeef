"""DuckDB SQL for the queries of this subpackage that SQL can express."""

SQL: dict[str, str] = {}

SQL["op10_quality_rules"] = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
g AS (SELECT doc_id, i, [ws[i], ws[i + 1], ws[i + 2]] AS g FROM w, unnest(range(1, len(ws) - 1)) AS u(i)),
r AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM r, unnest([0, 1, 2]) AS v(k) GROUP BY doc_id),
m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, len(array_to_string(ws, ''))::BIGINT AS word_chars,
             len(regexp_extract_all(t, '[#*$%&|<>]'))::BIGINT AS n_symbols,
             (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words,
             len(ls) AS n_lines,
             len(list_intersect(list_transform(ws, lambda x: lower(x)), {stop})) AS stop_words
      FROM w LEFT JOIN c ON w.doc_id = c.doc_id),
b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND word_chars::DOUBLE / n_words BETWEEN 2.5 AND 12 AND n_symbols::DOUBLE / n_words <= 0.1
       AND stop_words >= 2 AND (n_lines = 0 OR n_dup_lines::DOUBLE / n_lines <= 0.5) AS kept
FROM b
"""


def _stop_words() -> str:
    from graphwatch.llm.quality import STOP_WORDS

    return "[" + ", ".join(f"'{x}'" for x in dict.fromkeys(STOP_WORDS)) + "]"


SQL["op10_quality_rules"] = SQL["op10_quality_rules"].replace("{stop}", _stop_words())

SQL["op8_line_dedup"] = r"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, i, ls[i] AS line, lower(trim(ls[i], ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13))) AS u,
             translate(trim(ls[i], ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
      FROM d, unnest(range(1, len(ls) + 1)) AS r(i)),
k AS (SELECT key, count(DISTINCT doc_id) AS n, max(doc_id) AS last_doc FROM l WHERE length(key) >= 20 GROUP BY key HAVING n >= 3),
x AS (SELECT l.doc_id, l.i, l.line, k.key IS NOT NULL AND l.doc_id <> k.last_doc AS dropped FROM l LEFT JOIN k ON l.key = k.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (dropped)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT dropped), '')) AS kept_sha256
FROM x GROUP BY doc_id
"""
