"""DuckDB statements for the queries that SQL can express."""

ORACLES: dict[str, str] = {
    "op9_rule_cascade": r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, t, list_filter(string_split_regex(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM d),
win AS (SELECT r, i, md5(array_to_string(ws[i:i + 4], ' ')) AS h FROM w, unnest(range(1, len(ws) - 3)) AS u(i)),
twin AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, h) AS c FROM win) WHERE c > 1),
rep AS (SELECT r, sum(least(5, coalesce(nxt - i, 5)))::BIGINT AS n_repeat_words
        FROM (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS nxt FROM twin) GROUP BY r),
m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
             (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
             (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(rep.n_repeat_words, 0) AS n_repeat_words, len(ls) AS n_lines,
             len(list_filter(ls, lambda x: regexp_matches(x, '^[\x20\x09-\x0D]*[-*+•‣◦][\x20\x09]'))) AS n_bullet_lines,
             len(list_filter(ls, lambda x: regexp_matches(x, '(?:\.\.\.|…)[\x20\x09-\x0D]*\z'))) AS n_cut_lines,
             len(list_filter(ws, lambda x: regexp_matches(x, '\p{L}'))) AS n_letter_words
      FROM (SELECT *, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM w) w
      LEFT JOIN rep USING (r)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT (100 * n_symbols > 20 * n_words) AND NOT (n_dup_lines > 5 AND 10 * n_dup_lines > n_words)
       AND NOT (word_chars < 2 * n_words OR word_chars > 100 * n_words)
       AND NOT (10 * n_bullet_lines > 9 * n_lines) AND NOT (10 * n_cut_lines > 3 * n_lines) AND NOT (10 * n_letter_words < 6 * n_words) AS kept
FROM b""",
    "op10_url_lists": r"""
WITH c AS (SELECT row_number() OVER () AS r, page_id, url, TIMESTAMP '2024-01-01' + to_days((page_id % 366)::INT) + to_hours((page_id % 24)::INT) AS fetched,
                  lower(regexp_extract(coalesce(url, ''), '^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]/?#]*\]|[^/?#:]*)', 1)) AS host,
                  list_filter(string_split(regexp_extract(coalesce(url, ''), '^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*([^?#]*)', 1), '/'), lambda p: p <> '')[1:3] AS parts FROM pages),
h AS (SELECT host, ('0x' || substr(md5(host), 1, 2))::INT AS m FROM (SELECT DISTINCT host FROM c WHERE host <> '')),
e AS (SELECT 'spam' AS list, 'd:' || host AS pattern, 30 AS d, true AS act FROM h WHERE m % 3 = 0
      UNION SELECT 'spam', 'd:' || host, 40, true FROM h WHERE m % 3 = 0
      UNION SELECT 'spam', 'd:' || host, 100 + m, false FROM h WHERE m % 3 = 0
      UNION SELECT 'spam', 'd:' || host, 300, true FROM h WHERE m % 6 = 0
      UNION SELECT 'tracker', 'd:' || substr(host, strpos(host, '.') + 1), 120, true FROM h WHERE m % 5 = 0 AND strpos(host, '.') > 0
      UNION SELECT 'section', 'p:' || host || '/en', 180, true FROM h WHERE m % 4 = 1),
k AS (SELECT r, fetched, 'd:' || array_to_string(string_split(host, '.')[i:], '.') AS pattern FROM c, unnest(range(1, len(string_split(host, '.')) + 1)) AS u(i) WHERE host <> ''
      UNION SELECT r, fetched, 'p:' || host || '/' || array_to_string(parts[1:i], '/') FROM c, unnest(range(1, len(parts) + 1)) AS u(i) WHERE host <> ''),
a AS (SELECT r, list, pattern, arg_max(act, d * 2 + (NOT act)::INT) AS act FROM k JOIN e USING (pattern)
      WHERE TIMESTAMP '2024-01-01' + to_days(d) <= fetched GROUP BY r, list, pattern),
l AS (SELECT r, string_agg(DISTINCT list, ',' ORDER BY list) AS lists FROM a WHERE act GROUP BY r)
SELECT page_id, url, fetched, coalesce(lists, '') AS lists, lists IS NOT NULL AS blocked FROM c LEFT JOIN l USING (r)""",
}
