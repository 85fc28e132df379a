"""DuckDB SQL for the text operators that SQL can express, by plainer ways than the operators': joins of whole strings."""

from __future__ import annotations

from tempcorr.llm import op6_quality

#: Words of the contracts in RE2.
WORD = r"[^\x20\x09-\x0D]+"
LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _words(table: str, key: str, text: str, pattern: str) -> str:
    """(key, word, i) of every word of a table's texts."""
    return f"SELECT {key}, unnest(words) AS word, generate_subscripts(words, 1) AS i FROM (SELECT {key}, regexp_extract_all({text}, '{pattern}') AS words FROM {table})"


def _windows(words: str, key: str, size: int) -> str:
    """(key, i, word, win, n): for every word the string of it and those after it, and how many they are."""
    return f"SELECT {key}, i, word, string_agg(word, ' ') OVER f AS win, count(*) OVER f AS n FROM {words} WINDOW f AS (PARTITION BY {key} ORDER BY i ROWS BETWEEN CURRENT ROW AND {size - 1} FOLLOWING)"


#: Every string of 400 bytes as 800 hex digits, texts cut into blocks first, since a substring is found from the text's begin.
SUFFIX = """
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS x, strlen(coalesce(text, '')) AS n FROM documents),
b AS (SELECT r, j, substr(x, 2 * j + 1, 2 * (256 + 399)) AS y, least(256, n - 399 - j) AS m FROM (SELECT r, x, n, unnest(range(0, n - 399, 256)) AS j FROM d)),
g AS MATERIALIZED (SELECT r, j + i AS i, md5(substr(y, 2 * i + 1, 800)) AS win FROM (SELECT r, j, y, unnest(range(m)) AS i FROM b)),
h AS (SELECT r, i FROM g SEMI JOIN (SELECT win FROM g GROUP BY win HAVING count(*) > 1) USING (win)),
s AS (SELECT r, i, CASE WHEN i - lag(i) OVER (PARTITION BY r ORDER BY i) <= 400 THEN 0 ELSE 1 END AS new FROM h),
p AS (SELECT r, min(i) AS a, max(i) + 400 AS z FROM (SELECT r, i, sum(new) OVER (PARTITION BY r ORDER BY i) AS span FROM s) GROUP BY r, span),
c AS (SELECT r, a, z FROM p UNION ALL SELECT r, n, n FROM d),
k AS (SELECT r, a, z, coalesce(lag(z) OVER (PARTITION BY r ORDER BY a, z), 0) AS kept FROM c)
SELECT doc_id, n AS n_bytes, sum(z - a)::BIGINT AS n_removed, count(*) FILTER (z > a) AS n_spans,
    sha256(unhex(string_agg(substr(x, 2 * kept + 1, 2 * (a - kept)), '' ORDER BY a, z))) AS kept_sha256
FROM k JOIN d USING (r) GROUP BY r, doc_id, n
"""

SUBSTRING = f"""
WITH w AS ({_words("documents", "doc_id", "coalesce(text, '')", WORD)}),
g AS ({_windows("w", "doc_id", 13)}),
m AS (SELECT win, min(doc_id) AS first FROM g WHERE n = 13 GROUP BY win),
h AS (SELECT g.doc_id, i, word, coalesce(n = 13 AND first < g.doc_id, false) AS hit FROM g LEFT JOIN m USING (win)),
c AS (SELECT doc_id, i, word, bool_or(hit) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 12 PRECEDING AND CURRENT ROW) AS gone FROM h)
SELECT doc_id, count(i) AS n_words, count(i) FILTER (gone) AS n_removed, sha256(coalesce(string_agg(word, ' ' ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM documents LEFT JOIN c USING (doc_id) GROUP BY doc_id
"""

NEARDUP = f"""
WITH RECURSIVE w AS ({_words("documents", "doc_id", LOWER, WORD)}),
g AS ({_windows("w", "doc_id", 3)}),
s AS (SELECT DISTINCT doc_id, win FROM g WHERE n = 3 OR i = 1),
z AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b USING (win) WHERE a.doc_id < b.doc_id GROUP BY ALL),
k AS (SELECT x, y FROM p JOIN z a ON a.doc_id = x JOIN z b ON b.doc_id = y WHERE 100 * c >= 85 * (a.n + b.n - c)),
l AS (SELECT x, y FROM k UNION ALL SELECT y, x FROM k),
r(doc_id, other) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, l.y FROM r JOIN l ON l.x = r.other),
c AS (SELECT doc_id, min(other) AS component_id FROM r GROUP BY doc_id)
SELECT d.doc_id, coalesce(z.n, 0) AS n_shingles, component_id, component_id = d.doc_id AS kept
FROM documents d JOIN c USING (doc_id) LEFT JOIN z USING (doc_id)
"""

ITEM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

DECONTAMINATION = f"""
WITH w AS ({_words("documents", "doc_id", LOWER, ITEM_WORD)}),
g AS ({_windows("w", "doc_id", 13)}),
v AS ({_words("benchmark", "item_id", LOWER, ITEM_WORD)}),
b AS ({_windows("v", "item_id", 13)}),
t AS (SELECT DISTINCT item_id, word AS first, win, n FROM b WHERE n = 13 OR (i = 1 AND n < 13)),
h AS (
    SELECT doc_id, i, g.n AS k, item_id FROM g JOIN t USING (win) WHERE g.n = 13 AND t.n = 13
    UNION ALL SELECT doc_id, i, t.n, item_id FROM g JOIN t ON g.word = t.first WHERE t.n < 13 AND starts_with(g.win || ' ', t.win || ' ')
),
c AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS j FROM h) GROUP BY doc_id),
o AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS items FROM (SELECT DISTINCT doc_id, item_id FROM h) GROUP BY doc_id),
a AS (SELECT doc_id, len(regexp_extract_all({LOWER}, '{ITEM_WORD}')) AS n_words FROM documents)
SELECT a.doc_id, n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256,
    coalesce(n_hit > 0 AND 20 * n_hit >= n_words, false) AS contaminated
FROM a LEFT JOIN c USING (doc_id) LEFT JOIN o USING (doc_id)
"""

#: The rules once more, in RE2: phrases between signs that are no ASCII letters or digits, runs between separators, last signs.
_PHRASES = ["all rights reserved", "terms of use", "terms of service", "privacy policy", "cookie policy", "we use cookies", "accept cookies", "accept all cookies", "powered by", "sign in", "sign up", "login", "log in", "subscribe now", "subscribe to", "click here", "read more", "share this", "share on", "skip to content", "skip to main content", "javascript is disabled", "javascript is required"]
_RE2 = {
    "boilerplate": "(?i)(?:^|[^[:alnum:]])(?:" + "|".join(_PHRASES) + ")(?:[^[:alnum:]]|$)",
    "navigation": r"^[\t-\r ]*(?:(?:[^\t-\r |>»·•]+[\t-\r ]*[|>»·•][\t-\r ]*){3,}|[-*#=_~.|>»·•\t-\r ]+$)",
    "closed": r"""[.!?…:;"'')\]”’»。！？][\t-\r ]*$""",
}

QUALITY = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS ({_words("d", "doc_id", "text", WORD)}),
g AS ({_windows("w", "doc_id", op6_quality.WINDOW)}),
m AS (SELECT doc_id, win FROM g WHERE n = {op6_quality.WINDOW} GROUP BY ALL HAVING count(*) > 1),
h AS (SELECT g.doc_id, i, m.win IS NOT NULL AS hit FROM g LEFT JOIN m ON m.doc_id = g.doc_id AND m.win = g.win AND g.n = {op6_quality.WINDOW}),
r AS (SELECT doc_id, count(*) FILTER (again) AS n_repeat_words FROM (
    SELECT doc_id, bool_or(hit) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN {op6_quality.WINDOW - 1} PRECEDING AND CURRENT ROW) AS again FROM h) GROUP BY doc_id),
l AS (SELECT doc_id, line, len(regexp_extract_all(line, '{WORD}')) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d)),
k AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines, coalesce(sum(n) FILTER (
    (n > 20 OR NOT regexp_matches(line, '{_RE2["boilerplate"]}')) AND NOT regexp_matches(line, '{_RE2["navigation"]}') AND (n >= 5 OR regexp_matches(line, '{_RE2["closed"]}'))), 0) AS kept_words
    FROM l WHERE n > 0 GROUP BY doc_id),
a AS (SELECT doc_id, len(regexp_extract_all(text, '{WORD}')) AS n_words, length(regexp_replace(text, '[\\x20\\x09-\\x0D]+', '', 'g')) AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS n_symbols FROM d),
f AS (SELECT a.*, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(kept_words, 0) AS kept_words
    FROM a LEFT JOIN k USING (doc_id) LEFT JOIN r USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    n_words < {op6_quality.LEAST_WORDS} OR 100 * n_repeat_words > {op6_quality.MOST_REPEATED} * n_words AS base_failed,
    NOT (n_words < {op6_quality.LEAST_WORDS} OR 100 * n_repeat_words > {op6_quality.MOST_REPEATED} * n_words) AND 10 * n_symbols <= n_words
        AND word_chars BETWEEN 2 * n_words AND 15 * n_words AND 100 * kept_words >= {op6_quality.LEAST_KEPT} * n_words AS kept
FROM f
"""

#: Plain equality of payloads by hash join, and the capture index's columns: no archive is written.
WARC = r"""
WITH p AS (
    SELECT page_id, coalesce(url, '') AS url, coalesce(html, '') AS html FROM pages WHERE page_id IS NOT NULL
), k AS (
    SELECT page_id, url, strlen(html) AS payload_bytes, sha1(html) AS payload_digest,
        max(page_id) OVER (PARTITION BY sha1(html)) AS last,
        lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:@]+)', 1)) AS host,
        regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]+([^?#]*)', 1) AS path,
        regexp_extract(url, '[?]([^#]*)', 1) AS query
    FROM p
)
SELECT page_id, payload_bytes::BIGINT AS payload_bytes, payload_digest,
    CASE WHEN payload_bytes >= 1000 AND page_id < last THEN 'revisit' ELSE 'response' END AS record_type,
    CASE WHEN payload_bytes >= 1000 AND page_id < last THEN last END AS refers_to,
    CASE WHEN url = '' THEN '' ELSE array_to_string(list_reverse(string_split(host, '.')), ',') || ')' ||
        CASE WHEN path = '' THEN '/' ELSE lower(path) END || CASE WHEN query = '' THEN '' ELSE '?' || lower(query) END END AS urlkey,
    strftime(make_timestamp((1700000000 + page_id % 1000000000) * 1000000), '%Y-%m-%dT%H:%M:%SZ') AS captured
FROM k
"""

ORACLES = {"op3_suffix_dedup": SUFFIX, "op4_substring_dedup": SUBSTRING, "op5_warc": WARC, "op6_quality": QUALITY, "op7_neardup": NEARDUP, "op9_decontamination": DECONTAMINATION}
