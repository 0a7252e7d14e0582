"""DuckDB SQL of the queries that SQL can express, written from the contracts alone."""

from __future__ import annotations

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_ALNUM_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_LOWER_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+')"

DECONTAMINATION = rf"""
WITH d AS (SELECT doc_id, {_ALNUM_WORDS} AS w FROM documents),
b AS (SELECT item_id, {_ALNUM_WORDS} AS w FROM benchmark),
item_windows AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS size, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') AS win
  FROM b, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS t(i) WHERE len(w) > 0),
sizes AS (SELECT DISTINCT size FROM item_windows),
doc_windows AS (SELECT doc_id, size, i, array_to_string(w[i : i + size - 1], ' ') AS win FROM d, sizes, unnest(range(1, len(w) - size + 2)) AS t(i)),
hits AS (SELECT doc_id, item_id, i, size FROM doc_windows JOIN item_windows USING (size, win)),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + size)) AS p FROM hits) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""

NEAR_DUPLICATES = rf"""
WITH RECURSIVE d AS (SELECT doc_id, {_LOWER_WORDS} AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) >= 5 THEN list_distinct([array_to_string(w[i : i + 4], ' ') FOR i IN range(1, len(w) - 3)])
             WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS g FROM d),
n AS (SELECT doc_id, CAST(len(g) AS BIGINT) AS n FROM s),
e AS (SELECT doc_id, unnest(g) AS g FROM s),
c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM e x JOIN e y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM c JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * shared >= 75 * (p.n + q.n - shared)),
both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT doc_id AS v, doc_id AS r FROM d UNION SELECT b, r FROM reach JOIN both_ways ON v = a)
SELECT doc_id, n AS n_shingles, c AS component_id, doc_id = c AS kept FROM n JOIN (SELECT v AS doc_id, min(r) AS c FROM reach GROUP BY v) USING (doc_id)
"""

# runs of 50 bytes by their first byte; hex text, two digits a byte, so that all texts can be cut anywhere
REPEATED_SPANS = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
w AS (SELECT doc_id, i, md5_number(x[2 * i - 1 : 2 * i + 98]) AS g FROM d, unnest(range(1, n - 48)) AS t(i) WHERE n >= 50),
m AS (SELECT g, min(doc_id) AS least FROM w GROUP BY g),
c AS (SELECT doc_id, i FROM w JOIN m USING (g) WHERE least < doc_id),
o AS (SELECT doc_id, i, coalesce(i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 50, true) AS fresh FROM c),
k AS (SELECT doc_id, i, sum(fresh::INT) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM o),
s AS (SELECT doc_id, run, min(i) AS a, max(i) + 50 AS b FROM k GROUP BY ALL),
e AS (SELECT doc_id, run, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 1) AS prev FROM s),
p AS (SELECT doc_id, sum(b - a) AS n_removed, count(*) AS n_spans, max(b) AS tail, string_agg(substr(x, CAST(2 * prev - 1 AS BIGINT), CAST(2 * (a - prev) AS BIGINT)), '' ORDER BY a) AS head FROM e JOIN d USING (doc_id) GROUP BY doc_id)
SELECT doc_id, CAST(n AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans,
  sha256(unhex(coalesce(head || substr(x, CAST(2 * tail - 1 AS BIGINT)), x))) AS kept_sha256
FROM d LEFT JOIN p USING (doc_id)
"""

_NORM_LINE = r"trim(regexp_replace(regexp_replace(lower(l), '[0-9]+', '0', 'g'), '[\x20\x09\x0B-\x0D]+', ' ', 'g'))"

LINE_FREQUENCY = rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, coalesce(source, '') AS host, coalesce(text, '') AS text FROM documents),
w AS (SELECT k, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS w FROM d),
win AS (SELECT k, i, array_to_string(w[i : i + 2], ' ') AS g FROM w, unnest(range(1, len(w) - 1)) AS t(i)),
again AS (SELECT k, i FROM win SEMI JOIN (SELECT k, g FROM win GROUP BY ALL HAVING count(*) > 1) USING (k, g)),
rep AS (SELECT k, count(DISTINCT p) AS n_repeat FROM (SELECT k, unnest([i, i + 1, i + 2]) AS p FROM again) GROUP BY k),
raw AS (SELECT k, unnest(string_split(text, chr(10))) AS l FROM d),
dup AS (SELECT k, count(*) - count(DISTINCT l) AS n_dup FROM raw WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY k),
texts AS (SELECT host, text, min(k) AS k FROM d GROUP BY ALL),
hosts AS (SELECT host, count(*) AS texts FROM texts GROUP BY host),
lines AS (SELECT host, texts.k, {_NORM_LINE} AS line FROM texts JOIN raw USING (k)),
freq AS (SELECT host, line FROM (SELECT host, line, count(DISTINCT k) AS n FROM lines WHERE line <> '' GROUP BY ALL) JOIN hosts USING (host) WHERE n > 20 AND (n > 0.10 * texts OR n > 200)),
lost AS (SELECT host, k, sum(len(string_split(line, ' '))) AS lost FROM lines JOIN freq USING (host, line) GROUP BY ALL),
m AS (SELECT d.k, doc_id, d.host, d.text, len(w) AS n_words, coalesce(list_sum([length(x) FOR x IN w]), 0) AS word_chars,
  length(regexp_replace(d.text, '[^#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(n_dup, 0) AS n_dup_lines, coalesce(n_repeat, 0) AS n_repeat_words,
  coalesce(lost, 0) AS n_removed_words
  FROM d JOIN w USING (k) LEFT JOIN rep USING (k) LEFT JOIN dup USING (k) JOIN texts ON texts.host = d.host AND texts.text = d.text LEFT JOIN lost ON lost.k = texts.k)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines,
  CAST(n_repeat_words AS BIGINT) AS n_repeat_words, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND n_removed_words <= 0.5 * n_words AS kept, CAST(n_removed_words AS BIGINT) AS n_removed_words
FROM m
"""
