"""DuckDB SQL for the training-data queries that SQL can express."""

from __future__ import annotations

from .decontaminate import ASCII_CAPITALS, ASCII_SMALL

_ALNUM = rf"regexp_extract_all(translate(coalesce(text, ''), '{ASCII_CAPITALS}', '{ASCII_SMALL}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_PLAIN = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_LOWER = rf"regexp_extract_all(translate(coalesce(text, ''), '{ASCII_CAPITALS}', '{ASCII_SMALL}'), '[^\x20\x09-\x0D]+')"

OP2 = rf"""
WITH d AS (SELECT doc_id, {_PLAIN} AS w FROM documents),
p AS (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS i FROM d WHERE len(w) >= 50),
g AS (SELECT doc_id, i, md5(array_to_string(w[i:i+49], ' ')) AS h FROM p),
f AS (SELECT h, min(doc_id) AS first_doc FROM g GROUP BY h),
c AS (SELECT DISTINCT doc_id, i + k AS place FROM g JOIN f USING (h), range(0, 50) AS r(k) WHERE first_doc < doc_id),
l AS (SELECT doc_id, list(place) AS gone FROM c GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(len(gone), 0) AS BIGINT) AS n_removed,
  sha256(coalesce(array_to_string(CASE WHEN gone IS NULL THEN w ELSE
    [w[j] FOR j IN range(1, len(w) + 1) IF NOT list_contains(gone, j)] END, ' '), '')) AS kept_sha256
FROM d LEFT JOIN l USING (doc_id)
"""

OP6 = rf"""
WITH RECURSIVE d AS (SELECT doc_id, {_LOWER} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i+2], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS o FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM o JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * o >= 90 * (na.n + nb.n - o)),
r AS (SELECT doc_id, doc_id AS other FROM d UNION SELECT r.doc_id, e.b FROM r JOIN e ON e.a = r.other)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.other) AS component_id
FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN r ON r.doc_id = d.doc_id GROUP BY ALL
"""

OP9 = rf"""
WITH b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_ALNUM} AS w FROM benchmark),
g AS (SELECT DISTINCT item, least(10, len(w)) AS n, array_to_string(w[i:i+least(10, len(w))-1], ' ') AS h
  FROM (SELECT item, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)),
d AS (SELECT doc_id, {_ALNUM} AS w FROM documents),
z AS (SELECT DISTINCT n FROM g),
p AS (SELECT doc_id, n, i, array_to_string(w[i:i+n-1], ' ') AS h
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, z WHERE len(w) >= n)),
m AS (SELECT doc_id, item, p.n, i FROM p JOIN g ON g.n = p.n AND g.h = p.h),
k AS (SELECT doc_id, count(DISTINCT i + j) AS n_hit FROM m, range(0, 10) AS r(j) WHERE j < n GROUP BY doc_id),
t AS (SELECT doc_id, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM m GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit,
  CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN k USING (doc_id) LEFT JOIN t USING (doc_id)
"""

_BITS = "array_to_string([format('{:04b}', strpos('0123456789abcdef', c) - 1) FOR c IN string_split(sha1(html), '')], '')"
OP10 = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
q AS (SELECT page_id, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes, {_BITS} AS bits, min(page_id) OVER (PARTITION BY html) AS first_id FROM p)
SELECT page_id, payload_bytes,
  array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + CAST(('0b' || substr(bits, 5 * i + 1, 5)) AS INTEGER), 1) FOR i IN range(0, 32)], '') AS payload_digest,
  CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = first_id THEN NULL ELSE first_id END AS refers_to
FROM q
"""

ORACLES = {
    "op2_substring_dedup": OP2,
    "op6_ngram_jaccard_join": OP6,
    "op9_decontamination": OP9,
    "op10_warc": OP10,
}
