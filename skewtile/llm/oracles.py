"""DuckDB SQL for the queries of this subpackage that SQL can express over whole tables."""

from __future__ import annotations

_WORD = r"[^\x20\x09-\x0D]+"
_WORDS = f"regexp_extract_all(coalesce(text, ''), '{_WORD}')"

_TURNS = """(SELECT CAST(conv_id AS BIGINT) AS conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, i, r, '<|im_end|><|im_start|>assistant ok' FROM (VALUES (0, 'user'), (1, 'assistant')) AS v(i, r))"""
OP2 = rf"""
WITH t AS (SELECT *, regexp_matches(text, '<\\*\|im_(start|end)\|>') AS hot, regexp_replace(text, '<(\\*\|im_(start|end)\|>)', '<\\\1', 'g') AS safe FROM {_TURNS})
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(length('<|im_start|>' || role || chr(10) || safe || '<|im_end|>' || chr(10))) AS BIGINT) AS formatted_chars,
  CAST(sum(CAST(hot AS INTEGER)) AS INTEGER) AS n_escaped, TRUE AS round_trip
FROM t GROUP BY conv_id"""

_SETS = f"""
w AS (SELECT doc_id, list_transform({_WORDS}, lambda x: translate(x, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS ws FROM documents),
g AS (SELECT doc_id, CASE WHEN len(ws) >= 4 THEN list_distinct(list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i+3], ' '))) WHEN len(ws) > 0 THEN ['short ' || array_to_string(ws, ' ')] ELSE [] END AS s FROM w),
n AS (SELECT doc_id, len(s) AS n FROM g),
e AS (SELECT doc_id, md5_number(t) AS h FROM (SELECT doc_id, unnest(s) AS t FROM g)),
"""
OP3 = f"""
WITH RECURSIVE {_SETS}
links AS (SELECT p.a, p.b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS o FROM e x JOIN e y ON x.h = y.h AND x.doc_id <> y.doc_id GROUP BY 1, 2) p
  JOIN n na ON na.doc_id = p.a JOIN n nb ON nb.doc_id = p.b WHERE 100 * o >= 85 * (na.n + nb.n - o)),
reach(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b)
SELECT n.doc_id, CAST(n.n AS BIGINT) AS n_shingles, c.c AS component_id, coalesce(k.k, 0) AS n_links
FROM n JOIN (SELECT a, min(b) AS c FROM reach GROUP BY a) c ON c.a = n.doc_id LEFT JOIN (SELECT a, count(*) AS k FROM links GROUP BY a) k ON k.a = n.doc_id"""

OP4 = r"""
WITH u AS (SELECT page_id, translate(CASE WHEN contains(url, '://') THEN regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1) ELSE '' END, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  CASE WHEN contains(url, '://') THEN regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1) ELSE '' END AS path FROM (SELECT page_id, coalesce(url, '') AS url FROM pages)),
r AS (SELECT * FROM (VALUES ('net/', 'net', '/', 'block'), ('example.net/en/', 'example.net', '/en/', 'allow'), ('example.com/de/', 'example.com', '/de/', 'block'), ('org/fr/', 'org', '/fr/', 'allow')) AS v(rule, site, start, said)),
m AS (SELECT u.*, r.rule, r.said, row_number() OVER (PARTITION BY u.page_id ORDER BY length(r.rule) DESC) AS k FROM u LEFT JOIN r ON (u.host = r.site OR ends_with(u.host, '.' || r.site)) AND starts_with(u.path, r.start))
SELECT page_id, host, path, rule, coalesce(said, CASE WHEN substr(md5(host), 1, 1) < '4' OR contains(host, 'farm') THEN 'block' ELSE 'allow' END) AS verdict FROM m WHERE k = 1"""

OP5 = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages), h AS (SELECT page_id, octet_length(b) AS n, sha1(b) AS x, min(page_id) OVER (PARTITION BY b) AS f FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST(((16 * (position(substr(x, 1 + 5 * i // 4, 1) IN '0123456789abcdef') - 1) + greatest(0, position(substr(x || '0', 2 + 5 * i // 4, 1) IN '0123456789abcdef') - 1)) >> (3 - 5 * i % 4)) & 31 AS INTEGER), 1)), '') AS payload_digest,
  CASE WHEN page_id = f THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> f THEN f END AS refers_to FROM h"""

OP7 = f"""
WITH w AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
v AS (SELECT doc_id, i, md5_number(array_to_string(ws[i:i+12], ' ')) AS h FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM w)),
f AS (SELECT h, min(doc_id) AS d FROM v GROUP BY h),
x AS (SELECT v.doc_id, list(i) AS hits FROM v JOIN f ON f.h = v.h AND f.d < v.doc_id GROUP BY v.doc_id),
gone AS (SELECT doc_id, list_distinct(flatten(list_transform(hits, lambda i: range(i, i + 13)))) AS g FROM x),
k AS (SELECT w.doc_id, ws, coalesce(g, []) AS g FROM w LEFT JOIN gone ON gone.doc_id = w.doc_id),
p AS (SELECT doc_id, len(ws) AS n, len(g) AS r, unnest(range(1, len(ws) + 1)) AS i, ws FROM k),
s AS (SELECT p.doc_id, string_agg(p.ws[p.i], ' ' ORDER BY p.i) AS kept FROM p LEFT JOIN (SELECT doc_id, unnest(g) AS i FROM gone) z ON z.doc_id = p.doc_id AND z.i = p.i WHERE z.i IS NULL GROUP BY p.doc_id)
SELECT k.doc_id, CAST(len(k.ws) AS BIGINT) AS n_words, CAST(len(k.g) AS BIGINT) AS n_removed, sha256(coalesce(s.kept, '')) AS kept_sha256 FROM k LEFT JOIN s ON s.doc_id = k.doc_id"""

OP8 = f"""
WITH d AS (SELECT doc_id, source, CAST(len({_WORDS}) AS BIGINT) AS size FROM documents),
s0 AS (SELECT source, CAST(sum(size) AS BIGINT) AS s FROM d GROUP BY source),
s1 AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS w FROM s0),
s2 AS (SELECT *, 3 * s / w AS ratio FROM s1),
s3 AS (SELECT *, (sum(s) OVER () - 3 * coalesce(sum(s) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(w) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM s2),
s4 AS (SELECT source, s, least(max(CASE WHEN level <= ratio THEN level END) OVER () * w, CAST(3 * s AS DOUBLE)) AS target FROM s3),
r AS (SELECT d.*, row_number() OVER (PARTITION BY source ORDER BY size, md5(CAST(doc_id AS VARCHAR))) - 1 AS k FROM d),
o AS (SELECT r.doc_id, r.size, s4.s AS source_size, s4.target, r.k, CASE WHEN s4.s > 0 THEN s4.target / s4.s ELSE 0e0 END AS f, CAST(CAST('0x' || substr(md5('7' || chr(0) || coalesce(r.source, chr(0))), 1, 8) AS BIGINT) AS DOUBLE) / 4294967296e0 AS u
  FROM r JOIN s4 ON s4.source IS NOT DISTINCT FROM r.source)
SELECT doc_id, size, source_size, target, CAST(floor(u + f * (k + 1)) - floor(u + f * k) AS BIGINT) * size AS taken FROM o"""

OP9 = rf"""
WITH d AS (SELECT doc_id, source AS host, coalesce(text, '') AS text FROM documents),
w AS (SELECT *, {_WORDS} AS ws, string_split(text, chr(10)) AS ls FROM d),
c AS (SELECT doc_id, len(ws) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars, length(text) - length(translate(text, '#*$%&|<>', '')) AS n_symbols FROM w),
lines AS (SELECT doc_id, host, text, line, len(regexp_extract_all(line, '{_WORD}')) AS n, translate(array_to_string(regexp_extract_all(line, '{_WORD}'), ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm FROM (SELECT doc_id, host, text, unnest(ls) AS line FROM w)),
dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM lines WHERE n > 0 GROUP BY doc_id),
g AS (SELECT doc_id, i, md5_number(array_to_string(ws[i:i+2], ' ')) AS h FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
two AS (SELECT doc_id, h FROM g GROUP BY doc_id, h HAVING count(*) > 1),
rep AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT g.doc_id, unnest([i, i + 1, i + 2]) AS j FROM g JOIN two ON two.doc_id = g.doc_id AND two.h = g.h) GROUP BY doc_id),
per AS (SELECT host, count(DISTINCT doc_id) AS docs FROM d GROUP BY host),
hot AS (SELECT l.host, l.norm FROM lines l JOIN per ON per.host IS NOT DISTINCT FROM l.host WHERE n > 0 GROUP BY l.host, l.norm, docs HAVING count(DISTINCT doc_id) > 10 AND count(DISTINCT doc_id) > 0.05 * docs),
gone AS (SELECT l.doc_id, sum(l.n) AS b FROM lines l JOIN hot ON hot.host IS NOT DISTINCT FROM l.host AND hot.norm = l.norm GROUP BY l.doc_id)
SELECT c.doc_id, CAST(n_words AS BIGINT) AS n_words, word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words,
  (n_words < 50 OR 100 * coalesce(rep.n, 0) > 50 * n_words) AS base_failed, CAST(coalesce(b, 0) AS BIGINT) AS n_boilerplate_words,
  NOT (n_words < 50 OR 100 * coalesce(rep.n, 0) > 50 * n_words) AND n_words - coalesce(b, 0) >= 50 AND n_words - coalesce(b, 0) >= 0.2 * n_words AS kept
FROM c LEFT JOIN dup ON dup.doc_id = c.doc_id LEFT JOIN rep ON rep.doc_id = c.doc_id LEFT JOIN gone ON gone.doc_id = c.doc_id"""

ORACLE_SQL = {"op2_chat": OP2, "op3_ngram_join": OP3, "op4_urls": OP4, "op5_warc": OP5, "op7_substring_dedup": OP7, "op8_mixing": OP8, "op9_quality": OP9}
