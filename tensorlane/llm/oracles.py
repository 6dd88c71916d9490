"""DuckDB SQL that gives the same rows as the registered queries, where SQL can."""

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP2 = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
i AS (SELECT item_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
iw AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[p:p + 9], ' ') AS k
  FROM (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 9) + 1)) AS p FROM i WHERE len(w) > 0)
),
dw AS (
  SELECT r, p, n, array_to_string(w[p:p + n - 1], ' ') AS k
  FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM iw) WHERE len(w) >= n)
),
o AS (SELECT r, p, n, item_id FROM dw JOIN iw USING (n, k)),
h AS (SELECT r, count(DISTINCT q) AS n_hit FROM (SELECT r, unnest(range(p, p + n)) AS q FROM (SELECT DISTINCT r, p, n FROM o)) GROUP BY r),
f AS (SELECT r, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS id FROM o) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (r) LEFT JOIN f USING (r)
"""

OP1 = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS h FROM pages),
g AS (SELECT *, max(page_id) OVER (PARTITION BY h) AS top FROM p)
SELECT page_id, n::BIGINT AS payload_bytes,
       array_to_string(list_transform(range(0, 32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
         (((('0x' || substr(h, (k // 4 * 5 + 1)::INT, 5))::INT >> (5 * (3 - k % 4))::INT) & 31) + 1)::INT, 1)), '') AS payload_digest,
       CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id = top THEN NULL ELSE top END AS refers_to,
       1::BIGINT AS n_request, 1::BIGINT AS n_metadata
FROM g
"""

_SP = r"[\x20\x09-\x0D]"

OP10_BASE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
x AS (
  SELECT r, p, array_to_string(w[p:p + 7], ' ') AS k FROM (SELECT r, w, unnest(range(1, len(w) - 6)) AS p FROM d WHERE len(w) >= 8)
),
h AS (SELECT r, count(DISTINCT q) AS n FROM (
  SELECT r, unnest(range(p, p + 8)) AS q FROM (SELECT r, p, count(*) OVER (PARTITION BY r, k) AS c FROM x) WHERE c > 1) GROUP BY r),
l AS (SELECT r, count(*) - count(DISTINCT line) AS n FROM (SELECT r, unnest(string_split(t, chr(10))) AS line FROM d)
  WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, list_sum(list_transform(w, lambda s: length(s)))::BIGINT AS word_chars,
  len(regexp_extract_all(t, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(l.n, 0)::BIGINT AS n_dup_lines, coalesce(h.n, 0)::BIGINT AS n_repeat_words,
  len(w) < 20 OR 100 * coalesce(h.n, 0) > 30 * len(w) AS base_failed
FROM d LEFT JOIN h USING (r) LEFT JOIN l USING (r)
"""

OP7 = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, text, hex(encode(coalesce(text, ''))) AS x FROM documents),
w AS (SELECT r, s, md5(substr(x, 2 * s + 1, 800)) AS k FROM (SELECT r, x, unnest(range(0, length(x) // 2 - 399)) AS s FROM d)),
u AS (SELECT r, s FROM w WHERE k IN (SELECT k FROM w GROUP BY k HAVING count(*) > 1)),
i AS (SELECT r, s, sum(g) OVER (PARTITION BY r ORDER BY s) AS g
      FROM (SELECT r, s, CASE WHEN s > lag(s) OVER (PARTITION BY r ORDER BY s) + 400 THEN 1 ELSE 0 END AS g FROM u)),
p AS (SELECT r, min(s) AS a, max(s) + 400 AS b FROM i GROUP BY r, g),
q AS (SELECT r, a, b, coalesce(lag(b) OVER (PARTITION BY r ORDER BY a), 0) AS z FROM p),
k AS (SELECT r, sum(b - a) AS n_removed, count(*) AS n_spans, string_agg(substr(x, (2 * z + 1)::BIGINT, (2 * (a - z))::BIGINT), '' ORDER BY a) AS head, max(b) AS e
      FROM q JOIN d USING (r) GROUP BY r),
t AS (SELECT r, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS v FROM d),
ws AS (SELECT r, p, md5(array_to_string(v[p:p + 49], ' ')) AS k FROM (SELECT r, v, unnest(range(1, len(v) - 48)) AS p FROM t)),
wu AS (SELECT r, p FROM ws WHERE k IN (SELECT k FROM ws GROUP BY k HAVING count(*) > 1)),
wn AS (SELECT r, sum(least(50, coalesce(nxt - p, 50)))::BIGINT AS n_shared_words
       FROM (SELECT r, p, lead(p) OVER (PARTITION BY r ORDER BY p) AS nxt FROM wu) GROUP BY r)
SELECT doc_id, (length(x) // 2)::BIGINT AS n_bytes, coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_spans, 0)::BIGINT AS n_spans,
       sha256(unhex(coalesce(head || substr(x, (2 * e + 1)::BIGINT), x))) AS kept_sha256,
       coalesce(n_shared_words, 0)::BIGINT AS n_shared_words
FROM d LEFT JOIN k USING (r) LEFT JOIN wn USING (r)
"""

OP3 = rf"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT r, array_to_string(w[p:p + 4], ' ') AS k
      FROM (SELECT r, w, unnest(range(1, greatest(1, len(w) - 4) + 1)) AS p FROM d WHERE len(w) > 0)),
n AS (SELECT r, count(*) AS n FROM s GROUP BY r),
c AS (SELECT a.r AS a, b.r AS b, count(*) AS c FROM s a JOIN s b ON a.k = b.k AND a.r < b.r GROUP BY ALL),
l AS (SELECT a, b FROM c JOIN n x ON x.r = a JOIN n y ON y.r = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
g(r, m) AS (SELECT r, r FROM d UNION SELECT g.r, e.b FROM g JOIN e ON e.a = g.m),
z AS (SELECT g.r, min(x.doc_id) AS component_id FROM g JOIN d x ON x.r = g.m GROUP BY g.r)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept
FROM d JOIN z USING (r) LEFT JOIN n USING (r)
"""
