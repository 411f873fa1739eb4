"""SQL for those training-data queries that SQL can express, written another way round than the operators."""

from __future__ import annotations

import string

_WORDS = r"regexp_extract_all({text}, '[^\x20\x09-\x0D]+')"
_LOWER = f"translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}')"

#: All windows of 35 words, those that occur twice, and the words they cover.
SUBSTRINGS = f"""
WITH w AS (SELECT doc_id, {_WORDS.format(text="coalesce(text, '')")} ws FROM documents),
win AS (SELECT doc_id, i, md5(array_to_string(ws[i:i+34], ' ')) h FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) i FROM w WHERE len(ws) >= 35)),
twice AS (SELECT h FROM win GROUP BY h HAVING count(*) > 1),
gone AS (SELECT DISTINCT doc_id, i + k.k j FROM win JOIN twice USING (h), range(35) k(k)),
g AS (SELECT doc_id, list(j) js, count(*) c FROM gone GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(c, 0) AS n_removed,
  sha256(array_to_string(CASE WHEN js IS NULL THEN ws ELSE list_filter(ws, lambda x, i: NOT list_contains(js, i)) END, ' ')) AS kept_sha256
FROM w LEFT JOIN g ON g.doc_id = w.doc_id
"""

#: All pairs of documents that share a shingle, exact similarity, and reachability by recursion.
NEAR_DUPLICATES = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format(text=_LOWER)} ws FROM documents),
s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')] ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' '))) END sh FROM w),
x AS (SELECT doc_id, unnest(sh) v FROM s),
n AS (SELECT doc_id, CAST(len(sh) AS BIGINT) n FROM s),
p AS (SELECT a.doc_id a, b.doc_id b, count(*) c FROM x a JOIN x b ON a.v = b.v AND a.doc_id < b.doc_id GROUP BY ALL),
link AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
sym AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach AS (SELECT doc_id d, doc_id r FROM n UNION SELECT reach.d, sym.b FROM reach JOIN sym ON sym.a = reach.r)
SELECT n.doc_id, n.n AS n_shingles, m.r AS component_id, m.r = n.doc_id AS kept FROM n JOIN (SELECT d, min(r) r FROM reach GROUP BY d) m ON m.d = n.doc_id
"""

#: Pairs of lines (of 8 characters at least) that agree on a half, and how long they agree from the front and from the back. Equal lines of any length repeat one another.
LINES = """
WITH a AS (SELECT doc_id, string_split(text, chr(10)) ls FROM documents WHERE text IS NOT NULL),
l AS (SELECT doc_id, unnest(range(len(ls))) pos, unnest(ls) line FROM a),
c AS (SELECT * FROM l WHERE trim(line) <> ''),
f AS (SELECT line, min((doc_id, pos)) ref, length(line) n FROM c GROUP BY line),
k AS (SELECT line, n, m.m, s.s, CASE s.s WHEN 0 THEN left(line, m.m // 2) ELSE right(line, m.m // 2) END h FROM f, (VALUES (0), (1)) d(d), (VALUES (0), (1)) s(s), LATERAL (SELECT n - d.d AS m) m WHERE n >= 8),
p AS (SELECT DISTINCT x.line a, y.line b, x.n na, y.n nb, x.m FROM k x JOIN k y ON x.m = y.m AND x.s = y.s AND x.h = y.h AND x.line < y.line AND least(x.n, y.n) = x.m),
z AS (SELECT a, b, na, nb, m, string_split(a, '') ca, string_split(b, '') cb FROM p),
q AS (SELECT a, b, greatest(na, nb) big, list_position(list_transform(range(1, m + 1), lambda i: ca[i] = cb[i]), false) fw, list_position(list_transform(range(m), lambda i: ca[na - i] = cb[nb - i]), false) bw, m FROM z),
near AS (SELECT a, b FROM q WHERE coalesce(nullif(fw, 0) - 1, m) + coalesce(nullif(bw, 0) - 1, m) >= big - 1),
sym AS (SELECT a, b FROM near UNION ALL SELECT b, a FROM near),
best AS (SELECT sym.a line, min(g.ref) ref FROM sym JOIN f g ON g.line = sym.b GROUP BY 1),
gone AS (SELECT c.doc_id, c.pos, (c.doc_id, c.pos) = f.ref AS near FROM c JOIN f ON f.line = c.line LEFT JOIN best ON best.line = c.line WHERE (c.doc_id, c.pos) <> f.ref OR best.ref < f.ref),
r AS (SELECT doc_id, count(*) n_removed, count(*) FILTER (near) n_near, array_to_string(list_sort(list(pos)), ',') removed FROM gone GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(len(a.ls), 0) AS BIGINT) AS n_lines, coalesce(n_removed, 0) AS n_removed, coalesce(n_near, 0) AS n_near, coalesce(removed, '') AS removed
FROM documents d LEFT JOIN a ON a.doc_id = d.doc_id LEFT JOIN r ON r.doc_id = d.doc_id
"""
