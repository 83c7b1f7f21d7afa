"""Corpus queries in DuckDB's SQL, by plain window counts and joins."""

from __future__ import annotations

import string

_LOWER = f"translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}')"
_BLANK = r"'[^\x20\x09-\x0D]+'"



def _repeated(n: int) -> str:
    """SQL of (doc_id, removed, spans, kept): bytes in strings of n bytes that start elsewhere too."""
    return f"""(WITH w AS (SELECT doc_id, s, md5(substr(h, 2 * s + 1, {2 * n})) AS g FROM (SELECT doc_id, h, unnest(range(0, (length(h) // 2 - {n - 1})::BIGINT)) AS s FROM d WHERE length(h) >= {2 * n})),
r AS (SELECT doc_id, s FROM w JOIN (SELECT g FROM w GROUP BY g HAVING count(*) > 1) USING (g)),
e AS (SELECT doc_id, s, CASE WHEN s > lag(s) OVER (PARTITION BY doc_id ORDER BY s) + {n} THEN 1 ELSE 0 END AS new FROM r),
k AS (SELECT doc_id, s, sum(new) OVER (PARTITION BY doc_id ORDER BY s) AS k FROM e),
p AS (SELECT doc_id, min(s) AS a, max(s) + {n} AS z FROM k GROUP BY doc_id, k),
q AS (SELECT *, lead(a) OVER (PARTITION BY doc_id ORDER BY a) AS next, row_number() OVER (PARTITION BY doc_id ORDER BY a) AS i FROM p)
SELECT doc_id, sum(z - a)::BIGINT AS removed, count(*) AS spans, string_agg(CASE WHEN i = 1 THEN substr(h, 1, 2 * a) ELSE '' END || substr(h, 2 * z + 1, 2 * (coalesce(next, length(h) // 2) - z)), '' ORDER BY a) AS kept FROM q JOIN d USING (doc_id) GROUP BY doc_id)"""


#: every byte as two hexadecimal digits, so that places count bytes
op2_suffix_dedup = f"""
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents), t AS {_repeated(400)}, u AS {_repeated(240)}
SELECT doc_id, (length(h) // 2)::BIGINT AS n_bytes, coalesce(t.removed, 0)::BIGINT AS n_removed, coalesce(t.spans, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(t.kept, h))) AS kept_sha256,
  coalesce(u.removed, 0)::BIGINT AS passage_bytes, coalesce(u.spans, 0)::BIGINT AS n_passages
FROM d LEFT JOIN t USING (doc_id) LEFT JOIN u USING (doc_id)
"""

op3_jaccard_join = f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOWER}, {_BLANK}) AS w FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(w[s : s + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS s FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n, md5(string_agg(g, chr(10) ORDER BY g)) AS same FROM g GROUP BY doc_id),
c AS (SELECT same, min(doc_id) AS rep, count(*) AS mult, any_value(n) AS n FROM n GROUP BY same),
x AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM (SELECT g.* FROM g JOIN c ON doc_id = rep) a JOIN (SELECT g.* FROM g JOIN c ON doc_id = rep) b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
l AS (SELECT x.a, x.b, cb.mult FROM x JOIN c ca ON ca.rep = x.a JOIN c cb ON cb.rep = x.b WHERE 9 * shared >= 4 * (ca.n + cb.n)),
r AS (SELECT rep AS node, rep AS root FROM c UNION SELECT l.b, r.root FROM r JOIN l ON l.a = r.node),
m AS (SELECT node, min(root) AS class_id FROM r GROUP BY node),
k AS (SELECT a, sum(mult) AS links FROM l GROUP BY a)
SELECT d.doc_id, coalesce(class_id, d.doc_id) AS class_id, coalesce(rep, d.doc_id) AS copy_id, coalesce(coalesce(links, 0) + mult - 1, 0)::BIGINT AS n_links
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.same = n.same LEFT JOIN m ON m.node = rep LEFT JOIN k ON k.a = rep
"""

op8_word_windows = f"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), {_BLANK}) AS w FROM documents),
v AS (SELECT doc_id, s, array_to_string(w[s : s + 19], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, (len(w) - 18)::BIGINT)) AS s FROM d WHERE len(w) >= 20)),
r AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY g ORDER BY doc_id, s) AS k FROM v) WHERE k > 1),
x AS (SELECT DISTINCT doc_id, unnest(range(s, s + 20)) AS i FROM r),
e AS (SELECT doc_id, count(*) AS removed, sum(CASE WHEN i = before + 1 THEN 0 ELSE 1 END) AS spans FROM (SELECT doc_id, i, coalesce(lag(i) OVER (PARTITION BY doc_id ORDER BY i), -9) AS before FROM x) GROUP BY doc_id),
u AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
k AS (SELECT doc_id, string_agg(word, ' ' ORDER BY i) AS kept FROM u ANTI JOIN x USING (doc_id, i) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN e USING (doc_id) LEFT JOIN k USING (doc_id)
"""

_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
op9_decontaminate = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents), b AS (SELECT item_id::VARCHAR AS item, {_WORDS} AS w FROM benchmark),
v AS (SELECT DISTINCT item, len(g) AS n, array_to_string(g, ' ') AS g FROM (SELECT item, w[s : s + 12] AS g FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 11, 2))) AS s FROM b WHERE len(w) > 0))),
t AS (SELECT doc_id, s, n, array_to_string(w[s : s + n - 1], ' ') AS g FROM (SELECT doc_id, w, n, unnest(range(1, (len(w) - n + 2)::BIGINT)) AS s FROM d, (SELECT DISTINCT n FROM v) WHERE len(w) >= n)),
h AS (SELECT doc_id, s, n, item FROM t JOIN v USING (n, g)),
x AS (SELECT doc_id, count(DISTINCT i) AS hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS i FROM h) GROUP BY doc_id),
y AS (SELECT doc_id, count(*) AS items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT doc_id, item FROM h) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(hit, 0)::BIGINT AS n_hit, coalesce(items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(hit, 0) > 0 AND 20 * coalesce(hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN x USING (doc_id) LEFT JOIN y USING (doc_id)
"""

ORACLES = {"op2_suffix_dedup": op2_suffix_dedup, "op3_jaccard_join": op3_jaccard_join, "op8_word_windows": op8_word_windows, "op9_decontaminate": op9_decontaminate}
