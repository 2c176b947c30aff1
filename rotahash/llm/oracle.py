"""DuckDB SQL of the operators that SQL can express, written from their definitions."""

from __future__ import annotations

#: Every string of 100 bytes (200 hexadecimal digits) and where it starts first.
SUFFIX_DEDUP = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS (SELECT doc_id, i, substr(h, 2 * i + 1, 200) AS s FROM (SELECT doc_id, h, unnest(range(length(h) // 2 - 99)) AS i FROM d WHERE length(h) >= 200)),
f AS (SELECT s, min(struct_pack(d := doc_id, i := i)) AS first FROM w GROUP BY s HAVING count(*) > 1),
g AS (SELECT w.doc_id, w.i FROM w JOIN f USING (s) WHERE struct_pack(d := w.doc_id, i := w.i) > f.first),
n AS (SELECT doc_id, i, lag(i) OVER o AS before, lead(i) OVER o AS after FROM g WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
c AS (SELECT doc_id, CAST(sum(least(100, coalesce(after - i, 100))) AS BIGINT) AS n_removed, count(*) FILTER (WHERE before IS NULL OR i - before > 100) AS n_spans FROM n GROUP BY 1),
k AS (
  SELECT n.doc_id, i AS pos, substr(h, 2 * coalesce(before + 100, 0) + 1, 2 * greatest(0, i - coalesce(before + 100, 0))) AS part FROM n JOIN d USING (doc_id)
  UNION ALL SELECT n.doc_id, i + 100, substr(h, 2 * (i + 100) + 1) FROM n JOIN d USING (doc_id) WHERE after IS NULL),
p AS (SELECT doc_id, string_agg(part, '' ORDER BY pos) AS kept FROM k GROUP BY 1)
SELECT d.doc_id, length(h) // 2 AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, h))) AS kept_sha256
FROM d LEFT JOIN c ON c.doc_id = d.doc_id LEFT JOIN p ON p.doc_id = d.doc_id"""

JACCARD_JOIN = """
WITH RECURSIVE t AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^0-9a-z\\x{80}-\\x{10FFFF}]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(list_slice(w, i, i + 4), ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM t),
z AS (SELECT doc_id, count(*) AS n, md5(string_agg(g, '|' ORDER BY g)) AS whole FROM s GROUP BY 1),
r AS (SELECT whole, min(doc_id) AS copy_id FROM z GROUP BY 1),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM c JOIN z p ON p.doc_id = x JOIN z q ON q.doc_id = y WHERE k >= 0.8 * (p.n + q.n - k) - 1e-6),
reach AS (SELECT x, y FROM l UNION SELECT reach.x, l.y FROM reach JOIN l ON reach.y = l.x),
m AS (SELECT x, least(x, min(y)) AS low FROM reach GROUP BY 1),
o AS (SELECT x, count(*) AS links FROM l GROUP BY 1)
SELECT t.doc_id, coalesce(m.low, t.doc_id) AS class_id, coalesce(r.copy_id, t.doc_id) AS copy_id, coalesce(o.links, 0) AS n_links, coalesce(z.n, 0) AS n_shingles
FROM t LEFT JOIN z ON z.doc_id = t.doc_id LEFT JOIN r ON r.whole = z.whole LEFT JOIN m ON m.x = t.doc_id LEFT JOIN o ON o.x = t.doc_id"""

EMBEDDING_JOIN = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
g AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS n FROM v WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
l AS (SELECT a.vec_id AS x, b.vec_id AS y FROM g a JOIN g b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.95),
reach AS (SELECT x, y FROM l UNION SELECT reach.x, l.y FROM reach JOIN l ON reach.y = l.x),
m AS (SELECT x, least(x, min(y)) AS low FROM reach GROUP BY 1),
o AS (SELECT x, count(*) AS links FROM l GROUP BY 1)
SELECT vec_id, coalesce(links, 0) AS n_links, coalesce(low, vec_id) AS component_id, coalesce(low, vec_id) = vec_id AS kept FROM v LEFT JOIN m ON m.x = vec_id LEFT JOIN o ON o.x = vec_id"""


def licenses(templates, threshold: float) -> str:
    """Best template of each document, and the number of its units that match some template."""
    rows = ", ".join("({}, '{}', '{}')".format(k, n.replace("'", "''"), t.replace("'", "''")) for k, (n, t) in enumerate(templates))
    words = "list_filter(regexp_split_to_array(lower({0}), '[^0-9a-z\\x{{80}}-\\x{{10FFFF}}]+'), lambda x: x <> '')"
    grams = "list_distinct(list_transform(range(1, len(w)), lambda i: concat(w[i], ' ', w[i + 1])))"
    return f"""
WITH t AS (SELECT k, name, {grams} AS g FROM (SELECT k, name, {words.format("body")} AS w FROM (VALUES {rows}) AS v(k, name, body))),
l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS body, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) - 1 AS line FROM documents),
m AS (SELECT doc_id, line, {words.format("body")} AS w FROM l),
u AS (SELECT doc_id, line, w FROM m UNION ALL SELECT doc_id, -1, flatten(list(w ORDER BY line)) FROM m WHERE len(w) > 0 AND w[1] <> 'copyright' GROUP BY 1),
b AS (SELECT doc_id, line, {grams} AS g FROM u WHERE len(w) > 1),
d AS (SELECT doc_id, line, k, name, 2 * len(list_intersect(b.g, t.g)) / CAST(len(b.g) + len(t.g) AS DOUBLE) AS dice FROM b JOIN t ON 2 * least(len(b.g), len(t.g)) >= {threshold - 1e-9} * (len(b.g) + len(t.g))),
h AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY dice DESC, line, k) AS r FROM d WHERE dice >= {threshold - 1e-12}),
n AS (SELECT doc_id, count(DISTINCT line) AS n FROM h GROUP BY 1)
SELECT documents.doc_id, name AS license, coalesce(dice, 0.0) AS dice, CAST(line AS BIGINT) AS line, coalesce(n, 0) AS n_matches FROM documents LEFT JOIN h ON h.doc_id = documents.doc_id AND r = 1 LEFT JOIN n ON n.doc_id = documents.doc_id"""
