"""DuckDB SQL with the results of those queries that SQL can express, over the whole tables.

Plain definitions: windows and shingles as strings, all cosines, reachability by recursion. Only the line query joins
rarest words first, as all pairs of lines with a common word are too many for any engine.
"""

from __future__ import annotations

_FOLDED = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_REACH = """e AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach AS (SELECT a AS node, b AS other FROM e UNION SELECT r.node, e.b FROM reach r JOIN e ON r.other = e.a),
part AS (SELECT node, least(node, min(other)) AS component FROM reach GROUP BY node)"""

_words = rf"coalesce(regexp_extract_all({_FOLDED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), [])"
_tokens = rf"coalesce(regexp_extract_all({_FOLDED}, '[^\x20\x09-\x0D]+'), [])"
_line_words = r"list_filter(regexp_split_to_array(lower(line), '[ \t\x0B\f\r]+'), lambda w: w <> '')"

ORACLES = {
    "op2_decontaminate": f"""WITH i AS (SELECT CAST(item_id AS VARCHAR) AS item_id, {_words} AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[p : p + least(len(w), 10) - 1], ' ') AS s FROM i, unnest(range(1, greatest(len(w) - 9, 1) + 1)) u(p) WHERE len(w) > 0),
d AS (SELECT doc_id, {_words} AS w FROM documents), sizes AS (SELECT DISTINCT n FROM win),
hit AS (SELECT doc_id, p, n, item_id FROM (SELECT doc_id, p, n, array_to_string(w[p : p + n - 1], ' ') AS s FROM d, sizes, unnest(range(1, len(w) - n + 2)) u(p)) JOIN win USING (n, s)),
marked AS (SELECT doc_id, count(DISTINCT p + k) AS n_hit FROM hit, unnest(range(0, n)) u(k) GROUP BY doc_id),
found AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id, ',' ORDER BY item_id) AS items FROM hit GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN marked USING (doc_id) LEFT JOIN found USING (doc_id)""",
    "op3_near_duplicates": f"""WITH RECURSIVE d AS (SELECT doc_id, {_tokens} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[p : p + 4], ' ') AS s FROM d, unnest(range(1, greatest(len(w) - 4, 1) + 1)) u(p) WHERE len(w) > 0),
z AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS o FROM s x JOIN s y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM c JOIN z p ON p.doc_id = a JOIN z q ON q.doc_id = b WHERE 100 * o >= 80 * (p.n + q.n - o)),
{_REACH}
SELECT doc_id, coalesce(n, 0) AS n_shingles, coalesce(component, doc_id) AS component_id FROM d LEFT JOIN z USING (doc_id) LEFT JOIN part ON part.node = doc_id""",
    "op4_embeddings": f"""WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings),
fine AS (SELECT vec_id, x, sqrt(list_inner_product(x, x)) AS size FROM v WHERE len(x) > 0 AND len(list_filter(x, lambda t: t IS NULL OR isnan(t) OR isinf(t))) = 0 AND len(list_filter(x, lambda t: t <> 0)) > 0),
links AS (SELECT p.vec_id AS a, q.vec_id AS b FROM fine p JOIN fine q ON p.vec_id < q.vec_id AND len(p.x) = len(q.x) WHERE list_inner_product(p.x, q.x) / (p.size * q.size) >= 0.95),
{_REACH}, n AS (SELECT a AS vec_id, count(*) AS n FROM e GROUP BY a)
SELECT vec_id, coalesce(n, 0) AS n_links, coalesce(component, vec_id) AS component_id, vec_id = coalesce(component, vec_id) AS kept FROM v LEFT JOIN n USING (vec_id) LEFT JOIN part ON part.node = vec_id""",
    "op9_line_dedup": f"""WITH l AS (SELECT doc_id, ln, string_split(text, chr(10))[ln] AS line FROM documents, unnest(range(1, len(string_split(text, chr(10))) + 1)) u(ln)),
w AS (SELECT doc_id, ln, line, list_sort(list_distinct({_line_words})) AS ws FROM l),
k AS (SELECT ws, len(ws) AS n, min((doc_id, ln)) AS place FROM w WHERE len(ws) > 0 GROUP BY ws),
t AS (SELECT place, n, unnest(ws) AS t FROM k), f AS (SELECT t, count(*) AS df FROM t GROUP BY t),
p AS (SELECT place, n, t FROM t JOIN f USING (t) QUALIFY row_number() OVER (PARTITION BY place ORDER BY df, t) <= n - (4 * n + 4) // 5 + 1),
c AS (SELECT DISTINCT x.place AS a, y.place AS b FROM p x JOIN p y ON x.t = y.t AND x.place < y.place AND 5 * least(x.n, y.n) >= 4 * greatest(x.n, y.n)),
gone AS (SELECT DISTINCT b AS place FROM c JOIN k x ON x.place = a JOIN k y ON y.place = b WHERE 9 * len(list_intersect(x.ws, y.ws)) >= 4 * (x.n + y.n)),
stays AS (SELECT place FROM k WHERE place NOT IN (SELECT place FROM gone)),
kept AS (SELECT doc_id, ln, line FROM w WHERE len(ws) = 0 OR (doc_id, ln) IN (SELECT place FROM stays)),
joined AS (SELECT doc_id, count(*) AS n, string_agg(line, chr(10) ORDER BY ln) AS text FROM kept GROUP BY doc_id)
SELECT doc_id, CAST(coalesce(len(string_split(d.text, chr(10))), 0) AS BIGINT) AS n_lines, CAST(coalesce(len(string_split(d.text, chr(10))), 0) - coalesce(n, 0) AS BIGINT) AS n_removed, CASE WHEN d.text IS NOT NULL THEN coalesce(joined.text, '') END AS text
FROM documents d LEFT JOIN joined USING (doc_id)""",
}
