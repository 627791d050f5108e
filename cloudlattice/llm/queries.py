"""The registered queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from cloudlattice.llm import ann, grid_join, html_extract, licenses, mixing, packing, sharding, shingle_join, suffix_dedup, toxicity

QUERIES = {
    "op1_sharding": sharding.query,
    "op2_html_extract": html_extract.query,
    "op3_shingle_join": shingle_join.query,
    "op4_grid_join": grid_join.query,
    "op5_license_scan": licenses.query,
    "op6_suffix_dedup": suffix_dedup.query,
    "op7_ann": ann.query,
    "op8_toxicity": toxicity.query,
    "op9_mixing": mixing.query,
    "op10_packing": packing.query,
}

#: Every pair of documents that shares a shingle, counted in full; components by spreading every id along links.
SHINGLE_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 4 THEN list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS x, len(w) >= 4 AS whole FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
links AS (SELECT a AS u, b AS v FROM (SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS c FROM s p JOIN s q ON p.x = q.x AND p.whole = q.whole AND p.doc_id <> q.doc_id GROUP BY ALL) JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
reach(doc_id, root) AS (SELECT doc_id, doc_id FROM documents UNION SELECT l.v, r.root FROM reach r JOIN links l ON l.u = r.doc_id)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, root AS component_id FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT doc_id, min(root) AS root FROM reach GROUP BY doc_id) USING (doc_id)"""

#: Every pair of vectors of one label.
VECTOR_SQL = """
WITH RECURSIVE ok AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS u, b.vec_id AS v FROM ok a JOIN ok b ON a.label = b.label AND len(a.v) = len(b.v) AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.v, b.v) >= 0.98),
reach(vec_id, root) AS (SELECT vec_id, vec_id FROM embeddings UNION SELECT l.v, r.root FROM reach r JOIN links l ON l.u = r.vec_id)
SELECT e.vec_id, coalesce(n, 0) AS n_links, root AS component_id, root = e.vec_id AS kept FROM embeddings e LEFT JOIN (SELECT u AS vec_id, count(*) AS n FROM links GROUP BY u) USING (vec_id) JOIN (SELECT vec_id, min(root) AS root FROM reach GROUP BY vec_id) USING (vec_id)"""

#: Every string of 400 bytes of every text, by its MD5 over hexadecimal digits, two for a byte.
SUFFIX_SQL = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
starts AS (SELECT r, k, md5(substr(h, 2 * k + 1, 800)) AS m FROM (SELECT r, h, unnest(range(0, n - 399)) AS k FROM d WHERE n >= 400)),
again AS (SELECT r, k FROM starts WHERE m IN (SELECT m FROM starts GROUP BY m HAVING count(*) > 1)),
edges AS (SELECT r, k, CASE WHEN k <= lag(k) OVER (PARTITION BY r ORDER BY k) + 400 THEN 0 ELSE 1 END AS new FROM again),
spans AS (SELECT r, min(k) AS a, max(k) + 400 AS b FROM (SELECT r, k, sum(new) OVER (PARTITION BY r ORDER BY k ROWS UNBOUNDED PRECEDING) AS s FROM edges) GROUP BY r, s),
cuts AS (SELECT r, a, b, lag(b, 1, 0) OVER (PARTITION BY r ORDER BY a) AS before FROM spans),
kept AS (SELECT r, sum(b - a)::BIGINT AS removed, count(*) AS spans, string_agg(substr(h, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) || substr(any_value(h), 2 * max(b) + 1) AS h FROM cuts JOIN d USING (r) GROUP BY r)
SELECT doc_id, n::BIGINT AS n_bytes, coalesce(removed, 0) AS n_removed, coalesce(spans, 0) AS n_spans, sha256(unhex(coalesce(kept.h, d.h))) AS kept_sha256 FROM d LEFT JOIN kept USING (r)"""

#: Every query against every row, components summed in order.
SEARCH_SQL = """
WITH ok AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
sized AS (SELECT *, sqrt(list_reduce(list_transform(v, lambda x: x * x), lambda s, x: s + x)) AS size FROM ok),
pairs AS (SELECT q.vec_id AS query_id, c.vec_id, list_reduce(list_transform(range(1, len(q.v) + 1), lambda k: q.v[k] * c.v[k]), lambda s, x: s + x) / (q.size * c.size) AS score FROM sized q JOIN sized c ON len(q.v) = len(c.v) AND q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0)
SELECT query_id, rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM pairs) WHERE rank <= 5"""

ORACLES: dict[str, str] = {"op3_shingle_join": SHINGLE_SQL, "op4_grid_join": VECTOR_SQL, "op5_license_scan": licenses.oracle(), "op6_suffix_dedup": SUFFIX_SQL, "op7_ann": SEARCH_SQL}
