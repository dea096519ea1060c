"""DuckDB SQL for the queries that SQL can express."""

ORACLES: dict[str, str] = {
    "op6_cuckoo_exact_dedup": r"""
WITH d AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents
), g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256 FROM d JOIN g USING (t)
""",
    "op9_chosen_path_dedup": r"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(
           translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents
), s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
           ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g
  FROM d
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
k AS (SELECT md5(string_agg(g, '|' ORDER BY g)) AS k, doc_id FROM s GROUP BY doc_id),
r AS (SELECT k, min(doc_id) AS rep FROM k GROUP BY k),
sr AS (SELECT s.doc_id, s.g FROM s JOIN r ON s.doc_id = r.rep),
i AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM sr a JOIN sr b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (
  SELECT a, b FROM i JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 75 * (x.n + y.n - i)
), e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
c(v, m) AS (
  SELECT rep, rep FROM r UNION SELECT e.b, c.m FROM c JOIN e ON e.a = c.v WHERE c.m < e.b
), m AS (SELECT v, min(m) AS component_id FROM c GROUP BY v)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(m.component_id, d.doc_id) AS component_id,
       d.doc_id = coalesce(m.component_id, d.doc_id) AS kept
FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN k ON k.doc_id = d.doc_id LEFT JOIN r ON r.k = k.k LEFT JOIN m ON m.v = r.rep
""",
    "op2_pq_vector_dedup": r"""
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
), ok AS (
  SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(e) > 0
    AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0
), l AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.98
), n AS (SELECT a, count(*) AS n_links FROM l GROUP BY a),
c(x, m) AS (
  SELECT a, a FROM n UNION SELECT l.b, c.m FROM c JOIN l ON l.a = c.x WHERE c.m < l.b
), m AS (SELECT x, min(m) AS m FROM c GROUP BY x)
SELECT v.vec_id, coalesce(n.n_links, 0) AS n_links, coalesce(m.m, v.vec_id) AS component_id, v.vec_id = coalesce(m.m, v.vec_id) AS kept
FROM v LEFT JOIN n ON n.a = v.vec_id LEFT JOIN m ON m.x = v.vec_id
""",
    "op1_fuzzy_license_scan": r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), m(label, notice, e) AS (VALUES
  ('apache', 'apache license', 2), ('apache', 'licensed under the apache license', 4), ('bsd', 'bsd license', 1),
  ('bsd', 'redistribution and use in source and binary forms', 5), ('cc', 'creative commons attribution', 3), ('cc', 'licensed under cc by', 2),
  ('gpl', 'general public license', 3), ('mit', 'mit license', 1), ('mit', 'permission is hereby granted free of charge', 4), ('mpl', 'mozilla public license', 2)
), b(label, phrase, n) AS (VALUES ('mit', 'mit license', 2), ('apache', 'apache license', 2), ('gpl', 'general public license', 3)),
p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d),
s AS (SELECT doc_id, i, k, array_to_string(w[i:i + k - 1], ' ') AS x FROM p, range(1, 14) t(k) WHERE i + k - 1 <= len(w)),
t AS (
  SELECT s.doc_id, m.label, m.notice, s.i - 1 AS i, s.k, levenshtein(s.x, m.notice) AS e
  FROM s JOIN m ON length(s.x) >= length(m.notice) - m.e AND length(s.x) <= length(m.notice) + m.e WHERE levenshtein(s.x, m.notice) <= m.e
), f AS (SELECT doc_id, label, max(1 - CAST(e AS DOUBLE) / length(notice)) AS best FROM t GROUP BY 1, 2),
v AS (
  SELECT doc_id, string_agg(notice || ':' || i || ':' || k || ':' || e, '|' ORDER BY notice) AS best
  FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, notice ORDER BY e, i, k) AS r FROM t) WHERE r = 1 GROUP BY 1
), g AS (SELECT s.doc_id, s.i - 1 AS i, b.label FROM s JOIN b ON s.k = b.n AND s.x = b.phrase),
h AS (SELECT doc_id, count(*) AS n_base, min(i) AS first_word, max(i) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM g GROUP BY 1),
l AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT doc_id, label FROM f UNION SELECT doc_id, label FROM g) GROUP BY 1),
c AS (SELECT doc_id, max(best) AS best FROM (SELECT doc_id, best FROM f UNION ALL SELECT doc_id, 1.0 FROM g) GROUP BY 1)
SELECT d.doc_id, len(d.w) AS n_words, coalesce(h.n_base, 0) AS n_base, h.first_word, h.last_word,
       coalesce(h.base_labels, '') AS base_labels, coalesce(l.labels, '') AS labels, coalesce(c.best, 0.0) AS score, coalesce(v.best, '') AS best
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN l USING (doc_id) LEFT JOIN c USING (doc_id) LEFT JOIN v USING (doc_id)
""",
}
