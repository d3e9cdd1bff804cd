"""DuckDB SQL for the training-data queries that SQL can express.

The others are held against brute force in tests/llm: DuckDB has no tokenizer (op5, op7), no XXH64 (op10), no Viterbi
(op4), no substring edit distance (op3); op1's and op2's own spans and weights follow from their automata.
"""

_LETTER = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[(v >> {shift} & 31) + 1]"
_FOUR = " || ".join(_LETTER.format(shift=s) for s in (15, 10, 5, 0))

SQL: dict[str, str] = {
    "op6_embeddings": """WITH RECURSIVE v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings),
good AS (SELECT vec_id, e FROM v WHERE vec_id IS NOT NULL AND e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.9),
reach AS (SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b)
SELECT v.vec_id, (SELECT count(*) FROM links l WHERE l.a = v.vec_id) AS n_links, min(r.b) AS component_id, v.vec_id = min(r.b) AS kept FROM v JOIN reach r ON r.a = v.vec_id GROUP BY v.vec_id""",
    "op8_suffix_dedup": """WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents WHERE doc_id IS NOT NULL),
w AS (SELECT doc_id, s, md5(substr(h, 2 * s + 1, 200)) AS k FROM (SELECT doc_id, h, unnest(range(0, length(h) // 2 - 99)) AS s FROM d)),
again AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY k ORDER BY doc_id, s) AS r FROM w) WHERE r > 1),
marked AS (SELECT doc_id, s, (s > coalesce(lag(s) OVER (PARTITION BY doc_id ORDER BY s) + 100, -1))::INT AS fresh FROM again),
runs AS (SELECT doc_id, min(s) AS a, max(s) + 100 AS b FROM (SELECT doc_id, s, sum(fresh) OVER (PARTITION BY doc_id ORDER BY s ROWS UNBOUNDED PRECEDING) AS g FROM marked) GROUP BY doc_id, g),
kept AS (SELECT doc_id, count(*) AS n, sum(b - a) AS gone, list({'a': a, 'b': b} ORDER BY a) AS r FROM runs GROUP BY doc_id)
SELECT d.doc_id, length(h) // 2 AS n_bytes, coalesce(gone, 0)::BIGINT AS n_removed, coalesce(n, 0) AS n_spans,
sha256(unhex(CASE WHEN r IS NULL THEN h ELSE array_to_string(list_transform(range(0, len(r) + 1), lambda i: substr(h, 2 * (CASE WHEN i = 0 THEN 0 ELSE r[i].b END) + 1,
2 * ((CASE WHEN i = len(r) THEN length(h) // 2 ELSE r[i + 1].a END) - (CASE WHEN i = 0 THEN 0 ELSE r[i].b END)))), '') END)) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)""",
    "op9_warc": f"""WITH p AS (SELECT page_id, coalesce(html, '') AS t, max(page_id) OVER (PARTITION BY coalesce(html, '')) AS last FROM pages),
c AS (SELECT page_id, t, last, list_transform(range(0, 8), lambda i: ('0x' || substr(sha1(t), 5 * i + 1, 5))::BIGINT) AS parts FROM p)
SELECT page_id, strlen(t) AS payload_bytes, array_to_string(list_transform(parts, lambda v: {_FOUR}), '') AS payload_digest,
CASE WHEN page_id = last THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> last THEN last END AS refers_to FROM c""",
}
