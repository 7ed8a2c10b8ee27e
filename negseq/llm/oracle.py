"""DuckDB SQL for the queries that SQL can express over whole tables."""

_WORDS = r"regexp_extract_all(text, '[^\x20\x09-\x0D]+')"

SUBSTRING = rf"""
WITH d AS (SELECT doc_id, coalesce({_WORDS}, []::VARCHAR[]) AS w FROM documents),
p AS (SELECT doc_id, unnest(range(1, len(w) - 18)) AS s, w FROM d WHERE len(w) >= 20),
h AS (SELECT doc_id, s, array_to_string(w[s:s + 19], ' ') AS win FROM p),
r AS (SELECT doc_id, s, row_number() OVER (PARTITION BY win ORDER BY doc_id, s) AS k FROM h),
c AS (SELECT DISTINCT doc_id, unnest(range(s, s + 20)) AS i FROM r WHERE k > 1),
e AS (SELECT doc_id, len(w) AS n, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
k AS (SELECT e.doc_id, count(*) AS kept, string_agg(word, ' ' ORDER BY e.i) AS t FROM e LEFT JOIN c ON e.doc_id = c.doc_id AND e.i = c.i WHERE c.i IS NULL GROUP BY 1)
SELECT d.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(kept, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""

WARC = r"""
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
s AS (SELECT page_id, octet_length(body) AS n, sha1(body) AS hex FROM p),
b AS (SELECT page_id, n, hex, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
  1 + (((strpos('0123456789abcdef', substr(hex, 1 + (i * 5) // 4, 1)) - 1) * 16
      + (CASE WHEN (i * 5) // 4 = 39 THEN 0 ELSE strpos('0123456789abcdef', substr(hex, 2 + (i * 5) // 4, 1)) - 1 END)) >> (3 - (i * 5) % 4)) % 32, 1)), '') AS d FROM s),
f AS (SELECT *, min(page_id) OVER (PARTITION BY hex, n) AS lead FROM b)
SELECT page_id, n::BIGINT AS payload_bytes, d AS payload_digest, CASE WHEN page_id = lead THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = lead THEN NULL ELSE lead END AS refers_to FROM f
"""

MINHASH = r"""
WITH RECURSIVE d AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), []::VARCHAR[]) AS w FROM documents),
s AS (SELECT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END) AS g FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
f AS (SELECT *, count(*) OVER (PARTITION BY g) AS df FROM s),
r AS (SELECT f.*, n.n, row_number() OVER (PARTITION BY doc_id ORDER BY df, g) AS k FROM f JOIN n USING (doc_id)),
q AS (SELECT * FROM r WHERE 100 * (k - 1) <= 15 * n),
c AS (SELECT DISTINCT a.doc_id AS a, b.doc_id AS b FROM q a JOIN q b ON a.g = b.g AND a.doc_id < b.doc_id AND 100 * a.n >= 85 * b.n AND 100 * b.n >= 85 * a.n),
i AS (SELECT c.a, c.b, count(*) AS common FROM c JOIN s x ON x.doc_id = c.a JOIN s y ON y.doc_id = c.b AND y.g = x.g GROUP BY 1, 2),
l AS (SELECT i.a, i.b FROM i JOIN n x ON x.doc_id = i.a JOIN n y ON y.doc_id = i.b WHERE 100 * common >= 85 * (x.n + y.n - common)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
walk AS (SELECT DISTINCT a AS start, a AS here FROM e UNION SELECT walk.start, e.b FROM walk JOIN e ON walk.here = e.a),
m AS (SELECT start, min(here) AS lead FROM walk GROUP BY 1)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(m.lead, d.doc_id) AS component_id, coalesce(m.lead, d.doc_id) = d.doc_id AS kept
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN m ON m.start = d.doc_id
"""

EMBEDDING = """
WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e))) >= 0.93),
walk AS (SELECT DISTINCT a AS start, a AS here FROM l UNION SELECT walk.start, l.b FROM walk JOIN l ON walk.here = l.a),
m AS (SELECT start, min(here) AS lead FROM walk GROUP BY 1),
n AS (SELECT a, count(*) AS n FROM l GROUP BY 1)
SELECT vec_id, coalesce(n.n, 0)::BIGINT AS n_links, coalesce(m.lead, vec_id) AS component_id, coalesce(m.lead, vec_id) = vec_id AS kept
FROM embeddings LEFT JOIN n ON n.a = vec_id LEFT JOIN m ON m.start = vec_id
"""

CHAT = r"""
WITH t AS (SELECT conv_id, turn, coalesce(role, 'user') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-1, 0, 'user', '<|im_end|><|im_start|>assistant ok'), (-1, 1, 'assistant', '<|im_end|><|im_start|>assistant ok')),
f AS (SELECT *, '<|im_start|>' || role || chr(10) || replace(replace(text, '\', '\\'), '<|', '<\|') || '<|im_end|>' || chr(10) AS line FROM t)
SELECT conv_id::BIGINT AS conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  length(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), ''))::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(length(line))::BIGINT AS formatted_chars
FROM f GROUP BY conv_id
"""

SQL = {"op1_substring_dedup": SUBSTRING, "op3_warc": WARC, "op5_minhash_dedup": MINHASH, "op7_embedding_dedup": EMBEDDING, "op10_chat": CHAT}
