"""SQL counterparts of the operators that SQL can express."""

from __future__ import annotations

_WORDS = r"""w AS (
  SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i
  FROM (SELECT doc_id, regexp_extract_all({text}, '[^\x20\x09-\x0D]+') AS ws FROM documents))"""

_GRAMS = """g AS (
  SELECT doc_id, i,
         string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND {last} FOLLOWING) AS g,
         count(*) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND {last} FOLLOWING) AS k
  FROM w)"""

SUBSTRING = f"""
WITH {_WORDS.replace('{text}', "coalesce(text, '')")},
{_GRAMS.replace('{last}', '12')},
f AS (SELECT g, min(doc_id) AS lo FROM g WHERE k = 13 GROUP BY g),
cov AS (SELECT DISTINCT doc_id, i + j AS i FROM g JOIN f USING (g), (SELECT unnest(range(0, 13)) AS j) WHERE k = 13 AND lo < doc_id),
m AS (SELECT w.doc_id, w.word, w.i, cov.i IS NOT NULL AS gone FROM w LEFT JOIN cov USING (doc_id, i))
SELECT d.doc_id, count(m.i)::BIGINT AS n_words, coalesce(sum(gone::INT), 0)::BIGINT AS n_removed,
       sha256(coalesce(string_agg(word, ' ' ORDER BY m.i) FILTER (NOT gone), '')) AS kept_sha256
FROM documents d LEFT JOIN m USING (doc_id) GROUP BY d.doc_id
"""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

JACCARD = f"""
WITH RECURSIVE {_WORDS.replace('{text}', f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')")},
{_GRAMS.replace('{last}', '4')},
s AS (SELECT DISTINCT doc_id, g FROM g WHERE k = 5
      UNION ALL
      SELECT doc_id, string_agg(word, ' ' ORDER BY i) FROM w GROUP BY doc_id HAVING count(*) < 5),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * o >= 75 * (nx.n + ny.n - o)),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.y FROM r JOIN e ON r.b = e.x)
SELECT r.a AS doc_id, coalesce(max(n.n), 0)::BIGINT AS n_shingles, min(r.b) AS component_id FROM r LEFT JOIN n ON n.doc_id = r.a GROUP BY r.a
"""

VECTORS = """
WITH RECURSIVE v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings),
e AS (SELECT a.vec_id AS p, b.vec_id AS q FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.9),
r AS (SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, e.q FROM r JOIN e ON r.b = e.p),
c AS (SELECT a AS vec_id, min(b) AS component_id FROM r GROUP BY a),
n AS (SELECT p AS vec_id, count(*) AS n FROM e GROUP BY p)
SELECT c.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, component_id, c.vec_id = component_id AS kept FROM c LEFT JOIN n USING (vec_id)
"""
