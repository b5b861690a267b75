"""The queries of these operators over the given tables, and DuckDB's SQL where it can say the same."""

from __future__ import annotations

from .chat_format import op6_chat_format
from .decontaminate import OP7_SQL, op7_decontaminate
from .language_id import op5_language_id
from .media_columns import op2_media_columns
from .ngram_join import op8_ngram_jaccard_join
from .packing import op10_best_fit_packing
from .quality import op3_quality
from .suffix_dedup import op9_suffix_dedup
from .token_counts import op1_token_counts
from .toxicity import op4_toxicity

QUERIES = {f.__name__: f for f in (op1_token_counts, op2_media_columns, op3_quality, op4_toxicity, op5_language_id, op6_chat_format, op7_decontaminate, op8_ngram_jaccard_join, op9_suffix_dedup, op10_best_fit_packing)}

#: Sets of word runs, all pairs that share one, and what links reach.
OP8_SQL = """
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[p : p + least(4, len(w)) - 1], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 3) + 1)) AS p FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n u ON u.doc_id = a JOIN n v ON v.doc_id = b WHERE 100 * c >= 85 * (u.n + v.n - c)),
r AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.b) AS component_id FROM d LEFT JOIN n USING (doc_id) JOIN r ON r.a = d.doc_id GROUP BY d.doc_id, n.n
"""

#: All windows of 400 bytes (800 hex digits), counted.
OP9_SQL = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
w AS (SELECT doc_id, p, md5(substr(x, 2 * p + 1, 800)) AS h FROM (SELECT doc_id, x, unnest(range(0, len(x) // 2 - 399)) AS p FROM d WHERE len(x) >= 800)),
s AS (SELECT doc_id, p FROM w WHERE h IN (SELECT h FROM w GROUP BY h HAVING count(*) > 1)),
i AS (SELECT doc_id, p, sum(fresh) OVER (PARTITION BY doc_id ORDER BY p) AS g FROM (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 400 THEN 0 ELSE 1 END AS fresh FROM s)),
g AS (SELECT doc_id, min(p) AS a, max(p) + 400 AS b FROM i GROUP BY doc_id, g),
k AS (SELECT doc_id, b AS a, lead(a) OVER (PARTITION BY doc_id ORDER BY a, b) AS b FROM (SELECT doc_id, a, b FROM g UNION ALL SELECT doc_id, 0, 0 FROM d)),
t AS (SELECT doc_id, string_agg(substr(x, 2 * a + 1, 2 * (coalesce(b, len(x) // 2) - a)), '' ORDER BY a) AS x FROM k JOIN d USING (doc_id) GROUP BY doc_id),
m AS (SELECT doc_id, sum(b - a) AS removed, count(*) AS spans FROM g GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.x) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(spans, 0) AS BIGINT) AS n_spans, sha256(unhex(t.x)) AS kept_sha256
FROM d JOIN t USING (doc_id) LEFT JOIN m USING (doc_id)
"""

SQL = {"op7_decontaminate": OP7_SQL, "op8_ngram_jaccard_join": OP8_SQL, "op9_suffix_dedup": OP9_SQL}
