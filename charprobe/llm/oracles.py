"""DuckDB SQL of the queries that SQL can express.

Tokenizing (4, 8), learning (3, 7, 9, pipeline) and the calibration of 6 have none; tests hold them against brute force.
"""

from __future__ import annotations

from .queries import SHARDS, URL_RULES

WORDS = r"'[^\x20\x09-\x0D]+'"
LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

#: A url's host and path, the best rule that fits, and its verdict.
_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in URL_RULES)
URL = rf"""WITH r(v, h, p) AS (VALUES {_RULES}),
u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest, row_number() OVER () AS n FROM pages),
s AS (SELECT n, page_id, translate(regexp_extract(rest, '^[^/?#]*', 0, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's') AS path FROM u),
f AS (SELECT n, arg_max(h || p, (length(h || p), length(h), (v = 'block')::INT)) AS rule, arg_max(v, (length(h || p), length(h), (v = 'block')::INT)) AS v FROM s, r WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY n)
SELECT page_id, coalesce(host, '') AS host, coalesce(path, '') AS path, rule, coalesce(v, 'allow') AS verdict FROM s LEFT JOIN f USING (n)"""

#: All pairs that share a shingle, counted; then labels spread to a fixed point.
JACCARD = rf"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({LOWER}, {WORDS}) AS w FROM documents),
g AS (SELECT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct([w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] for i in range(1, len(w) - 1)]) END) AS s FROM w),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS MATERIALIZED (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 90 * (x.n + y.n - c)),
r(id, seen) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.seen)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, (SELECT min(seen) FROM r WHERE r.id = d.doc_id) AS component_id FROM documents d LEFT JOIN n USING (doc_id)"""

SEARCH = rf"""WITH w AS (SELECT doc_id, unnest(regexp_extract_all({LOWER}, {WORDS})) AS t FROM documents),
tf AS MATERIALIZED (SELECT doc_id, t, count(*) AS c FROM w GROUP BY ALL),
dl AS (SELECT doc_id, sum(c) AS n FROM tf GROUP BY doc_id),
corpus AS (SELECT (SELECT count(*) FROM documents) AS n, (SELECT sum(n) FROM dl) / (SELECT count(*) FROM documents) AS mean),
idf AS (SELECT t, ln(1 + ((SELECT n FROM corpus) - count(*) + 0.5) / (count(*) + 0.5)) AS idf FROM tf GROUP BY t),
part AS (SELECT doc_id, t, idf * c * 2.2::DOUBLE / (c + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * dl.n / (SELECT mean FROM corpus))) AS v FROM tf JOIN idf USING (t) JOIN dl USING (doc_id)),
hit AS (SELECT q.doc_id AS query_id, p.doc_id, round(sum(v), 6) AS score FROM tf q JOIN part p USING (t) WHERE q.doc_id % 20 = 0 GROUP BY ALL),
best AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank FROM hit)
SELECT query_id, rank::INT AS rank, doc_id, score FROM best WHERE rank <= 10"""

#: The jump goes by unsigned 128-bit products modulo 2**64; crc32 by a table made from its polynomial.
_M = "18446744073709551616::UHUGEINT"
SHARD = rf"""WITH RECURSIVE t0 AS (SELECT i::UINTEGER AS i, i::UINTEGER AS c FROM range(256) x(i)),
{", ".join(f"t{k + 1} AS (SELECT i, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384::UINTEGER) ELSE c >> 1 END AS c FROM t{k})" for k in range(8))},
tab AS MATERIALIZED (SELECT list(c ORDER BY i) AS t FROM t8),
base AS MATERIALIZED (SELECT row_number() OVER () AS n, doc_id, coalesce(text, '') AS text FROM documents),
bytes AS (SELECT n, list_transform(regexp_extract_all(hex(encode(text)), '..'), lambda h: ('0x' || h)::UINTEGER) AS b FROM base),
crc AS MATERIALIZED (SELECT n, CASE WHEN len(b) = 0 THEN 0::BIGINT ELSE xor(list_reduce(list_prepend(4294967295::UINTEGER, b), lambda a, x: xor(a >> 8, t[(xor(a, x) & 255) + 1])), 4294967295::UINTEGER)::BIGINT END AS crc FROM bytes, tab),
m0 AS (SELECT n, ((CASE WHEN coalesce(doc_id, 0) < 0 THEN 18446744073709551616::HUGEINT + doc_id ELSE coalesce(doc_id, 0)::HUGEINT END)::UHUGEINT + 11400714819323198485::UHUGEINT) % {_M} AS x FROM base),
m1 AS (SELECT n, (xor(x, x >> 30) * 13787848793156543929::UHUGEINT) % {_M} AS x FROM m0),
m2 AS (SELECT n, (xor(x, x >> 27) * 10723151780598845931::UHUGEINT) % {_M} AS x FROM m1),
k AS MATERIALIZED (SELECT n, xor(x, x >> 31) AS x FROM m2),
step(n, shards, x, b, j) AS (SELECT n, s, x, -1::BIGINT, 0::BIGINT FROM k, (VALUES ({SHARDS}), ({SHARDS + 1})) v(s)
UNION ALL SELECT n, shards, y, j, floor((j + 1) * (2147483648.0::DOUBLE / ((y >> 33)::DOUBLE + 1)))::BIGINT FROM (SELECT *, (x * 2862933555777941757::UHUGEINT + 1::UHUGEINT) % {_M} AS y FROM step WHERE j < shards)),
placed AS (SELECT n, shards, max(b)::INT AS shard FROM step WHERE j >= shards GROUP BY ALL),
r AS (SELECT doc_id, (octet_length(encode(text)) + 16)::BIGINT AS size, crc AS text_crc32, a.shard, g.shard AS grown_shard, (x >> 54)::INT AS chunk FROM base JOIN crc USING (n) JOIN k USING (n) JOIN placed a ON a.n = base.n AND a.shards = {SHARDS} JOIN placed g ON g.n = base.n AND g.shards = {SHARDS + 1})
SELECT doc_id, size, text_crc32, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY chunk, doc_id, text_crc32, size) - 1 AS slot, grown_shard FROM r"""

SQL: dict[str, str] = {"op1_jump_shards": SHARD, "op2_ngram_jaccard": JACCARD, "op5_url_rules": URL, "op10_bm25_search": SEARCH}
