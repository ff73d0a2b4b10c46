"""DuckDB SQL for the registered queries, assembled from common table expressions."""

from __future__ import annotations

GRAPHS = {
    "cp": """gl AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem),
edges AS (SELECT DISTINCT a.p AS u, b.p AS v FROM gl a JOIN gl b ON a.o = b.o AND a.p < b.p)""",
    "cpy": """gl AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem JOIN orders ON o_orderkey = l_orderkey
  WHERE o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1997-01-01'),
edges AS (SELECT DISTINCT a.p AS u, b.p AS v FROM gl a JOIN gl b ON a.o = b.o AND a.p < b.p)""",
    "tr": """tl AS (SELECT 3 * o_custkey AS c, 3 * l_partkey + 1 AS p, 3 * l_suppkey + 2 AS s FROM lineitem JOIN orders ON o_orderkey = l_orderkey),
edges AS (SELECT DISTINCT least(x, y) AS u, greatest(x, y) AS v FROM (SELECT c AS x, p AS y FROM tl UNION ALL SELECT p, s FROM tl UNION ALL SELECT c, s FROM tl))""",
    "ev": """es AS (SELECT DISTINCT floor(epoch(ts) / 600)::BIGINT AS slot, user_id AS i FROM events),
edges AS (SELECT DISTINCT a.i AS u, b.i AS v FROM es a JOIN es b ON a.slot = b.slot AND a.i < b.i)""",
    "em": """ev AS (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings),
edges AS (SELECT a.id AS u, b.id AS v FROM ev a JOIN ev b ON a.id < b.id WHERE list_cosine_similarity(a.x, b.x) > 0.2)""",
    "pg": """pl AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS host, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS link FROM pages),
pk AS (SELECT 3 * page_id AS p, 3 * ('0x' || substr(md5(host), 1, 12))::BIGINT + 1 AS h, 3 * ('0x' || substr(md5(link), 1, 12))::BIGINT + 2 AS l FROM pl),
edges AS (SELECT DISTINCT least(x, y) AS u, greatest(x, y) AS v FROM (SELECT p AS x, h AS y FROM pk UNION ALL SELECT h, l FROM pk UNION ALL SELECT p, l FROM pk))""",
    "cv": """cw AS (SELECT DISTINCT conv_id AS c, unnest(regexp_split_to_array(lower(text), '[\\x20\\x09-\\x0D]+')) AS word FROM conversations),
cr AS (SELECT word FROM cw WHERE word <> '' GROUP BY word HAVING count(*) BETWEEN 2 AND 4),
edges AS (SELECT DISTINCT a.c AS u, b.c AS v FROM cw a JOIN cr USING (word) JOIN cw b ON b.word = a.word AND a.c < b.c)""",
    "ge": """gl AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS p FROM lineitem),
edges AS (SELECT DISTINCT a.p AS u, b.p AS v FROM gl a JOIN gl b ON a.o = b.o AND a.p < b.p)""",
}

LAYER = """,
nodes AS (SELECT u AS id FROM edges UNION SELECT v FROM edges),
adj AS (SELECT u AS src, v AS dst FROM edges UNION ALL SELECT v, u FROM edges),
deg AS (SELECT src AS id, count(*) AS d FROM adj GROUP BY src),
head AS (SELECT src AS id, sum(d - 1)::BIGINT AS wh FROM adj JOIN deg ON id = dst GROUP BY src),
tri AS (SELECT a.u AS a, a.v AS b, b.v AS c FROM edges a JOIN edges b ON a.v = b.u JOIN edges x ON x.u = a.u AND x.v = b.v),
nt AS (SELECT id, count(*) AS t FROM (SELECT a AS id FROM tri UNION ALL SELECT b FROM tri UNION ALL SELECT c FROM tri) GROUP BY id),
prof AS (SELECT deg.id, d, coalesce(t, 0) AS t, d * (d - 1) // 2 AS wc, wh,
  CASE WHEN d > 1 THEN 2.0::DOUBLE * coalesce(t, 0) / (d * (d - 1)) ELSE 0 END AS alpha, CASE WHEN wh > 0 THEN 2.0::DOUBLE * coalesce(t, 0) / wh ELSE 0 END AS phi
  FROM deg JOIN head USING (id) LEFT JOIN nt USING (id))"""


def numbered(labels: str) -> str:
    """Buckets by order of label from (id, label)."""
    return f""",
lab AS ({labels}),
buckets AS (SELECT lab.id, r.bucket, lab.label FROM lab JOIN (SELECT label, (row_number() OVER (ORDER BY label) - 1)::INTEGER AS bucket FROM (SELECT DISTINCT label FROM lab)) r USING (label)),
sizes AS (SELECT bucket, count(*) AS size FROM buckets GROUP BY bucket)"""


LABELS = {
    "brand": "SELECT nodes.id, coalesce(p_brand, 'none') AS label FROM nodes LEFT JOIN part ON p_partkey = nodes.id",
    "type": "SELECT nodes.id, coalesce(p_type, 'none') AS label FROM nodes LEFT JOIN part ON p_partkey = nodes.id",
    "segment": """SELECT nodes.id, coalesce(s.label, 'none') AS label FROM nodes LEFT JOIN (SELECT id, label FROM (
  SELECT l_partkey AS id, c_mktsegment AS label, row_number() OVER (PARTITION BY l_partkey ORDER BY count(*) DESC, c_mktsegment) AS r
  FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey WHERE c_mktsegment IS NOT NULL GROUP BY l_partkey, c_mktsegment) WHERE r = 1) s ON s.id = nodes.id""",
    "deg": """SELECT deg.id, lpad(g.g::VARCHAR, 6, '0') AS label FROM deg JOIN (SELECT d, floor(25 * coalesce(sum(n) OVER (ORDER BY d ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)
  / (sum(n) OVER ()))::BIGINT AS g FROM (SELECT d, count(*) AS n FROM deg GROUP BY d)) g USING (d)""",
    "log": "SELECT id, lpad((CASE WHEN d <= 1 THEN 1 ELSE floor(ln(1 + (d - 2) / ln(2)))::INTEGER + 2 END)::VARCHAR, 4, '0') AS label FROM deg",
    "rnd": "SELECT id, lpad((('0x' || substr(md5('0:' || id), 1, 8))::BIGINT % 30)::VARCHAR, 6, '0') AS label FROM nodes",
    "one": "SELECT id, 'all' AS label FROM nodes",
}

W = {"clustering": "SELECT id, (d * (d - 1) // 2)::DOUBLE AS w FROM deg", "closure": "SELECT id, wh / 2.0::DOUBLE AS w FROM head"}
NUMBER = """,
numbered AS (SELECT row_number() OVER (ORDER BY (u * 31 + v) % 4096, u, v) - 1 AS eid, u, v FROM edges), total AS (SELECT count(*) AS m FROM edges)"""


def hashed(seed: int, stream: str, *keys: str) -> str:
    text = " || ':' || ".join([f"'{seed}:{stream}'", *keys])
    return f"(('0x' || substr(md5({text}), 1, 13))::BIGINT / 4503599627370496::DOUBLE)"


def bag(s: str, seed: int, stream: str = "main") -> str:
    return f""",
bag AS (SELECT ix, u, v FROM (SELECT i AS ix, least(floor({hashed(seed, stream, "i")} * m)::BIGINT, m - 1) AS eid FROM total, range(0, {s}) r(i)) JOIN numbered USING (eid))"""


#: Common neighbours of distinct edges, what each edge gives at a split weight, and values by bucket.
def values(edge_table: str, q: str, coefficient: str, m: str = "(SELECT m FROM total)") -> str:
    return f""",
wt AS ({W[coefficient]}),
et AS (SELECT e.u, e.v, a.dst AS w FROM (SELECT DISTINCT u, v FROM {edge_table}) e JOIN adj a ON a.src = e.u JOIN adj b ON b.src = e.v AND b.dst = a.dst),
shares AS (SELECT u, v, w AS node, (1 - 2 * {q})::DOUBLE AS a FROM et UNION ALL SELECT u, v, u, count(*) * {q}::DOUBLE FROM et GROUP BY u, v UNION ALL SELECT u, v, v, count(*) * {q}::DOUBLE FROM et GROUP BY u, v),
vals AS (SELECT u, v, bucket, sum(a / (wt.w * size)) * {m} AS x FROM shares JOIN wt ON wt.id = node AND wt.w > 0 JOIN buckets b ON b.id = node JOIN sizes USING (bucket) GROUP BY u, v, bucket)"""


def graph(code: str) -> str:
    return "WITH " + GRAPHS[code] + LAYER


def with_buckets(code: str, kind: str) -> str:
    return graph(code) + numbered(LABELS[kind])


SIDE = """,
iw AS (SELECT b.id, bucket, 1 / w AS iw FROM wt JOIN buckets b USING (id) WHERE w > 0),
ends AS (SELECT u, v, CASE WHEN a.d <= b.d THEN u ELSE v END AS z, CASE WHEN a.d <= b.d THEN v ELSE u END AS o, least(a.d, b.d) - 1 AS t FROM edges JOIN deg a ON a.id = u JOIN deg b ON b.id = v),
around AS (SELECT src AS z, bucket, sum(iw) AS s FROM adj JOIN iw ON iw.id = dst GROUP BY src, bucket),
rb AS (SELECT u, v, bucket, sum(x) AS x FROM (
  SELECT u, v, bucket, iw * t * 0.2::DOUBLE AS x FROM ends JOIN iw ON iw.id = u WHERE t > 0 UNION ALL SELECT u, v, bucket, iw * t * 0.2::DOUBLE FROM ends JOIN iw ON iw.id = v WHERE t > 0
  UNION ALL SELECT u, v, bucket, greatest(sum(s), 0) * 0.6::DOUBLE FROM (SELECT u, v, bucket, s FROM ends JOIN around USING (z) WHERE t > 0
    UNION ALL SELECT u, v, bucket, -iw FROM ends JOIN iw ON iw.id = o WHERE t > 0) GROUP BY u, v, bucket) GROUP BY u, v, bucket)"""

#: As SIDE, with the smaller of both ends' sums.
TIGHT = """,
iw AS (SELECT b.id, bucket, 1 / w AS iw FROM wt JOIN buckets b USING (id) WHERE w > 0),
ends AS (SELECT u, v, least(a.d, b.d) - 1 AS t FROM edges JOIN deg a ON a.id = u JOIN deg b ON b.id = v WHERE least(a.d, b.d) > 1),
around AS (SELECT src AS z, bucket, sum(iw) AS s FROM adj JOIN iw ON iw.id = dst GROUP BY src, bucket),
su AS (SELECT u, v, a.bucket, greatest(s - coalesce(iw, 0), 0) AS s FROM ends JOIN around a ON z = u LEFT JOIN iw ON iw.id = v AND iw.bucket = a.bucket),
sv AS (SELECT u, v, a.bucket, greatest(s - coalesce(iw, 0), 0) AS s FROM ends JOIN around a ON z = v LEFT JOIN iw ON iw.id = u AND iw.bucket = a.bucket),
rb AS (SELECT u, v, bucket, sum(x) AS x FROM (
  SELECT u, v, bucket, iw * t * 0.2::DOUBLE AS x FROM ends JOIN iw ON iw.id = u UNION ALL SELECT u, v, bucket, iw * t * 0.2::DOUBLE FROM ends JOIN iw ON iw.id = v
  UNION ALL SELECT su.u, su.v, su.bucket, least(su.s, sv.s) * 0.6::DOUBLE FROM su JOIN sv USING (u, v, bucket)) GROUP BY u, v, bucket)"""
