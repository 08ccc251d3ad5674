"""SQL of the graphs that the oracles start from: each defines e(src, dst) and v(id, label). DuckDB reads it."""

from __future__ import annotations

COPURCHASE = """
lp AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
e AS (SELECT a.l_partkey AS src, b.l_partkey AS dst FROM lp a JOIN lp b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
      GROUP BY 1, 2 HAVING count(*) >= CASE WHEN (SELECT count(*) FROM part) <= 200 THEN 4 ELSE 2 END),
v AS (SELECT p.id, CAST(t.label AS INTEGER) AS label
      FROM (SELECT src AS id FROM e UNION SELECT dst FROM e) p JOIN part ON p.id = p_partkey
      JOIN (SELECT p_type, dense_rank() OVER (ORDER BY p_type) AS label FROM (SELECT DISTINCT p_type FROM part)) t ON t.p_type = part.p_type)
"""

KNN = """
x AS (SELECT vec_id, label, list_transform(embedding, lambda c: CAST(c AS DOUBLE)) AS w FROM embeddings),
u AS (SELECT vec_id, label, list_transform(w, lambda c: c / sqrt(list_sum(list_transform(w, lambda d: d * d)))) AS w FROM x),
near AS (SELECT a.vec_id AS i, b.vec_id AS j, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_dot_product(a.w, b.w) DESC, b.vec_id) AS r
         FROM u a JOIN u b ON a.vec_id <> b.vec_id),
e AS (SELECT DISTINCT least(i, j) AS src, greatest(i, j) AS dst FROM near WHERE r <= 5),
v AS (SELECT vec_id AS id, CAST(label + 1 AS INTEGER) AS label FROM embeddings WHERE vec_id IN (SELECT src FROM e UNION SELECT dst FROM e))
"""

COACTIVE = """
t AS (SELECT user_id, epoch_us(CAST(ts AS TIMESTAMP)) AS m FROM events),
e AS (SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM t a JOIN t b ON a.user_id < b.user_id AND b.m BETWEEN a.m - 10000000 AND a.m + 10000000),
usual AS (SELECT user_id, event_type FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS r
          FROM events GROUP BY 1, 2) WHERE r = 1),
v AS (SELECT user_id AS id, CAST(label AS INTEGER) AS label FROM usual
      JOIN (SELECT event_type, dense_rank() OVER (ORDER BY event_type) AS label FROM (SELECT DISTINCT event_type FROM usual)) USING (event_type)
      WHERE user_id IN (SELECT src FROM e UNION SELECT dst FROM e))
"""

COSUPPLIER = """
ls AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem),
e AS (SELECT a.l_suppkey AS src, b.l_suppkey AS dst FROM ls a JOIN ls b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey
      GROUP BY 1, 2 HAVING count(*) >= CASE WHEN (SELECT count(*) FROM supplier) <= 10 THEN 150 WHEN (SELECT count(*) FROM supplier) <= 100 THEN 24 ELSE 5 END),
v AS (SELECT s_suppkey AS id, CAST(s_nationkey + 1 AS INTEGER) AS label FROM supplier WHERE s_suppkey IN (SELECT src FROM e UNION SELECT dst FROM e))
"""

PARTSUPP = """
e AS (SELECT DISTINCT l_partkey AS src, l_suppkey + 1099511627776 AS dst FROM lineitem),
v AS (SELECT DISTINCT src AS id, 1 AS label FROM e UNION ALL SELECT DISTINCT dst, 2 FROM e)
"""

TURNS = """
t AS (SELECT conv_id * 100000 + turn AS id, conv_id, turn, role FROM conversations),
e AS (SELECT least(id, nxt) AS src, greatest(id, nxt) AS dst FROM (SELECT id, lead(id) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM t) WHERE nxt IS NOT NULL),
v AS (SELECT id, CAST(label AS INTEGER) AS label FROM t JOIN (SELECT role, dense_rank() OVER (ORDER BY role) AS label FROM (SELECT DISTINCT role FROM t)) USING (role)
      WHERE id IN (SELECT src FROM e UNION SELECT dst FROM e))
"""

CUSTOMER_PART = """
e AS (SELECT DISTINCT o_custkey AS src, l_partkey + 1099511627776 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 45),
v AS (SELECT id, CAST(coalesce(label, 1) AS INTEGER) AS label FROM (SELECT src AS id FROM e UNION SELECT dst FROM e)
      LEFT JOIN (SELECT c_custkey, 1 + dense_rank() OVER (ORDER BY c_mktsegment) AS label FROM customer) ON id = c_custkey)
"""

#: Both directions, and connected 3- and 4-subsets, over e.
SYM = "s AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e)"
SETS3 = "c3 AS (SELECT DISTINCT list_sort([x.a, x.b, y.b]) AS w FROM s x JOIN s y ON x.a = y.a AND x.b < y.b)"
SETS4 = "c4 AS (SELECT DISTINCT list_sort(list_append(w, s.b)) AS w FROM c3 JOIN s ON list_contains(w, s.a) AND NOT list_contains(w, s.b))"
#: Edges inside each subset of 4, and its sorted degrees, which tell the six shapes apart.
SHAPES4 = """
i4 AS (SELECT w, src, dst FROM c4 JOIN e ON list_contains(w, src) AND list_contains(w, dst)),
d4 AS (SELECT w, x, count(*) AS d FROM (SELECT w, src AS x FROM i4 UNION ALL SELECT w, dst FROM i4) GROUP BY 1, 2),
k4 AS (SELECT w, string_agg(CAST(d AS VARCHAR), '' ORDER BY d) AS ds FROM d4 GROUP BY 1),
m4 AS (SELECT CASE ds WHEN '1122' THEN 'path' WHEN '1113' THEN 'star' WHEN '2222' THEN 'cycle' WHEN '1223' THEN 'tailed_triangle' WHEN '2233' THEN 'diamond' ELSE 'clique' END AS motif,
       count(*) AS frequency FROM k4 GROUP BY 1)
"""
SETS5 = "c5 AS (SELECT DISTINCT list_sort(list_append(w, s.b)) AS w FROM (SELECT w, unnest(w) AS x FROM c4) JOIN s ON s.a = x WHERE NOT list_contains(w, s.b))"
#: Each connected set of three with its sorted degrees.
LABELLED3 = "k3s AS (SELECT w, CASE WHEN EXISTS (SELECT 1 FROM s WHERE a = w[1] AND b = w[2]) AND EXISTS (SELECT 1 FROM s WHERE a = w[2] AND b = w[3]) AND EXISTS (SELECT 1 FROM s WHERE a = w[1] AND b = w[3]) THEN '222' ELSE '112' END AS ds FROM c3)"


def shapes5() -> str:
    """m5(motif, frequency): sorted degrees and the number of triangles tell the 21 shapes of five vertices apart."""
    from levelmine.pattern.encode import matrix
    from levelmine.pattern.names import names

    cases = []
    for code, name in names().items():
        labels, bits = code.split("|")
        if labels.count(".") != 4:
            continue
        m = matrix(5, int(bits, 16))
        triangles = sum(m[i][j] and m[j][k] and m[i][k] for i in range(5) for j in range(i) for k in range(j))
        cases.append(f"WHEN ds = '{''.join(map(str, sorted(map(sum, m))))}' AND t = {triangles} THEN '{name}'")
    return f"""
i5 AS (SELECT w, src, dst FROM (SELECT w, unnest(w) AS x FROM c5) JOIN e ON src = x WHERE list_contains(w, dst)),
d5 AS (SELECT w, x, count(*) AS d FROM (SELECT w, src AS x FROM i5 UNION ALL SELECT w, dst FROM i5) GROUP BY 1, 2),
r5 AS (SELECT x.w, count(*) AS t FROM i5 x JOIN i5 y ON x.w = y.w AND x.dst = y.src JOIN i5 z ON z.w = x.w AND z.src = x.src AND z.dst = y.dst GROUP BY 1),
k5 AS (SELECT w, string_agg(CAST(d AS VARCHAR), '' ORDER BY d) AS ds FROM d5 GROUP BY 1),
m5 AS (SELECT CASE {' '.join(cases)} END AS motif, count(*) AS frequency FROM (SELECT ds, coalesce(t, 0) AS t FROM k5 LEFT JOIN r5 ON k5.w = r5.w) GROUP BY 1)
"""


SHAPES3 = """
t3 AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst),
m3 AS (SELECT motif, frequency FROM (SELECT 'triangle' AS motif, count(*) AS frequency FROM t3
       UNION ALL SELECT 'chain', (SELECT count(*) FROM c3) - (SELECT count(*) FROM t3)) WHERE frequency > 0)
"""


def sql(graph: str, *ctes: str, select: str) -> str:
    return "WITH " + ",\n".join(c.strip() for c in (graph, *ctes)) + "\n" + select
