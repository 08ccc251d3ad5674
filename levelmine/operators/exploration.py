"""Queries of graph preparation and exploration."""

from __future__ import annotations

from pyspark.sql import functions as F

from levelmine.explore import edge, loop, vertex
from levelmine.explore.canonical import is_canonical
from levelmine.operators.registry import query
from levelmine.pattern.exact import isomorphic
from levelmine.session import read_table
from levelmine.sources import ctes
from levelmine.sources.ctes import sql
from levelmine.sources.graphs import load, paired, part_copurchase, supplier_coorder, vector_knn

COP = ctes.COPURCHASE


def _text(path: str = "path", name: str = "verts", ordered: bool = True):
    col = F.array_sort(F.col(path)) if ordered else F.col(path)
    return F.array_join(F.transform(col, lambda x: x.cast("string")), "-").alias(name)


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM e"))
def graph_normalise(spark, sf_dir):
    """Loops, directions and duplicates go."""
    from levelmine.graph.model import PropertyGraph

    pairs = paired(read_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", 4 if read_table(spark, sf_dir, "part").count() <= 200 else 2)
    doubled = pairs.select("src", "dst").unionAll(pairs.select("dst", "src")).unionAll(pairs.select("src", "src"))
    return PropertyGraph.from_pairs(doubled.toDF("src", "dst")).edges.select("src", "dst")


@query(sql(COP, ctes.SYM, select="SELECT CAST(a AS BIGINT) AS id, CAST(0 AS INTEGER) AS chunk, string_agg(CAST(b AS VARCHAR), '-' ORDER BY b) AS nbrs, count(*) AS deg FROM s GROUP BY a"))
def adjacency_lists(spark, sf_dir):
    return load(part_copurchase, spark, sf_dir).adjacency().select("id", "chunk", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), "-").alias("nbrs"), "deg")


@query(sql(COP, ctes.SYM, select="SELECT count(DISTINCT a) AS n_vertices, (SELECT count(*) FROM e) AS n_edges, (SELECT count(DISTINCT label) FROM v) AS n_labels, round(count(*) / count(DISTINCT a), 6) AS avg_degree, (SELECT max(d) FROM (SELECT count(*) AS d FROM s GROUP BY a)) AS max_degree FROM s"))
def degree_stats(spark, sf_dir):
    return load(part_copurchase, spark, sf_dir).stats()


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM e WHERE src IN (SELECT id FROM v WHERE label <= 3) AND dst IN (SELECT id FROM v WHERE label <= 3)"))
def induced_subgraph(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    return g.induced(g.vertices.filter("label <= 3")).edges.select("src", "dst")


def _same_by_order() -> str:
    """SQL: some order of three vertices takes one form to the other."""
    from itertools import permutations

    bit = {frozenset((0, 1)): 0, frozenset((0, 2)): 1, frozenset((1, 2)): 2}
    ways = []
    for p in permutations(range(3)):
        labels = " AND ".join(f"x.l[{i + 1}] = y.l[{p[i] + 1}]" for i in range(3))
        edges = " AND ".join(f"(x.bits >> {b}) & 1 = (y.bits >> {bit[frozenset(p[i] for i in pair)]}) & 1" for pair, b in bit.items())
        ways.append(f"({labels} AND {edges})")
    return " OR ".join(ways)


_FORMS3 = """
f AS (SELECT DISTINCT [a.label, b.label, c.label] AS l, 1 + CASE WHEN pr.a IS NULL THEN 0 ELSE 2 END + CASE WHEN qr.a IS NULL THEN 0 ELSE 4 END AS bits
      FROM k3 JOIN v a ON a.id = p JOIN v b ON b.id = q JOIN v c ON c.id = r LEFT JOIN s pr ON pr.a = p AND pr.b = r LEFT JOIN s qr ON qr.a = q AND qr.b = r)
"""
_PATHS3 = """
p3 AS (SELECT DISTINCT x.a AS p, x.b AS q, y.b AS r FROM s x JOIN s y ON (y.a = x.a OR y.a = x.b) WHERE y.b <> x.a AND y.b <> x.b),
k3 AS (SELECT p, q, r FROM p3 WHERE p < q AND p < r AND NOT (r < q AND EXISTS (SELECT 1 FROM s WHERE s.a = p AND s.b = r)))
"""


@query(sql(COP, ctes.SYM, _PATHS3, _FORMS3, select=f"SELECT array_to_string(x.l, '-') AS labels_a, CAST(x.bits AS BIGINT) AS ba, array_to_string(y.l, '-') AS labels_b, CAST(y.bits AS BIGINT) AS bb, ({_same_by_order()}) AS isomorphic FROM f x JOIN f y ON list_sort(x.l) = list_sort(y.l) AND bit_count(x.bits) = bit_count(y.bits) AND (x.l < y.l OR (x.l = y.l AND x.bits < y.bits))"))
def isomorphic_pairs(spark, sf_dir):
    """Which raw forms of three vertices are one pattern: a bijection that keeps labels and edges exists."""
    raw = loop.embeddings(load(part_copurchase, spark, sf_dir), 3).select("labels", "bits").distinct()
    same = F.udf(lambda a, m, b, n: isomorphic((tuple(a), m), (tuple(b), n)), "boolean")
    key = F.struct(F.array_sort("labels"), F.bit_count("bits"))
    a = raw.select(F.col("labels").alias("la"), F.col("bits").alias("ba"), key.alias("k"))
    b = raw.select(F.col("labels").alias("lb"), F.col("bits").alias("bb"), key.alias("k"))
    both = a.join(b, "k").filter(F.struct("la", "ba") < F.struct("lb", "bb"))
    return both.select(_text("la", "labels_a", False), "ba", _text("lb", "labels_b", False), "bb", same("la", "ba", "lb", "bb").alias("isomorphic"))


@query(sql(COP, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts, (SELECT count(*) FROM e WHERE list_contains(w, src) AND list_contains(w, dst)) AS n_edges FROM c3"))
def automorphic_dedup(spark, sf_dir):
    """All orders of a connected triple are one subgraph."""
    g = load(part_copurchase, spark, sf_dir)
    s = g.sym.select("u", "v")
    grown = s.toDF("a", "b").select("a", "b", F.explode(F.array("a", "b")).alias("x")).join(s.toDF("x", "c"), "x")
    triples = grown.filter("c <> a and c <> b").select(F.array_sort(F.array("a", "b", "c")).alias("path")).dropDuplicates(["path"])
    at = triples.select("path", F.explode("path").alias("x")).join(g.edges.select(F.col("src").alias("x"), "dst"), "x").filter(F.array_contains("path", F.col("dst")))
    return at.groupBy("path").agg(F.count("*").alias("n_edges")).select(_text(), "n_edges")


@query(sql(COP, ctes.SYM, _PATHS3, select="SELECT p || '-' || q || '-' || r AS path FROM k3"))
def canonical_check(spark, sf_dir):
    """Of all orders in which triples can be grown, the canonical ones."""
    s = load(part_copurchase, spark, sf_dir).sym.select("u", "v")
    rows = s.toDF("p", "q").select("p", "q", F.explode(F.array("p", "q")).alias("x")).join(s.toDF("x", "r"), "x").filter("r <> p and r <> q")
    mask = F.bit_or(F.when(F.col("x") == F.col("p"), 1).otherwise(2)).cast("long")
    rows = rows.groupBy("p", "q", "r").agg(mask.alias("m"))
    path, masks = F.array("p", "q", "r"), F.array(F.lit(0).cast("long"), F.lit(1).cast("long"), F.col("m"))
    return rows.select(path.alias("path"), masks.alias("masks")).filter(is_canonical(F.col("path"), F.col("masks"))).select(_text(name="path", ordered=False))


@query(sql(COP, select="SELECT CAST(id AS BIGINT) AS id, label FROM v"))
def init_vertices(spark, sf_dir):
    level = vertex.init(load(part_copurchase, spark, sf_dir), 1)
    return level.df.select(F.col("path")[0].alias("id"), F.col("labels")[0].alias("label"))


@query(sql(COP, select="SELECT src || '-' || dst AS path FROM e"))
def init_edges(spark, sf_dir):
    return vertex.init(load(part_copurchase, spark, sf_dir), 2).df.select(_text(name="path", ordered=False))


@query(sql(COP, select="SELECT src || '-' || dst AS verts, CAST(1 AS BIGINT) AS n_edges FROM e"))
def init_edge_induced(spark, sf_dir):
    return edge.init(load(part_copurchase, spark, sf_dir)).df.select(_text("verts"), F.size("eids").cast("long").alias("n_edges"))


_SETS3 = sql(COP, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3")


@query(_SETS3)
def vertex_embeddings_3(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 3).select(_text())


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, select="SELECT array_to_string(w, '-') AS verts FROM c4"))
def vertex_embeddings_4(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 4).select(_text())


@query(_SETS3)
def vertex_embeddings_rejoin(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 3, strategy="rejoin").select(_text())


_WEDGES = """
n AS (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS eid, src, dst FROM e),
h AS (SELECT eid, src AS x FROM n UNION ALL SELECT eid, dst FROM n),
w2 AS (SELECT DISTINCT p.eid AS a, q.eid AS b FROM h p JOIN h q ON p.x = q.x AND p.eid < q.eid)
"""
_W3 = """
g2 AS (SELECT a, b, x FROM w2 JOIN h ON h.eid = a UNION SELECT a, b, x FROM w2 JOIN h ON h.eid = b),
w3 AS (SELECT DISTINCT list_sort([g2.a, g2.b, h.eid]) AS w FROM g2 JOIN h ON g2.x = h.x WHERE h.eid NOT IN (g2.a, g2.b))
"""


@query(sql(COP, _WEDGES, select="SELECT a || '-' || b AS edges FROM w2"))
def edge_embeddings_2(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 2, mode="edge").select(_text("eids", "edges"))


@query(sql(COP, _WEDGES, _W3, select="SELECT array_to_string(w, '-') AS edges FROM w3"))
def edge_embeddings_3(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 3, mode="edge").select(_text("eids", "edges"))


@query(sql(COP, _WEDGES, _W3, select="SELECT array_to_string(w, '-') AS edges FROM w3"))
def edge_embeddings_distinct(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    level = edge.init(g, carry=False)
    for _ in range(2):
        level = edge.expand(g, level, unique="distinct")
    return level.df.select(_text("eids", "edges"))


@query(sql(COP, ctes.SYM, select="SELECT DISTINCT e.src || '-' || e.dst AS path, CAST(s.b AS BIGINT) AS v FROM e JOIN s ON s.a IN (e.src, e.dst) WHERE s.b NOT IN (e.src, e.dst)"))
def candidates(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    return vertex.candidates(g, vertex.init(g, 2)).select(_text(name="path", ordered=False), "v")


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, select="SELECT CAST(1 AS INTEGER) AS k, (SELECT count(*) FROM v) AS n UNION ALL SELECT 2, (SELECT count(*) FROM e) UNION ALL SELECT 3, (SELECT count(*) FROM c3) UNION ALL SELECT 4, (SELECT count(*) FROM c4)"))
def level_sizes(spark, sf_dir):
    return loop.level_sizes(load(part_copurchase, spark, sf_dir), 4)


@query(sql(COP, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3 WHERE w[1] % 2 = w[2] % 2 AND w[1] % 2 = w[3] % 2"))
def filtered_explore(spark, sf_dir):
    """A user's filter: all vertices of an embedding have one parity."""
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 3, efilter=lambda path, v: F.element_at(path, 1) % 2 == v % 2).select(_text())


@query(sql(COP, ctes.SYM, select="SELECT deg, count(*) AS n FROM (SELECT e.src, e.dst, count(DISTINCT s.b) AS deg FROM e JOIN s ON s.a IN (e.src, e.dst) WHERE s.b NOT IN (e.src, e.dst) GROUP BY 1, 2) GROUP BY deg UNION ALL SELECT 0, count(*) FROM e WHERE NOT EXISTS (SELECT 1 FROM s WHERE s.a IN (e.src, e.dst) AND s.b NOT IN (e.src, e.dst)) HAVING count(*) > 0"))
def embedding_degree(spark, sf_dir):
    from levelmine.balance.predict import predict

    level = vertex.init(load(part_copurchase, spark, sf_dir), 2)
    return predict(level).groupBy(F.col("pred").alias("deg")).agg(F.count("*").alias("n"))


_DEEP = [ctes.SETS3] + [f"c{k} AS (SELECT DISTINCT list_sort(list_append(w, s.b)) AS w FROM (SELECT w, unnest(w) AS x FROM c{k - 1}) JOIN s ON s.a = x WHERE NOT list_contains(w, s.b))" for k in range(4, 8)]


@query(sql(ctes.KNN.replace("r <= 5", "r <= 1"), ctes.SYM, *_DEEP, select="SELECT CAST(1 AS INTEGER) AS k, (SELECT count(*) FROM v) AS n UNION ALL SELECT 2, (SELECT count(*) FROM e)" + "".join(f" UNION ALL SELECT {k}, (SELECT count(*) FROM c{k})" for k in range(3, 8))))
def deep_sizes(spark, sf_dir):
    """Sizes of the levels 1 to 7 on a sparse graph: each vector and the nearest other one."""
    return loop.level_sizes(load(vector_knn, spark, sf_dir, k=1), 7)


@query(sql(ctes.KNN, ctes.SYM, ctes.SETS3, ctes.SETS4, select="SELECT count(*) AS n FROM c4"))
def embeddings_4_count(spark, sf_dir):
    """How many embeddings of four vertices there are, counted without making them."""
    g = load(vector_knn, spark, sf_dir)
    for level in loop.explore(g, 4):
        if level.k == 3:
            return level.df.agg(F.coalesce(F.sum(loop.children(level)), F.lit(0).cast("long")).alias("n"))


@query(sql(ctes.COSUPPLIER, select="SELECT label, count(*) AS n FROM v GROUP BY 1"))
def label_histogram(spark, sf_dir):
    return load(supplier_coorder, spark, sf_dir).vertices.groupBy("label").agg(F.count("*").alias("n"))
