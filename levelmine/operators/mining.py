"""Queries of patterns, applications, baselines and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from levelmine import api
from levelmine.apps import clique, fsm, motif, triangle
from levelmine.baselines import brute, layered_dag, relational
from levelmine.explore import edge, loop
from levelmine.operators.exploration import COP, _text, _WEDGES
from levelmine.operators import shapes_sql
from levelmine.operators.registry import query
from levelmine.pattern import spectral
from levelmine.pattern.classify import classify, counts_by_embedding, pattern_counts
from levelmine.pattern.encode import bit, matrix, raw_counts
from levelmine.session import materialise, read_table
from levelmine.sources import ctes
from levelmine.sources.ctes import sql
from levelmine.sources.graphs import coactive_cells, load, part_copurchase, part_supplier, supplier_coorder, vector_knn
from levelmine.support import mni

KNN, SUP = ctes.KNN, ctes.COSUPPLIER
_M3 = "SELECT motif, CAST(frequency AS BIGINT) AS frequency FROM m3"
_M4 = "SELECT motif, frequency FROM m4"


def _labels(name: str = "labels"):
    return F.array_join(F.transform(name, lambda x: x.cast("string")), "-").alias("labels")


def vertices_text(code):
    """Column: label and degree of each vertex of a coded pattern, sorted; for the few patterns of a result."""

    def text(c: str) -> str:
        labels, bits = c.split("|")[:2]
        labels, m = labels.split("."), matrix(len(labels.split(".")), int(bits, 16))
        return " ".join(sorted(f"{x}:{sum(row)}" for x, row in zip(labels, m, strict=True)))

    return F.udf(text, "string")(code).alias("vertices")


# patterns


@query(sql(COP, ctes.SYM, ctes.SETS3, select="SELECT n_edges, count(*) AS n FROM (SELECT w, (SELECT count(*) FROM e WHERE list_contains(w, src) AND list_contains(w, dst)) AS n_edges FROM c3) GROUP BY 1"))
def raw_patterns_3(spark, sf_dir):
    """Raw forms by their number of edges."""
    raw = raw_counts(loop.embeddings(load(part_copurchase, spark, sf_dir), 3), labelled=False)
    return raw.groupBy(F.bit_count("bits").cast("long").alias("n_edges")).agg(F.sum("n").alias("n"))


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select="SELECT CAST(n_edges AS BIGINT) AS n_edges, count(*) AS n FROM (SELECT w, count(*) AS n_edges FROM i4 GROUP BY w) GROUP BY 1"))
def raw_patterns_4(spark, sf_dir):
    raw = raw_counts(loop.embeddings(load(part_copurchase, spark, sf_dir), 4), labelled=False)
    return raw.groupBy(F.bit_count("bits").cast("long").alias("n_edges")).agg(F.sum("n").alias("n"))


#: Lines of one order are adjacent if they were shipped within so many microseconds and their return flags differ.
_SPAN = 730 * 86_400_000_000
_PAIRS = [(i, j) for j in range(4) for i in range(j)]
_ORDERS = "w AS (SELECT l_orderkey, " + ", ".join(f"min(epoch_us(CAST(l_shipdate AS TIMESTAMP))) FILTER (l_linenumber = {i + 1}) AS s{i}, min(l_returnflag) FILTER (l_linenumber = {i + 1}) AS f{i}" for i in range(4)) + f""" FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY 1),
b AS (SELECT CASE WHEN s3 IS NULL THEN 3 ELSE 4 END AS k, {', '.join(f'CASE WHEN abs(s{i} - s{j}) <= {_SPAN} AND f{i} <> f{j} THEN 1 ELSE 0 END AS e{i}{j}' for i, j in _PAIRS)} FROM w WHERE s0 IS NOT NULL AND s1 IS NOT NULL AND s2 IS NOT NULL),
g AS (SELECT k, CASE k WHEN 3 THEN '1-1-1' ELSE '1-1-1-1' END AS labels, CAST(e01 + 2 * e02 + 4 * e12 + 8 * e03 + 16 * e13 + 32 * e23 AS BIGINT) AS bits,
      e01 + e02 + e12 + e03 + e13 + e23 AS m, e01 * e02 * e12 + e01 * e03 * e13 + e02 * e03 * e23 + e12 * e13 * e23 AS t,
      e01 * e23 AS x, e02 * e13 AS y, e03 * e12 AS z, count(*) AS n FROM b GROUP BY ALL)"""


def _order_graphs(spark, sf_dir):
    """(labels, bits, n): the small graphs of the first three or four lines of each order, by raw form."""
    lines = read_table(spark, sf_dir, "lineitem").filter("l_orderkey is not null and l_linenumber between 1 and 4")
    at, own = F.unix_micros(F.col("l_shipdate").cast("timestamp")), lambda i, c: F.min(F.when(F.col("l_linenumber") == i + 1, c))
    wide = lines.groupBy("l_orderkey").agg(*[own(i, at).alias(f"s{i}") for i in range(4)], *[own(i, F.col("l_returnflag")).alias(f"f{i}") for i in range(4)])
    near = lambda i, j: (F.abs(F.col(f"s{i}") - F.col(f"s{j}")) <= _SPAN) & (F.col(f"f{i}") != F.col(f"f{j}"))
    bits = sum((F.when(near(i, j), 1 << bit(i, j)).otherwise(0) for i, j in _PAIRS), F.lit(0).cast("long"))
    forms = wide.filter("s0 is not null and s1 is not null and s2 is not null").select(F.expr("if(s3 is null, 3, 4)").alias("k"), bits.alias("bits"))
    return forms.groupBy("k", "bits").agg(F.count("*").alias("n")).select(F.expr("array_repeat(1, k)").alias("labels"), "bits", "n")


@query(sql(_ORDERS, select="SELECT labels, bits, CASE WHEN m = 0 THEN '0.0' ELSE '0.-' || m END || CASE WHEN t = 0 THEN '.0' ELSE '.-' || 2 * t END || CASE WHEN k = 4 THEN '.' || (x + y + z - 2 * (x * y + x * z + y * z)) ELSE '' END AS polynomial, n FROM g"))
def charpoly_fixture(spark, sf_dir):
    """Characteristic polynomials of the orders' small graphs; of four vertices the last coefficient is the pairs of
    edges without a common end, less two for each cycle of four."""
    poly = F.udf(lambda lab, bits: ".".join(map(str, spectral.charpoly(spectral.matrix(len(lab), bits)))), "string")
    return _order_graphs(spark, sf_dir).select(_labels(), "bits", poly("labels", "bits").alias("polynomial"), "n")


def _classes(spark, sf_dir, k, engine, graph=vector_knn):
    counts = pattern_counts(loop.embeddings(load(graph, spark, sf_dir), k), False, engine)
    return counts.select(F.col("frequency"))


_F3, _F4 = "SELECT CAST(frequency AS BIGINT) AS frequency FROM m3", "SELECT frequency FROM m4"
_K3, _K4 = (KNN, ctes.SYM, ctes.SETS3, ctes.SHAPES3), (KNN, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4)


@query(sql(*_K3, select=_F3))
def spectral_classes_3(spark, sf_dir):
    return _classes(spark, sf_dir, 3, "spectral")


@query(sql(*_K4, select=_F4))
def spectral_classes_4(spark, sf_dir):
    return _classes(spark, sf_dir, 4, "spectral")


def _keyed(spark, sf_dir, labels: bool, degrees: bool):
    """Embeddings by a spectral key of the given parts."""
    raw = raw_counts(loop.embeddings(load(vector_knn, spark, sf_dir), 4), labelled=labels)
    key = F.udf(lambda lab, bits: spectral.key_text(spectral.key(tuple(lab), bits, use_labels=labels, use_degrees=degrees)), "string")
    return raw.select(key("labels", "bits").alias("key"), "n").groupBy("key").agg(F.sum("n").alias("frequency"))


@query(sql(*_K4, select=_F4))
def spectral_plain(spark, sf_dir):
    return _keyed(spark, sf_dir, False, False).select("frequency")


@query(sql(*_K4, select=_F4))
def spectral_degrees(spark, sf_dir):
    return _keyed(spark, sf_dir, False, True).select("frequency")


@query(sql(KNN, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select=shapes_sql.labelled_classes(4, "k4", "ds")))
def spectral_labelled(spark, sf_dir):
    """Labelled classes by the key alone: for each bag of labels and degrees, how many keys, and their embeddings."""
    raw = raw_counts(loop.embeddings(load(vector_knn, spark, sf_dir), 4))
    both = F.udf(lambda lab, bits: (spectral.key_text(spectral.key(tuple(lab), bits)), " ".join(sorted(f"{x}:{sum(r)}" for x, r in zip(lab, matrix(len(lab), bits), strict=True)))), "key string, vertices string")
    keyed = raw.select(both("labels", "bits").alias("b"), "n").groupBy("b.key", "b.vertices").agg(F.sum("n").alias("n"))
    return keyed.groupBy("vertices").agg(F.count("*").alias("classes"), F.sum("n").cast("long").alias("frequency"))


@query(sql(_ORDERS, select="SELECT labels, bits, CAST(0 AS BIGINT) AS total, CAST(2 * m AS BIGINT) AS squares, CAST(6 * t AS BIGINT) AS cubes, n FROM g"))
def eigenvalue_check(spark, sf_dir):
    """Power sums of the eigenvalues of the orders' small graphs: none, twice the edges, six times the triangles."""

    def sums(lab, bits):
        values = spectral.eigenvalues(tuple(lab), bits, use_labels=False)
        return [round(sum(x**n for x in values)) for n in (1, 2, 3)]

    found = _order_graphs(spark, sf_dir).select(_labels(), "bits", F.udf(sums, "array<long>")("labels", "bits").alias("s"), "n")
    return found.select("labels", "bits", F.col("s")[0].alias("total"), F.col("s")[1].alias("squares"), F.col("s")[2].alias("cubes"), "n")


@query(sql(*_K3, select=_F3))
def exact_classes_3(spark, sf_dir):
    return _classes(spark, sf_dir, 3, "exact")


@query(sql(*_K4, select=_F4))
def exact_classes_4(spark, sf_dir):
    return _classes(spark, sf_dir, 4, "exact")


@query(sql(*_K4, select=_F4))
def verified_classes(spark, sf_dir):
    return _classes(spark, sf_dir, 4, "verified")


@query(sql(*_K4, select=_M4))
def named_motifs(spark, sf_dir):
    return motif.named(motif.motifs(load(vector_knn, spark, sf_dir), 4))


@query("SELECT * FROM (VALUES ('spectral', CAST(0 AS BIGINT), CAST(0 AS BIGINT)), ('verified', 0, 0), ('search_tree', 0, 0)) t(engine, false_merges, false_splits)")
def engine_agreement(spark, sf_dir):
    """False merges and false splits of each engine against the exact form, over labelled raw forms of four vertices."""
    from functools import reduce

    raw = materialise(raw_counts(loop.embeddings(load(part_copurchase, spark, sf_dir), 4)).select("labels", "bits"), "raw")
    truth = classify(raw, "exact").withColumnRenamed("code", "truth")

    def wrong(engine):
        both = classify(raw, engine).join(truth, ["labels", "bits"])
        merges = both.groupBy("code").agg((F.countDistinct("truth") - 1).alias("n")).agg(F.sum("n").alias("false_merges"))
        splits = both.groupBy("truth").agg((F.countDistinct("code") - 1).alias("n")).agg(F.sum("n").alias("false_splits"))
        return merges.join(splits).select(F.lit(engine).alias("engine"), "false_merges", "false_splits")

    return reduce(lambda a, b: a.unionByName(b), map(wrong, ("spectral", "verified", "search_tree")))


# motifs


@query(sql(*_K3, select=_M3))
def motif_3(spark, sf_dir):
    return motif.named(motif.motifs(load(vector_knn, spark, sf_dir), 3))


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select=_M4))
def motif_4(spark, sf_dir):
    return motif.named(motif.motifs(load(part_copurchase, spark, sf_dir), 4))


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SETS5, ctes.shapes5(), select="SELECT motif, frequency FROM m5"))
def motif_5(spark, sf_dir):
    return motif.named(motif.motifs(load(part_copurchase, spark, sf_dir), 5))


@query(sql(ctes.COACTIVE, ctes.SYM, ctes.SETS3, ctes.SHAPES3, select=_M3))
def motif_3_coactivity(spark, sf_dir):
    """Chains and triangles of a dense graph, counted on packed edges."""
    return motif.named(motif.motifs_3(*coactive_cells(read_table(spark, sf_dir, "events"))))


@query(sql(*_K3, select=_M3))
def motif_3_stored(spark, sf_dir):
    return motif.named(motif.motifs(load(vector_knn, spark, sf_dir), 3, fuse_last=False))


_LABELLED3 = """
tl AS (SELECT w, list_sort([v1.label, v2.label, v3.label]) AS ls, 3 AS edges FROM (SELECT [a, b, c] AS w FROM t3) JOIN v v1 ON v1.id = w[1] JOIN v v2 ON v2.id = w[2] JOIN v v3 ON v3.id = w[3]),
ch AS (SELECT x.a AS m, least(x.b, y.b) AS p, greatest(x.b, y.b) AS q FROM s x JOIN s y ON x.a = y.a AND x.b < y.b WHERE NOT EXISTS (SELECT 1 FROM e WHERE src = x.b AND dst = y.b)),
cl AS (SELECT vm.label AS middle, least(vp.label, vq.label) AS lo, greatest(vp.label, vq.label) AS hi FROM ch JOIN v vm ON vm.id = m JOIN v vp ON vp.id = p JOIN v vq ON vq.id = q)
"""


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SHAPES3, _LABELLED3, select="SELECT count(*) AS frequency FROM tl GROUP BY ls UNION ALL SELECT count(*) FROM cl GROUP BY middle, lo, hi"))
def motif_3_labelled(spark, sf_dir):
    return motif.motifs(load(part_copurchase, spark, sf_dir), 3, labelled=True).select("frequency")


# cliques and triangles

_C3 = "q3 AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst)"
_C4 = "q4 AS (SELECT a, b, c, w.dst AS d FROM q3 JOIN e w ON w.src = c JOIN e x ON x.src = a AND x.dst = w.dst JOIN e y ON y.src = b AND y.dst = w.dst)"
_C5 = "q5 AS (SELECT x.a, x.b, x.c, x.d, y.d AS f FROM q4 x JOIN q4 y ON x.a = y.a AND x.b = y.b AND x.c = y.c AND x.d < y.d JOIN e ON src = x.d AND dst = y.d)"


@query(sql(COP, _C3, select="SELECT a || '-' || b || '-' || c AS path FROM q3"))
def match_triangle(spark, sf_dir):
    from levelmine.pattern.exact import canonical

    code = canonical((1, 1, 1), 7)[0]
    return motif.match(load(part_copurchase, spark, sf_dir), code, 3).select(_text(name="path"))


@query(sql(SUP, _C3, select="SELECT a || '-' || b || '-' || c AS path FROM q3"))
def clique_3(spark, sf_dir):
    return clique.cliques(load(supplier_coorder, spark, sf_dir), 3).select(_text(name="path"))


@query(sql(SUP, _C3, _C4, select="SELECT a || '-' || b || '-' || c || '-' || d AS path FROM q4"))
def clique_4(spark, sf_dir):
    return clique.cliques(load(supplier_coorder, spark, sf_dir), 4).select(_text(name="path"))


@query(sql(SUP, _C3, _C4, _C5, select="SELECT a || '-' || b || '-' || c || '-' || d || '-' || f AS path FROM q5"))
def clique_5(spark, sf_dir):
    return clique.cliques(load(supplier_coorder, spark, sf_dir), 5, oriented=True).select(_text(name="path"))


@query(sql(SUP, _C3, _C4, select="SELECT count(*) AS n FROM q4"))
def clique_4_count(spark, sf_dir):
    return clique.clique_count(load(supplier_coorder, spark, sf_dir), 4)


_T = sql(COP, _C3, select="SELECT count(*) AS n FROM q3")


@query(_T)
def triangle_count(spark, sf_dir):
    return triangle.triangles(load(part_copurchase, spark, sf_dir))


@query(_T)
def triangle_join(spark, sf_dir):
    return triangle.triangles(load(part_copurchase, spark, sf_dir), "join")


@query(_T)
def triangle_oriented(spark, sf_dir):
    return triangle.triangles(load(part_copurchase, spark, sf_dir), "oriented")


DENSE = COP.replace("HAVING count(*) >= CASE WHEN (SELECT count(*) FROM part) <= 200 THEN 4 ELSE 2 END", "")


@query(sql(DENSE, _C3, select="SELECT count(*) AS n FROM q3"))
def triangle_count_dense(spark, sf_dir):
    """Parts that share any order: the graph with the most edges."""
    return triangle.triangles(load(part_copurchase, spark, sf_dir, min_orders=1), "oriented")


@query(sql(ctes.PARTSUPP, _C3, select="SELECT count(*) AS n FROM q3"))
def triangle_count_bipartite(spark, sf_dir):
    """None, in a graph of two sides."""
    return triangle.triangles(load(part_supplier, spark, sf_dir), "oriented")


@query(sql(SUP, ctes.SYM, _C3, select="SELECT id, coalesce(t, 0) AS triangles, round(CASE WHEN deg > 1 THEN 2.0 * coalesce(t, 0) / (deg * (deg - 1)) ELSE 0 END, 6) AS clustering FROM (SELECT a AS id, count(*) AS deg FROM s GROUP BY 1) LEFT JOIN (SELECT x AS id, count(*) AS t FROM (SELECT a AS x FROM q3 UNION ALL SELECT b FROM q3 UNION ALL SELECT c FROM q3) GROUP BY 1) USING (id)").replace("round(CASE WHEN", "CAST(round(CASE WHEN").replace("END, 6) AS clustering", "END, 6) AS DOUBLE) AS clustering"))
def triangle_per_vertex(spark, sf_dir):
    return triangle.per_vertex(load(supplier_coorder, spark, sf_dir))


# frequent subgraphs

_E1 = """
p1 AS (SELECT least(a.label, b.label) AS lo, greatest(a.label, b.label) AS hi, CASE WHEN a.label <= b.label THEN src ELSE dst END AS x, CASE WHEN a.label <= b.label THEN dst ELSE src END AS y FROM e JOIN v a ON a.id = src JOIN v b ON b.id = dst),
i1 AS (SELECT lo, hi, CASE WHEN lo = hi THEN 0 ELSE 1 END AS o, x AS z FROM p1 UNION ALL SELECT lo, hi, 0, y FROM p1),
s1 AS (SELECT lo, hi, min(n) AS mni FROM (SELECT lo, hi, o, count(DISTINCT z) AS n FROM i1 GROUP BY 1, 2, 3) GROUP BY 1, 2)
"""
_E2 = """
p2 AS (SELECT vm.label AS m, least(va.label, vb.label) AS lo, greatest(va.label, vb.label) AS hi, x.a AS mid, CASE WHEN va.label <= vb.label THEN x.b ELSE y.b END AS p, CASE WHEN va.label <= vb.label THEN y.b ELSE x.b END AS q
       FROM s x JOIN s y ON x.a = y.a AND x.b < y.b JOIN v vm ON vm.id = x.a JOIN v va ON va.id = x.b JOIN v vb ON vb.id = y.b),
i2 AS (SELECT m, lo, hi, 0 AS o, mid AS z FROM p2 UNION ALL SELECT m, lo, hi, CASE WHEN lo = hi THEN 2 ELSE 1 END, p FROM p2 UNION ALL SELECT m, lo, hi, 2, q FROM p2),
s2 AS (SELECT m, lo, hi, min(n) AS mni FROM (SELECT m, lo, hi, o, count(DISTINCT z) AS n FROM i2 GROUP BY 1, 2, 3, 4) GROUP BY 1, 2, 3)
"""


def _support(spark, sf_dir) -> int:
    return 3 if load(part_copurchase, spark, sf_dir).vertices.count() < 500 else 40


#: The support the queries ask for, by the graph's size.
_S = "(SELECT CASE WHEN count(*) < 500 THEN 3 ELSE 40 END FROM v)"


def _fsm(spark, sf_dir, n, support=None, **how):
    return fsm.fsm(load(part_copurchase, spark, sf_dir), n, support or _support(spark, sf_dir), **how)


@query(sql(COP, _E1, select="SELECT mni FROM s1"))
def mni_edges(spark, sf_dir):
    return mni.exact(edge.init(load(part_copurchase, spark, sf_dir), carry=False).df).select("mni")


def _told(found):
    """Frequent patterns as the SQL names them."""
    return found.select("n_edges", vertices_text("pattern"), "mni", "embeddings")


def _frequent(n: int, graph: str = COP, least: str = _S) -> str:
    return sql(graph, ctes.SYM, select=shapes_sql.frequent(n, least))


@query(_frequent(1))
def fsm_edges_1(spark, sf_dir):
    return _told(_fsm(spark, sf_dir, 1))


_FSM2 = _frequent(2)


@query(_FSM2)
def fsm_edges_2(spark, sf_dir):
    return _told(_fsm(spark, sf_dir, 2))


@query(_frequent(3))
def fsm_edges_3(spark, sf_dir):
    return _told(_fsm(spark, sf_dir, 3))


@query(_frequent(4))
def fsm_edges_4(spark, sf_dir):
    return _told(_fsm(spark, sf_dir, 4))


#: Labels folded to two, so that patterns of four edges are frequent too.
TWO = COP.replace("CAST(t.label AS INTEGER) AS label", "CAST(t.label % 2 + 1 AS INTEGER) AS label")
TWO_SUPPORT = 100


def two_labels(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    return g.relabelled(g.vertices.select("id", (F.col("label") % 2 + 1).alias("label")))


@query(_frequent(4, TWO, str(TWO_SUPPORT)))
def fsm_edges_4_two_labels(spark, sf_dir):
    return _told(fsm.fsm(two_labels(spark, sf_dir), 4, TWO_SUPPORT))


@query(_frequent(3, TWO, str(TWO_SUPPORT)))
def fsm_by_distinct(spark, sf_dir):
    """Grown without carrying candidates, as for graphs whose hubs do not fit a row."""
    return _told(fsm.fsm(two_labels(spark, sf_dir), 3, TWO_SUPPORT, strategy="distinct"))


@query(f"SELECT n_edges, vertices FROM ({_frequent(4, TWO, str(TWO_SUPPORT))})")
def fsm_capped_4(spark, sf_dir):
    """Counting stops early: the set of patterns is that of the exact counts."""
    return fsm.fsm(two_labels(spark, sf_dir), 4, TWO_SUPPORT, exact=False).select("n_edges", vertices_text("pattern"))


BRAND = COP.replace("p_type", "p_brand")


@query(sql(BRAND, ctes.SYM, _E1, _E2, select="SELECT CAST(1 AS INTEGER) AS n_edges, mni FROM s1 WHERE mni >= 3 UNION ALL SELECT 2, mni FROM s2 WHERE mni >= 3"))
def fsm_many_labels(spark, sf_dir):
    """The same graph with more labels: more patterns, each with less support."""
    return fsm.fsm(load(part_copurchase, spark, sf_dir, label="p_brand"), 2, 3).select("n_edges", "mni")


@query(sql(KNN, ctes.SYM, _E1, _E2, select="SELECT CAST(1 AS INTEGER) AS n_edges, mni FROM s1 WHERE mni >= 10 UNION ALL SELECT 2, mni FROM s2 WHERE mni >= 10"))
def fsm_knn(spark, sf_dir):
    return fsm.fsm(load(vector_knn, spark, sf_dir), 2, 10).select("n_edges", "mni")


@query(sql(COP, ctes.SYM, _E1, _E2, select=f"SELECT n_edges, count(*) AS patterns FROM (SELECT CAST(1 AS INTEGER) AS n_edges, mni FROM s1 UNION ALL SELECT 2, mni FROM s2) WHERE mni >= {_S} GROUP BY 1"))
def fsm_capped(spark, sf_dir):
    """Counting stops at the support; the set of patterns is that of the exact counts."""
    return _fsm(spark, sf_dir, 2, exact=False).groupBy("n_edges").agg(F.count("*").alias("patterns"))


@query(_FSM2)
def fsm_noprune(spark, sf_dir):
    return _told(_fsm(spark, sf_dir, 2, prune=False))


@query(sql(COP, _E1, select=f"SELECT count(*) AS n FROM p1 JOIN s1 USING (lo, hi) WHERE mni >= {_S}"))
def fsm_frequent_edges(spark, sf_dir):
    g = fsm.frequent_edges(load(part_copurchase, spark, sf_dir), _support(spark, sf_dir))
    return g.edges.agg(F.count("*").alias("n"))


@query(sql(COP, ctes.SYM, _E1, _E2, select=f"SELECT CAST(1 AS INTEGER) AS n_edges, n AS mni FROM (SELECT count(*) AS n FROM p1 GROUP BY lo, hi) WHERE n >= {_S} UNION ALL SELECT 2, n FROM (SELECT count(*) AS n FROM p2 GROUP BY m, lo, hi) WHERE n >= {_S}"))
def fsm_count(spark, sf_dir):
    return _fsm(spark, sf_dir, 2, measure="count").select("n_edges", "mni")


@query(sql(COP, ctes.SYM, _E1, _E2, select="SELECT count(*) AS patterns, count(*) AS close FROM s2"))
def mni_approx(spark, sf_dir):
    """Supports by sketches: patterns, and those within a fifth of the exact number."""
    level = materialise(loop.embeddings(load(part_copurchase, spark, sf_dir), 2, mode="edge"), "two")
    both = mni.approximate(level).withColumnRenamed("mni", "screen").join(mni.exact(level), "code")
    return both.agg(F.count("*").alias("patterns"), F.sum((F.abs(F.col("screen") - F.col("mni")) <= 0.2 * F.col("mni") + 1).cast("long")).alias("close"))


@query(sql(COP, _WEDGES, select="SELECT count(*) AS n FROM w2"))
def fsm_level_rows(spark, sf_dir):
    return loop.embeddings(load(part_copurchase, spark, sf_dir), 2, mode="edge").agg(F.count("*").alias("n"))


# the programming interface


@query(sql(*_K3, select="SELECT CAST(frequency AS BIGINT) AS value FROM m3"))
def job_motif_3(spark, sf_dir):
    return api.MiningJob(load(vector_knn, spark, sf_dir), 3, labelled=False).run().select("value")


@query(sql(*_K3, select="SELECT CAST(frequency AS BIGINT) AS value FROM m3 WHERE frequency > 1000"))
def job_pattern_filter(spark, sf_dir):
    return api.MiningJob(load(vector_knn, spark, sf_dir), 3, labelled=False, pfilter=F.col("value") > 1000).run().select("value")


@query(sql(KNN, ctes.SYM, ctes.SETS3, select="SELECT count(*) AS n FROM c3"))
def job_count_only(spark, sf_dir):
    return api.MiningJob(load(vector_knn, spark, sf_dir), 3, mapper=None).run()


_LOW = f"""
low AS (SELECT src, dst FROM e WHERE src IN (SELECT id FROM v WHERE label <= 3) AND dst IN (SELECT id FROM v WHERE label <= 3)),
s AS (SELECT src AS a, dst AS b FROM low UNION ALL SELECT dst, src FROM low)"""


@query(sql(COP, _LOW, ctes.SETS3, ctes.LABELLED3, select=shapes_sql.labelled_classes(3, "k3s", "ds").replace("count(*) AS classes, ", "")))
def job_each_round(spark, sf_dir):
    """Patterns are filtered after every round, here to three labels; the embeddings of the others are not grown."""
    low = F.expr("forall(split(split(pattern, '[|]')[0], '[.]'), x -> int(x) <= 3)")
    found = api.MiningJob(load(part_copurchase, spark, sf_dir), 3, loop="each", pfilter=low).run()
    return found.groupBy(vertices_text("pattern")).agg(F.sum("value").cast("long").alias("frequency"))


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select=_M4))
def job_balanced(spark, sf_dir):
    """Each level dealt out by predicted work before it is grown; levels by predicted size in memory or on disk."""
    from levelmine.store.hybrid import Storage

    job = api.MiningJob(load(part_copurchase, spark, sf_dir), 4, labelled=False, balance="predicted", storage=Storage("hybrid", 1 << 20))
    return motif.named(job.run().withColumnsRenamed({"pattern": "code", "value": "frequency"}))


@query(sql(KNN, ctes.SYM, ctes.SETS3, ctes.SHAPES3, select="SELECT CAST(sum(frequency) AS BIGINT) AS mapped, count(*) AS final, true AS between FROM m3"))
def combine_rows(spark, sf_dir):
    """Pairs that the mapper makes, raw forms in the end; what tasks pass on lies between."""
    level = loop.embeddings(load(vector_knn, spark, sf_dir), 3).withColumn("labels", F.array_repeat(F.lit(1), 3))
    got = api.combine_rows(level.withColumn("bits", F.when(F.bit_count("bits") == 3, 7).otherwise(3)))
    return got.select("mapped", "final", ((F.col("partial") <= F.col("mapped")) & (F.col("partial") >= F.col("final"))).alias("between"))


# baselines


@query(sql(KNN, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3"))
def baseline_dag_3(spark, sf_dir):
    return layered_dag.explore(load(vector_knn, spark, sf_dir), 3).select(_text())


@query(sql(*_K3, select=_M3))
def baseline_relational_motif_3(spark, sf_dir):
    return motif.named(relational.motifs(load(vector_knn, spark, sf_dir), 3, "exact"))


@query(sql(KNN, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select=_M4))
def baseline_relational_motif_4(spark, sf_dir):
    """Six rounds: a clique of four is reached with its sixth edge."""
    return motif.named(relational.motifs(load(vector_knn, spark, sf_dir), 4, "exact"))


@query(sql(SUP, _C3, select="SELECT a || '-' || b || '-' || c AS path FROM q3"))
def baseline_relational_clique_3(spark, sf_dir):
    return relational.cliques(load(supplier_coorder, spark, sf_dir), 3).select(_text(name="path"))


@query(sql(KNN, _C3, _C4, select="SELECT a || '-' || b || '-' || c || '-' || d AS path FROM q4"))
def baseline_relational_clique_4(spark, sf_dir):
    return relational.cliques(load(vector_knn, spark, sf_dir), 4).select(_text(name="path"))


@query(sql(SUP, _C3, select="SELECT count(*) AS n FROM q3"))
def baseline_gather_triangles(spark, sf_dir):
    return relational.triangles(load(supplier_coorder, spark, sf_dir))


@query(sql(*_K4, select=_F4))
def baseline_search_tree_4(spark, sf_dir):
    return _classes(spark, sf_dir, 4, "search_tree")


_EACH = sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, ctes.SHAPES4, select=_F4)


@query(_EACH)
def baseline_search_tree_each(spark, sf_dir):
    """Every embedding labelled by the search tree."""
    return counts_by_embedding(loop.embeddings(load(part_copurchase, spark, sf_dir), 4), False, "search_tree").select("frequency")


@query(_EACH)
def spectral_each(spark, sf_dir):
    """Every embedding keyed by its spectrum."""
    return counts_by_embedding(loop.embeddings(load(part_copurchase, spark, sf_dir), 4), False, "spectral").select("frequency")


@query(sql(KNN, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3"))
def brute_3(spark, sf_dir):
    return brute.subsets(load(vector_knn, spark, sf_dir), 3).select(_text("verts"))


@query(sql(COP, ctes.SYM, ctes.SETS3, _WEDGES, _C3, select="SELECT CAST(1 AS INTEGER) AS round, (SELECT count(*) FROM e) AS relational_rows, (SELECT count(*) FROM v) AS level_rows UNION ALL SELECT 2, (SELECT count(*) FROM w2), (SELECT count(*) FROM e) UNION ALL SELECT 3, (SELECT count(*) FROM q3), (SELECT count(*) FROM c3)"))
def relational_rounds(spark, sf_dir):
    """Rows that each round of the relational baseline makes, beside the levels of the exploration."""
    g = load(part_copurchase, spark, sf_dir)
    _, made = relational.vertex_sets(g, 3)
    ours = {r["k"]: r["n"] for r in loop.level_sizes(g, 3).collect()}
    return spark.createDataFrame([(i + 1, n, ours.get(i + 1)) for i, n in enumerate(made)], "round int, relational_rows long, level_rows long")
