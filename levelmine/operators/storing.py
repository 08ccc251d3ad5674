"""Queries of the level store, of storage and of load balance."""

from __future__ import annotations

from pyspark.sql import functions as F

from levelmine.apps.motif import named
from levelmine.balance import predict as balance
from levelmine.explore import vertex
from levelmine.explore.loop import explore
from levelmine.explore.vertex import Level
from levelmine.operators.exploration import COP, _PATHS3, _text
from levelmine.operators.registry import query
from levelmine.pattern.classify import pattern_counts
from levelmine.session import materialise
from levelmine.sources import ctes
from levelmine.sources.ctes import sql
from levelmine.sources.graphs import load, part_copurchase
from levelmine.store.hybrid import Storage, expand_by_part, explore_stored
from levelmine.store.levels import LevelStore, stored

_STORES: dict[tuple, LevelStore] = {}


def _store(spark, sf_dir, k: int = 3, layout: str = "links") -> LevelStore:
    key = (spark.sparkContext.applicationId, sf_dir, k, layout)
    if key not in _STORES:
        _STORES[key] = stored(load(part_copurchase, spark, sf_dir), k, layout)
    return _STORES[key]


_LEVELS = """
l2 AS (SELECT src, dst, row_number() OVER (ORDER BY src, dst) - 1 AS pos FROM e),
l3 AS (SELECT p, q, r, row_number() OVER (ORDER BY p, q, r) - 1 AS pos FROM k3),
f3 AS (SELECT l3.pos, l2.pos AS parent, r AS vert, p, q, r FROM l3 JOIN l2 ON p = src AND q = dst)
"""


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT pos, parent, CAST(vert AS BIGINT) AS vert FROM f3"))
def level_table_3(spark, sf_dir):
    return _store(spark, sf_dir).level(3).select("pos", "parent", "vert")


_OFFSETS = """
n3 AS (SELECT l2.pos AS parent, count(f3.pos) AS n FROM l2 LEFT JOIN f3 ON f3.parent = l2.pos GROUP BY 1),
o3 AS (SELECT parent, CAST(coalesce(sum(n) OVER (ORDER BY parent ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start, n FROM n3)
"""


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, _OFFSETS, select="SELECT parent, start, start + n AS stop FROM o3"))
def level_offsets_3(spark, sf_dir):
    return _store(spark, sf_dir).offsets(3)


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT pos, parent, CAST(vert AS BIGINT) AS vert FROM f3 WHERE parent = 7"))
def level_children(spark, sf_dir):
    return _store(spark, sf_dir).children(3, 7).select("pos", "parent", "vert")


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT CAST(5 AS BIGINT) AS pos, p || '-' || q || '-' || r AS path FROM l3 WHERE pos = 5"))
def decode_one(spark, sf_dir):
    path = _store(spark, sf_dir).decode(3, 5)
    return spark.createDataFrame([(5, "-".join(map(str, path)))], "pos long, path string")


_ALL3 = sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT pos, p || '-' || q || '-' || r AS path FROM l3")


@query(_ALL3)
def decode_all_3(spark, sf_dir):
    return _store(spark, sf_dir).paths(3).select("pos", _text(name="path", ordered=False))


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT pos, p || '-' || q || '-' || r AS path FROM l3 WHERE pos >= 100 AND pos < 200"))
def decode_range(spark, sf_dir):
    return _store(spark, sf_dir).paths(3, 100, 200).select("pos", _text(name="path", ordered=False))


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT pos, p || '-' || q || '-' || r AS path FROM l3"))
def tensor_lookup(spark, sf_dir):
    """Of all canonical triples and all of them turned round, those that are cells."""
    paths = _store(spark, sf_dir).paths(3).select("path")
    return _store(spark, sf_dir).contains(paths.unionAll(paths.select(F.reverse("path"))), 3).select("pos", _text(name="path", ordered=False))


@query(_ALL3)
def paths_layout(spark, sf_dir):
    return _store(spark, sf_dir, layout="paths").paths(3).select("pos", _text(name="path", ordered=False))


@query()
def store_bytes(spark, sf_dir):
    """Bytes of each level as links, as whole paths and as a layered DAG, its rows, and the expected number by the formula."""
    from levelmine.baselines.layered_dag import LayeredDag
    from levelmine.measure.stats import space_formula
    from levelmine.session import path_bytes

    g = load(part_copurchase, spark, sf_dir)
    links, paths, s = _store(spark, sf_dir), _store(spark, sf_dir, layout="paths"), g.stats().first()
    dag = {k: sum(path_bytes(spark, f) for link in LayeredDag.build(paths.level(k), k).links for f in link.inputFiles()) for k in (2, 3)}
    rows = [(k, links.level(k).count(), links.bytes(k), paths.bytes(k), dag.get(k), float(space_formula(s["n_vertices"], s["n_edges"], k))) for k in (1, 2, 3)]
    return spark.createDataFrame(rows, "k int, n_rows long, link_bytes long, path_bytes long, dag_bytes long, expected_rows double")


_MOTIF3 = sql(COP, ctes.SYM, ctes.SETS3, ctes.SHAPES3, select="SELECT motif, CAST(frequency AS BIGINT) AS frequency FROM m3")


def _by_kind(spark, sf_dir, kind):
    rows = explore_stored(load(part_copurchase, spark, sf_dir), 3, Storage(kind, 1 << 20))
    return named(pattern_counts(rows, labelled=False))


@query(_MOTIF3)
def memory_same_answer(spark, sf_dir):
    return _by_kind(spark, sf_dir, "memory")


@query(_MOTIF3)
def hybrid_same_answer(spark, sf_dir):
    return _by_kind(spark, sf_dir, "hybrid")


@query(_MOTIF3)
def disk_same_answer(spark, sf_dir):
    return _by_kind(spark, sf_dir, "disk")


@query(sql(COP, select="SELECT CAST(part AS INTEGER) AS part, count(*) AS n FROM (SELECT (row_number() OVER (ORDER BY src, dst) - 1) * 4 // (SELECT count(*) FROM e) AS part FROM e) GROUP BY 1"))
def even_parts(spark, sf_dir):
    level = vertex.init(load(part_copurchase, spark, sf_dir), 2)
    return balance.split_even(level.df.select("path"), 4, "path").groupBy("part").agg(F.count("*").alias("n"))


@query(sql(COP, select="SELECT CAST(part AS INTEGER) AS part, count(*) AS n, min(pos) AS lo, max(pos) AS hi FROM (SELECT pos, pos * 4 // (SELECT count(*) FROM e) AS part FROM (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pos FROM e)) GROUP BY 1"))
def level_parts(spark, sf_dir):
    """Parts as folders, read back part by part."""
    store = LevelStore(spark)
    parted = balance.split_even(_store(spark, sf_dir).paths(2).select("path"), 4, "path")
    back = spark.read.parquet(store.write_parts(2, parted))
    return back.groupBy("part").agg(F.count("*").alias("n"), F.min("pos").alias("lo"), F.max("pos").alias("hi"))


@query(sql(COP, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3"))
def by_part_same_answer(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    return expand_by_part(g, vertex.init(g, 2), 3).select(_text())


@query(sql(COP, ctes.SYM, ctes.SETS3, ctes.SETS4, select="SELECT array_to_string(w, '-') AS verts FROM c4"))
def by_window_same_answer(spark, sf_dir):
    """Level 4 from parts of the stored level 3 and the windows of the levels above it."""
    from levelmine.store.hybrid import expand_windows

    return expand_windows(load(part_copurchase, spark, sf_dir), _store(spark, sf_dir), 3).select(_text())


@query(sql(COP, ctes.SYM, _PATHS3, _LEVELS, select="SELECT CAST(part AS INTEGER) AS part, count(DISTINCT parent) AS runs, min(pos) AS lo, max(pos) + 1 AS hi FROM (SELECT pos, parent, pos * 4 // (SELECT count(*) FROM f3) AS part FROM f3) GROUP BY 1"))
def part_offsets(spark, sf_dir):
    """The offsets that are written beside the parts of level 3."""
    store = _store(spark, sf_dir, layout="links")
    rows = store.level(3).select("pos", "parent", "vert")
    parted = balance.split_even(rows.withColumnRenamed("pos", "own"), 4, "own").drop("pos").withColumnRenamed("own", "pos")
    store.write_parts(3, parted)
    runs = spark.read.parquet(f"{store.root}/parts_offsets=3")
    return runs.groupBy("part").agg(F.count("*").alias("runs"), F.min("start").alias("lo"), F.max("stop").alias("hi"))


_PRED = "SELECT e.src, e.dst, count(DISTINCT s.b) FILTER (WHERE s.b NOT IN (e.src, e.dst)) AS pred FROM e JOIN s ON s.a IN (e.src, e.dst) GROUP BY 1, 2"


@query(sql(COP, ctes.SYM, select=f"SELECT src || '-' || dst AS path, pred FROM ({_PRED})"))
def predicted_candidates(spark, sf_dir):
    level = vertex.init(load(part_copurchase, spark, sf_dir), 2)
    return balance.predict(level).select(_text(name="path", ordered=False), "pred")


@query(sql(COP, ctes.SYM, select="SELECT e.src || '-' || e.dst AS path, count(*) AS pred FROM e JOIN s ON s.a IN (e.src, e.dst) GROUP BY 1"))
def degree_bound(spark, sf_dir):
    g = load(part_copurchase, spark, sf_dir)
    return balance.degree_bound(g, vertex.init(g, 2)).select(_text(name="path", ordered=False), "pred")


_PARTS = f"""
p AS ({_PRED}),
q AS (SELECT pred, coalesce(sum(pred) OVER (ORDER BY src, dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead, sum(pred) OVER () AS total FROM p)
"""


@query(sql(COP, ctes.SYM, _PARTS, select="SELECT CAST(least(ahead * 4 // total, 3) AS INTEGER) AS part, count(*) AS n, CAST(sum(pred) AS BIGINT) AS work FROM q GROUP BY 1"))
def predicted_parts(spark, sf_dir):
    level = vertex.init(load(part_copurchase, spark, sf_dir), 2)
    parted = balance.split_predicted(balance.predict(level).select("path", "pred"), 4, "path")
    return parted.groupBy("part").agg(F.count("*").alias("n"), F.sum("pred").alias("work"))


_SKEW = f"""
p AS ({_PRED}),
q AS (SELECT pred, row_number() OVER (ORDER BY src, dst) - 1 AS pos, coalesce(sum(pred) OVER (ORDER BY src, dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead, sum(pred) OVER () AS total, count(*) OVER () AS n FROM p),
parts AS (SELECT 'even' AS split, pos * 8 // n AS part, pred FROM q UNION ALL SELECT 'predicted', least(ahead * 8 // total, 7), pred FROM q),
work AS (SELECT split, part, sum(pred) AS w FROM parts GROUP BY 1, 2)
"""


@query(sql(COP, ctes.SYM, _SKEW, select="SELECT split, count(*) AS parts, CAST(max(w) AS BIGINT) AS max_pred, round(avg(w), 6) AS mean_pred, round(max(w) / avg(w), 6) AS skew FROM work GROUP BY 1"))
def part_skew(spark, sf_dir):
    """How unequal parts are, split by number and by predicted work."""
    g = load(part_copurchase, spark, sf_dir)
    level = [x for x in explore(g, 3) if x.k == 2][0]
    rows = materialise(balance.predict(Level(level.df, 2, True)).select("path", "pred"), "pred")
    even = balance.skew(balance.split_even(rows, 8, "path")).withColumn("split", F.lit("even"))
    return even.unionByName(balance.skew(balance.split_predicted(rows, 8, "path")).withColumn("split", F.lit("predicted")))
