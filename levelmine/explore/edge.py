"""Edge-induced exploration: every connected set of k edges once, in canonical order of edge numbers.

The canonical test is that of vertices on the line graph, which is never built: the edges next to a path are those at
its endpoints, and a hub's edges are joined by the hub. A level has eids, verts (in order of first appearance), labels,
bits (of the path's own edges alone), elabels (bit and label of each edge, by bit), and, if it is to be grown by carrying,
pos and ext: edge -> (mask of path positions it touches, ends, label). Written rows have no ext: they name their parent and
the new edge's ends, and `attached` joins what the parent holds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelmine.explore.canonical import may_follow, suffix_max
from levelmine.explore.vertex import EFilter, Level, _allowed
from levelmine.graph.model import PropertyGraph


def incident(graph: PropertyGraph) -> DataFrame:
    """(id, inc): each vertex's edges as a map eid -> struct(m, s, d, l)."""
    entry = F.struct("eid", F.struct(F.lit(0).alias("m"), F.col("src").alias("s"), F.col("dst").alias("d"), F.col("elabel").alias("l")).alias("e"))
    ends = graph.edges.select(F.explode(F.array("src", "dst")).alias("id"), entry.alias("entry"))
    return ends.groupBy("id").agg(F.map_from_entries(F.sort_array(F.collect_list("entry"))).alias("inc"))


def _with(ext: Column, inc: Column, position: int) -> Column:
    def one(_, a: Column, b: Column) -> Column:
        known = F.coalesce(a, b)
        mask = F.coalesce(a["m"], F.lit(0)).bitwiseOR(F.when(b.isNotNull(), 1 << position).otherwise(0))
        return F.struct(mask.alias("m"), known["s"].alias("s"), known["d"].alias("d"), known["l"].alias("l"))

    return F.map_zip_with(ext, inc, one)


def init(graph: PropertyGraph, carry: bool = True) -> Level:
    """Each edge is an embedding of size 1."""
    lab = graph.vertices.select("id", "label")
    e = graph.edges.join(lab.toDF("src", "ls"), "src").join(lab.toDF("dst", "ld"), "dst")
    cols = [F.array("eid").alias("eids"), F.array("src", "dst").alias("verts"), F.array("ls", "ld").alias("labels"), F.lit(1).cast("long").alias("bits"), F.array(F.struct(F.lit(0).alias("b"), F.col("elabel").alias("l"))).alias("elabels")]
    if carry:
        inc = incident(graph)
        e = e.join(inc.toDF("src", "is"), "src").join(inc.toDF("dst", "id_"), "dst")
        empty = F.map_filter("is", lambda k, v: F.lit(False))
        cols += [_with(_with(empty, F.col("is"), 0), F.col("id_"), 0).alias("ext"), F.col("eid").alias("pos")]
    return Level(e.select(*cols), 1, carry)


def extensions(level: Level, efilter: EFilter = None, above: Column | None = None) -> Column:
    path = F.col("eids")
    above = suffix_max(path, level.k) if above is None else above
    return F.map_filter("ext", lambda v, x: may_follow(path, above, v, x["m"].cast("long")) & _allowed(efilter, path, v))


def _place(v: str) -> Column:
    """Position of a vertex from 0; that of the next new one where it is not there yet."""
    at = F.array_position("verts", F.col(v)).cast("int")
    return F.when(at > 0, at - 1).otherwise(F.size("verts"))


def _grown(rows: DataFrame) -> DataFrame:
    """rows: a level's columns and eid, s, d, el, ls, ld of one more edge that touches the path."""
    i, j = F.least(_place("s"), _place("d")), F.greatest(_place("s"), _place("d"))
    fresh = F.size("verts") == F.col("j")
    new, label = F.when(_place("s") == F.size("verts"), F.col("s")).otherwise(F.col("d")), F.when(_place("s") == F.size("verts"), F.col("ls")).otherwise(F.col("ld"))
    rows = rows.withColumns({"i": i, "j": j, "new": new, "lab": label})
    bit = F.expr("shiftleft(1L, cast(j * (j - 1) / 2 as int) + i)")
    keep = [c for c in rows.columns if c in ("ext", "is", "id_", "parent", "s", "d")]
    return rows.select(
        F.concat("eids", F.array("eid")).alias("eids"),
        F.when(fresh, F.concat("verts", F.array("new"))).otherwise(F.col("verts")).alias("verts"),
        F.when(fresh, F.concat("labels", F.array("lab"))).otherwise(F.col("labels")).alias("labels"),
        F.col("bits").bitwiseOR(bit).alias("bits"),
        F.array_sort(F.concat("elabels", F.array(F.struct(F.expr("cast(j * (j - 1) / 2 as int) + i").alias("b"), F.col("el").alias("l"))))).alias("elabels"),
        *keep,
    )


def _labelled(graph: PropertyGraph, rows: DataFrame) -> DataFrame:
    lab = graph.vertices.select("id", "label")
    return rows.join(lab.toDF("s", "ls"), "s").join(lab.toDF("d", "ld"), "d")


def expand(graph: PropertyGraph, level: Level, efilter: EFilter = None, last: bool = False, unique: str = "canonical") -> Level:
    """The next level. unique='distinct' grows by every adjacent edge and drops equal edge sets instead of testing."""
    if unique == "distinct" or not level.carried:
        return _distinct(graph, level, efilter)
    rows = level.df.withColumn("above", suffix_max(F.col("eids"), level.k))
    rows = rows.select(*level.df.columns, F.explode(extensions(level, efilter, F.col("above"))).alias("eid", "x"))
    rows = rows.select(*level.df.columns, "eid", F.col("x.s").alias("s"), F.col("x.d").alias("d"), F.col("x.l").alias("el"))
    rows = _labelled(graph, rows.drop("ext") if last else rows)
    if last:
        return Level(_grown(rows).drop("s", "d"), level.k + 1)
    inc = incident(graph)
    rows = rows.join(inc.toDF("s", "is"), "s").join(inc.toDF("d", "id_"), "d")
    grown = _grown(rows).withColumn("ext", _with(_with(F.col("ext"), F.col("is"), level.k), F.col("id_"), level.k)).drop("is", "id_", "s", "d")
    return Level(grown, level.k + 1, True)


def children(graph: PropertyGraph, level: Level, efilter: EFilter = None) -> DataFrame:
    """The rows of the next level without ext: parent, the new edge's ends s and d, eids, verts, labels, bits, elabels."""
    rows = level.df.withColumn("above", suffix_max(F.col("eids"), level.k))
    kept = ["eids", "verts", "labels", "bits", "elabels"]
    rows = rows.select(F.col("pos").alias("parent"), *kept, F.explode(extensions(level, efilter, F.col("above"))).alias("eid", "x"))
    rows = rows.select("parent", *kept, "eid", F.col("x.s").alias("s"), F.col("x.d").alias("d"), F.col("x.l").alias("el"))
    return _grown(_labelled(graph, rows))


def attached(graph: PropertyGraph, parents: Level, rows: DataFrame) -> Level:
    """Written children (with pos) as a level with ext."""
    inc = incident(graph)
    own = rows.join(inc.toDF("s", "is"), "s").join(inc.toDF("d", "id_"), "d")
    both = own.join(parents.df.select(F.col("pos").alias("up"), "ext"), F.col("parent") == F.col("up"))
    ext = _with(_with(F.col("ext"), F.col("is"), parents.k), F.col("id_"), parents.k)
    return Level(both.select("eids", "verts", "labels", "bits", "elabels", ext.alias("ext"), "pos"), parents.k + 1, True)


def _distinct(graph: PropertyGraph, level: Level, efilter: EFilter) -> Level:
    plain = level.df.drop("ext", "pos")
    near = graph.sym.select("u", "v", "eid", F.col("elabel").alias("el"))
    rows = plain.withColumn("u", F.explode("verts")).join(near, "u").filter(~F.array_contains("eids", F.col("eid")) & _allowed(efilter, F.col("eids"), F.col("eid")))
    rows = rows.select(*plain.columns, "eid", "el", F.least("u", "v").alias("s"), F.greatest("u", "v").alias("d"))
    rows = rows.withColumn("key", F.sort_array(F.concat("eids", F.array("eid")))).dropDuplicates(["key"]).drop("key")
    return Level(_grown(_labelled(graph, rows)).drop("s", "d"), level.k + 1)
