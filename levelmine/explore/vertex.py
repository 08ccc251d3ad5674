"""Vertex-induced exploration: every connected subgraph of k vertices once, as a path in canonical order.

A level has path, labels, bits (upper triangle of the adjacency matrix, row after row of the new vertex's adjacency to
those before it) and, if it is to be grown by the carry strategy, pos, its number, and ext: a map from every vertex
adjacent to the path to its label and the mask of positions it is adjacent to. Growing joins ext with the new vertex's
neighbours alone, and the canonical test needs nothing else. The rejoin strategy carries no map: it joins every position
anew.

What is kept of a level are links alone: pos, the parent's pos, the new vertex with its label and mask. `attached` makes
the level of its links: the children meet their own vertices' lists first, and then, by parent, the one row that holds
the prefix and its candidates.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelmine.explore.canonical import may_follow, suffix_max
from levelmine.graph.model import PropertyGraph

#: ext values hold the mask in the low bits, the label above.
MASK_BITS = 8
K_MAX = 8
#: A user's filter: a column, or a function of (path, candidate vertex).
EFilter = Column | Callable[[Column, Column], Column] | None

_MASK = (1 << MASK_BITS) - 1


@dataclass
class Level:
    df: DataFrame
    k: int
    carried: bool = False


def _as_ext(nbrs: Column, position: int) -> Column:
    entry = lambda n: F.struct(n["v"], F.shiftleft(n["l"].cast("long"), MASK_BITS).bitwiseOR(F.lit(1 << position)))
    return F.map_from_entries(F.transform(nbrs, entry))


def merged(a: Column, b: Column) -> Column:
    return F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)).bitwiseOR(F.coalesce(y, F.lit(0))))


def bit_base(k: int) -> int:
    """Where the bits of the vertex at position k (from 0) begin."""
    return k * (k - 1) // 2


def init(graph: PropertyGraph, depth: int = 1, carry: bool = True) -> Level:
    """Level 1 (vertices) or 2 (edges)."""
    if depth == 1:
        base = graph.vertices.select("id", "label")
        if carry:
            lists = graph.neighbours().select(F.col("id").alias("u"), "nbrs")
            base = base.join(lists, F.col("id") == F.col("u"), "left")
            ext = F.coalesce(_as_ext(F.col("nbrs"), 0), F.create_map().cast("map<bigint,bigint>"))
        df = base.select(F.array("id").alias("path"), F.array("label").alias("labels"), F.lit(0).cast("long").alias("bits"), *([ext.alias("ext"), F.col("id").alias("pos")] if carry else []))
        return Level(df, 1, carry)
    if not carry:
        lab = graph.vertices.select("id", "label")
        e = graph.edges.join(lab.toDF("src", "ls"), "src").join(lab.toDF("dst", "ld"), "dst")
        return Level(e.select(F.array("src", "dst").alias("path"), F.array("ls", "ld").alias("labels"), F.lit(1).cast("long").alias("bits")), 2)
    lists = graph.neighbours()
    a, b = lists.toDF("src", "ls", "ns"), lists.toDF("dst", "ld", "nd")
    e = graph.edges.select("eid", "src", "dst").join(a, "src").join(b, "dst")
    ext = merged(_as_ext(F.col("ns"), 0), _as_ext(F.col("nd"), 1))
    return Level(e.select(F.array("src", "dst").alias("path"), F.array("ls", "ld").alias("labels"), F.lit(1).cast("long").alias("bits"), ext.alias("ext"), F.col("eid").alias("pos")), 2, True)


def _allowed(efilter: EFilter, path: Column, v: Column) -> Column:
    if efilter is None:
        return F.lit(True)
    return efilter(path, v) if callable(efilter) and not isinstance(efilter, Column) else efilter


def extensions(level: Level, efilter: EFilter = None, above: Column | None = None) -> Column:
    """The entries of ext that grow a canonical child. above: a column with the suffix maxima, else worked out in place."""
    path = F.col("path")
    above = suffix_max(path, level.k) if above is None else above
    return F.map_filter("ext", lambda v, x: may_follow(path, above, v, x.bitwiseAND(_MASK)) & _allowed(efilter, path, v))


def _grown(level: Level, v: Column, value: Column) -> list[Column]:
    mask = value.bitwiseAND(_MASK)
    return [
        F.concat("path", F.array(v)).alias("path"),
        F.concat("labels", F.array(F.shiftright(value, MASK_BITS).cast("int"))).alias("labels"),
        F.col("bits").bitwiseOR(F.shiftleft(mask, bit_base(level.k))).alias("bits"),
    ]


def expand(graph: PropertyGraph, level: Level, efilter: EFilter = None, last: bool = False, strategy: str | None = None) -> Level:
    """The next level; last: it will not be grown further, so it needs no ext and no join."""
    if level.k >= K_MAX:
        raise ValueError(f"embeddings have at most {K_MAX} vertices")
    if strategy == "rejoin" or not level.carried:
        return _rejoined(graph, level, efilter)
    # a column of its own, so that it is worked out once a row and not once a candidate
    rows = level.df.withColumn("above", suffix_max(F.col("path"), level.k))
    rows = rows.select("path", "labels", "bits", "ext", F.explode(extensions(level, efilter, F.col("above"))).alias("v", "x"))
    grown = _grown(level, F.col("v"), F.col("x"))
    if last:
        return Level(rows.select(*grown), level.k + 1)
    lists = graph.neighbours().select("id", "nbrs")
    both = rows.join(lists, F.col("v") == F.col("id"))
    return Level(both.select(*grown, merged(F.col("ext"), _as_ext(F.col("nbrs"), level.k)).alias("ext")), level.k + 1, True)


LINK = "pos long, parent long, vert long, label int, mask long"


def children(level: Level, efilter: EFilter = None) -> DataFrame:
    """(parent, vert, label, mask): what tells the rows of the next level from their parents."""
    rows = level.df.withColumn("above", suffix_max(F.col("path"), level.k))
    rows = rows.select(F.col("pos").alias("parent"), F.explode(extensions(level, efilter, F.col("above"))).alias("vert", "x"))
    return rows.select("parent", "vert", F.shiftright("x", MASK_BITS).cast("int").alias("label"), F.col("x").bitwiseAND(_MASK).alias("mask"))


def attached(graph: PropertyGraph, parents: Level, links: DataFrame) -> Level:
    """The level whose links these are, with ext."""
    lists = graph.neighbours().select("id", "nbrs")
    own = links.join(lists, F.col("vert") == F.col("id")).select("pos", "parent", "vert", "label", "mask", "nbrs")
    above = parents.df.select(F.col("pos").alias("up"), "path", "labels", "bits", "ext")
    value = F.shiftleft(F.col("label").cast("long"), MASK_BITS).bitwiseOR(F.col("mask"))
    both = own.join(above, F.col("parent") == F.col("up"))
    ext = merged(F.col("ext"), _as_ext(F.col("nbrs"), parents.k))
    return Level(both.select(*_grown(parents, F.col("vert"), value), ext.alias("ext"), "pos"), parents.k + 1, True)


def with_ext(graph: PropertyGraph, rows: DataFrame, k: int) -> Level:
    """Rows of (path, labels, bits[, pos]) as a level with ext, from the lists of all their vertices."""
    out = rows
    for i in range(k):
        out = out.join(graph.neighbours().select(F.col("id").alias(f"id{i}"), F.col("nbrs").alias(f"n{i}")), F.col("path")[i] == F.col(f"id{i}"))
    ext = _as_ext(F.col("n0"), 0)
    for i in range(1, k):
        ext = merged(ext, _as_ext(F.col(f"n{i}"), i))
    return Level(out.select(*rows.columns, ext.alias("ext")), k, True)


def positions(graph: PropertyGraph, level: Level) -> DataFrame:
    """(path, labels, bits, v, mask): every vertex adjacent to a path, by joining all positions."""
    at = level.df.select("path", "labels", "bits", F.posexplode("path").alias("i", "u"))
    near = at.join(graph.sym.select("u", "v"), "u").select("path", "labels", "bits", "v", F.expr("shiftleft(1, i)").alias("bit"))
    return near.groupBy("path", "labels", "bits", "v").agg(F.bit_or("bit").cast("long").alias("mask"))


def _rejoined(graph: PropertyGraph, level: Level, efilter: EFilter) -> Level:
    path, v, mask = F.col("path"), F.col("v"), F.col("mask")
    rows = positions(graph, level).filter(may_follow(path, suffix_max(path, level.k), v, mask) & _allowed(efilter, path, v))
    rows = rows.join(graph.vertices.select(F.col("id").alias("v"), F.col("label").alias("l")), "v")
    value = F.shiftleft(F.col("l").cast("long"), MASK_BITS).bitwiseOR(mask)
    return Level(rows.select(*_grown(level, v, value)), level.k + 1)


def candidates(graph: PropertyGraph, level: Level) -> DataFrame:
    """(path, v): the union of the neighbourhoods, the path itself left out."""
    if level.carried:
        return level.df.select("path", F.explode(F.array_except(F.map_keys("ext"), F.col("path"))).alias("v"))
    return positions(graph, level).filter(~F.array_contains("path", F.col("v"))).select("path", "v")
