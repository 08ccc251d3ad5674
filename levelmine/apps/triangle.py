"""Triangle counting: common neighbours per edge, by joins of edges, or on an orientation by degree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.apps.clique import upward
from levelmine.graph.model import PropertyGraph


def _common(graph: PropertyGraph, oriented: bool) -> DataFrame:
    """(u, v, common): later vertices adjacent to both ends of an edge."""
    up = upward(graph, oriented)
    e = up.select(F.col("id").alias("u"), "up", F.explode("up").alias("v"))
    return e.join(up.toDF("w", "up2"), F.col("v") == F.col("w")).select("u", "v", F.array_intersect("up", "up2").alias("common"))


def triangle_rows(graph: PropertyGraph) -> DataFrame:
    """(a, b, c) by a chain of equi-joins of edges."""
    e = graph.edges.select("src", "dst")
    ab, bc, ac = e.toDF("a", "b"), e.toDF("b", "c"), e.toDF("a", "c")
    return ab.join(bc, "b").join(ac, ["a", "c"]).select("a", "b", "c")


def triangles(graph: PropertyGraph, method: str = "intersect") -> DataFrame:
    """(n)."""
    if method == "join":
        return triangle_rows(graph).agg(F.count("*").alias("n"))
    if method not in ("intersect", "oriented"):
        raise ValueError("methods: intersect, oriented, join")
    return _common(graph, method == "oriented").agg(F.coalesce(F.sum(F.size("common").cast("long")), F.lit(0).cast("long")).alias("n"))


def per_vertex(graph: PropertyGraph) -> DataFrame:
    """(id, triangles, clustering) of every vertex with an edge."""
    corner = F.explode(F.concat(F.array("u", "v"), F.array("x"))).alias("id")
    each = _common(graph, True).select("u", "v", F.explode("common").alias("x")).select(corner).groupBy("id").agg(F.count("*").alias("t"))
    both = graph.degrees().join(each, "id", "left").withColumn("t", F.coalesce("t", F.lit(0).cast("long")))
    return both.select("id", F.col("t").alias("triangles"), F.round(F.when(F.col("deg") > 1, 2 * F.col("t") / (F.col("deg") * (F.col("deg") - 1))).otherwise(0.0), 6).alias("clustering"))
