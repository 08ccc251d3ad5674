"""Cliques of k vertices. The filter "adjacent to every member" is carried as the array of vertices that pass it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.graph.model import PropertyGraph
from levelmine.session import materialise


def upward(graph: PropertyGraph, oriented: bool = False) -> DataFrame:
    """(id, up): neighbours that come later: by id, or by (degree, id), which bounds a hub's list by sqrt(2 E)."""
    if not oriented:
        return graph.edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("up"))
    deg = graph.degrees()
    e = graph.edges.join(deg.toDF("src", "ds"), "src").join(deg.toDF("dst", "dd"), "dst")
    swap = F.struct("dd", "dst") < F.struct("ds", "src")
    low, high = F.when(swap, F.col("dst")).otherwise(F.col("src")), F.when(swap, F.col("src")).otherwise(F.col("dst"))
    return e.select(low.alias("id"), high.alias("v")).groupBy("id").agg(F.sort_array(F.collect_list("v")).alias("up"))


def _grown(up: DataFrame, k: int) -> DataFrame:
    """(path, cand) of all cliques of k vertices with the later vertices adjacent to all of them."""
    rows = up.select(F.array("id").alias("path"), F.col("up").alias("cand"))
    for size in range(2, k + 1):
        each = rows.select("path", "cand", F.explode("cand").alias("v"))
        both = each.join(up, F.col("v") == F.col("id"), "left")
        rows = both.select(F.concat("path", F.array("v")).alias("path"), F.array_intersect("cand", F.coalesce("up", F.array().cast("array<bigint>"))).alias("cand"))
        if size < k:
            rows = rows.filter(F.size("cand") > 0)
    return rows


def cliques(graph: PropertyGraph, k: int, oriented: bool = True) -> DataFrame:
    """(path): each clique once, its vertices in rising order."""
    up = materialise(upward(graph, oriented), "upward")
    if k == 1:
        return graph.vertices.select(F.array("id").alias("path"))
    last = _grown(up, k - 1).filter(F.size("cand") > 0).select("path", F.explode("cand").alias("v"))
    return last.select(F.array_sort(F.concat("path", F.array("v"))).alias("path"))


def clique_count(graph: PropertyGraph, k: int, oriented: bool = True) -> DataFrame:
    """(n): cliques of k vertices, counted one level early by the sizes of the candidate sets."""
    up = materialise(upward(graph, oriented), "upward")
    return _grown(up, k - 1).agg(F.coalesce(F.sum(F.size("cand").cast("long")), F.lit(0).cast("long")).alias("n"))
