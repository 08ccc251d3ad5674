"""Brute force: all connected k-subsets by self-joins along edges, as sorted arrays, made unique at the end."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.graph.model import PropertyGraph


def subsets(graph: PropertyGraph, k: int) -> DataFrame:
    """(verts)."""
    rows = graph.vertices.select(F.array("id").alias("verts"))
    for _ in range(k - 1):
        near = graph.sym.select("u", "v")
        rows = rows.select("verts", F.explode("verts").alias("u")).join(near, "u").filter(~F.array_contains("verts", F.col("v")))
        rows = rows.select(F.array_sort(F.concat("verts", F.array("v"))).alias("verts")).distinct()
    return rows
