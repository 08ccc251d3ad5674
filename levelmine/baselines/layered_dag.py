"""Baseline A: levels kept as a layered DAG. Per pair of neighbouring positions only the distinct links are kept, so a
walk down the layers meets more than was put in, and each walk is checked again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.explore import vertex
from levelmine.explore.canonical import is_canonical
from levelmine.explore.vertex import Level
from levelmine.graph.model import PropertyGraph
from levelmine.session import materialise


class LayeredDag:
    """links[i]: distinct (a, b) of positions i and i + 1 of one level's embeddings."""

    def __init__(self, links: list[DataFrame], k: int):
        self.links, self.k = links, k

    @classmethod
    def build(cls, level: DataFrame, k: int) -> LayeredDag:
        pair = lambda i: level.select(F.element_at("path", i).alias("a"), F.element_at("path", i + 1).alias("b")).distinct()
        return cls([materialise(pair(i), "dag") for i in range(1, k)], k)

    def walk(self, graph: PropertyGraph) -> DataFrame:
        """(path): all walks, less those that are no canonical embedding of the graph."""
        rows = self.links[0].select(F.array("a", "b").alias("path"))
        for link in self.links[1:]:
            rows = rows.join(link, F.element_at("path", -1) == F.col("a")).select(F.concat("path", F.array("b")).alias("path"))
        rows = rows.filter(F.size(F.array_distinct("path")) == self.k)
        return checked(graph, rows, self.k)


def checked(graph: PropertyGraph, rows: DataFrame, k: int) -> DataFrame:
    """The paths that are canonical embeddings, by the adjacency of every pair of positions."""
    near = graph.sym.select("u", "v", F.lit(1).alias("hit"))
    rows = rows.select("path", F.array(F.lit(0).cast("long")).alias("masks"))
    for j in range(2, k + 1):
        mask = F.lit(0).cast("long")
        for i in range(1, j):
            ends = near.toDF("x", "y", "hit")
            rows = rows.join(ends, (F.element_at("path", i) == F.col("x")) & (F.element_at("path", j) == F.col("y")), "left").withColumn(f"h{i}", F.coalesce("hit", F.lit(0))).drop("x", "y", "hit")
            mask = mask + F.shiftleft(F.col(f"h{i}").cast("long"), i - 1)
        rows = rows.select("path", F.concat("masks", F.array(mask)).alias("masks"))
    return rows.filter(is_canonical(F.col("path"), F.col("masks"))).select("path")


def explore(graph: PropertyGraph, k: int) -> DataFrame:
    """(path) of level k: each level is stored as a DAG and read back by walking it."""
    level = vertex.init(graph, carry=False)
    for size in range(2, k + 1):
        grown = vertex.expand(graph, level, strategy="rejoin")
        if size == k:
            return LayeredDag.build(grown.df, size).walk(graph)
        paths = materialise(LayeredDag.build(grown.df, size).walk(graph), "walk")
        level = Level(materialise(grown.df.join(paths, "path", "left_semi"), "superstep"), size)
    return level.df.select("path")
