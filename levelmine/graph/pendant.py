"""Trees that hang on a graph, folded into the vertices that they hang on.

A vertex with one neighbour is cut off, and so on with what remains, until no such vertex is left (or `ROUNDS` have passed,
which changes no result). Each vertex keeps `sets`: entry i says how many connected sets of i + 1 vertices there are of it
and the trees cut off below it, with the vertex itself in them. A vertex's sets are the product of what each branch gives,
nothing or one of its sets, as polynomials cut at the size asked for.

Every connected set of the graph lies within one tree, where its highest vertex counts it, or has a connected part in what
remains: one such part stands for as many sets as the product of its vertices' `sets` says. What remains of a tree is one
vertex. The label of a vertex that remains tells its `sets`, so an exploration of them counts parts by labels alone.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelmine.graph.model import PropertyGraph
from levelmine.graph.numbering import numbered
from levelmine.session import materialise

ROUNDS = 64


def _times(a: Column, b: Column, k: int) -> Column:
    """Product of two polynomials of k coefficients, cut at k."""
    return F.array(*[functools.reduce(Column.__add__, [a[j] * b[i - j] for j in range(i + 1)]) for i in range(k)])


def _product(lists: Column | str, k: int) -> Column:
    return F.aggregate(lists, _alone(k), lambda a, b: _times(a, b, k))


def _alone(k: int) -> Column:
    return F.array(*[F.lit(int(i == 0)).cast("long") for i in range(k)])


def _marked(edges: DataFrame) -> DataFrame:
    """Edges with leaf and parent where one end has no other edge; of an edge alone the greater end is the leaf."""
    deg = edges.select(F.explode(F.array("src", "dst")).alias("u")).groupBy("u").agg(F.count("*").alias("n"))
    at = edges.join(deg.toDF("src", "n_src"), "src").join(deg.toDF("dst", "n_dst"), "dst")
    either = lambda of_dst, of_src: F.when(F.col("n_dst") == 1, F.col(of_dst)).when(F.col("n_src") == 1, F.col(of_src))
    return at.select("eid", "src", "dst", "elabel", either("dst", "src").alias("leaf"), either("src", "dst").alias("parent"))


@dataclass
class Folded:
    """graph: what remains. inside: for each size, the sets wholly among what was cut off. kinds(label, sets), or None if
    nothing was cut off."""

    graph: PropertyGraph
    k: int
    inside: list[int]
    kinds: DataFrame | None

    def stands_for(self, parts: DataFrame, size: int) -> list[int]:
        """parts(labels): connected sets of `size` vertices of what remains. How many sets of size, size + 1, ... k vertices
        they stand for."""
        if self.kinds is None:
            return [parts.count()]
        forms = parts.groupBy(F.array_sort("labels").alias("labels")).agg(F.count("*").alias("n"))
        at = forms.select("labels", "n", F.explode("labels").alias("label")).join(self.kinds, "label")
        each = at.groupBy("labels", "n").agg(_product(F.collect_list("sets"), self.k).alias("sets"))
        return [x or 0 for x in each.agg(*[F.sum(F.col("n") * F.col("sets")[i]) for i in range(self.k - size + 1)]).first()]


def fold(graph: PropertyGraph, k: int) -> Folded:
    """Connected sets of up to k vertices are to be counted."""
    edges, held, cut, inside = graph.edges, None, [], [0] * k
    for _ in range(ROUNDS):
        marked = materialise(_marked(edges), "marked")
        leaves = marked.filter("leaf is not null").select("leaf", "parent")
        if leaves.isEmpty():
            break
        edges = marked.filter("leaf is null").select("eid", "src", "dst", "elabel")
        if held is None:
            leaves = leaves.withColumn("sets", _alone(k))
        else:
            leaves = leaves.join(held, F.col("leaf") == F.col("id"), "left").select("leaf", "parent", F.coalesce("sets", _alone(k)).alias("sets"))
        leaves = materialise(leaves, "leaves")
        inside = [a + b for a, b in zip(inside, leaves.agg(*[F.sum(F.col("sets")[i]) for i in range(k)]).first(), strict=True)]
        cut.append(leaves.select(F.col("leaf").alias("id")))
        branch = F.slice(F.concat(F.array(F.lit(1).cast("long")), "sets"), 1, k)
        parts = leaves.select(F.col("parent").alias("id"), branch.alias("sets"))
        if held is not None:
            parts = parts.unionByName(held.join(cut[-1], "id", "left_anti"))
        held = materialise(parts.groupBy("id").agg(_product(F.collect_list("sets"), k).alias("sets")), "held")
    if not cut:
        return Folded(graph, k, inside, None)
    left = graph.vertices.join(functools.reduce(DataFrame.unionByName, cut), "id", "left_anti").join(held, "id", "left")
    left = materialise(left.select("id", "name", F.coalesce("sets", _alone(k)).alias("sets")), "left")
    kinds = numbered(left.select("sets").distinct(), "sets", name="label", start=1).select(F.col("label").cast("int").alias("label"), "sets")
    vertices = materialise(left.join(kinds, "sets").select("id", "label", "name"), "vertices")
    return Folded(PropertyGraph(vertices, edges), k, inside, kinds)
