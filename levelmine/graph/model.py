"""Property graphs as two DataFrames: undirected, simple, with int labels of 1 or more on vertices and edges."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.graph.numbering import numbered
from levelmine.session import materialise


@dataclass
class PropertyGraph:
    """vertices(id long, label int, name string), edges(eid long, src long, dst long, elabel int) with src < dst."""

    vertices: DataFrame
    edges: DataFrame

    @classmethod
    def from_pairs(cls, pairs: DataFrame, labels: DataFrame | None = None, isolated: bool = False) -> PropertyGraph:
        """pairs(src, dst[, elabel]): loops, duplicates, directions and nulls are normalised away.

        labels(id, label[, name]): a missing or null label is 1; a label below 1 is refused, for a zero would make an
        edge's weight vanish. isolated: keep labelled vertices without an edge.
        """
        elabel = F.coalesce(F.min("elabel"), F.lit(1)).cast("int") if "elabel" in pairs.columns else F.lit(1).cast("int")
        one = pairs.filter("src is not null and dst is not null and src <> dst")
        one = one.withColumns({"src": F.least("src", "dst").cast("long"), "dst": F.greatest("src", "dst").cast("long")})
        edges = numbered(one.groupBy("src", "dst").agg(elabel.alias("elabel")), "src", "dst", name="eid").select("eid", "src", "dst", "elabel")
        ends = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        if labels is None:
            vertices = ends.select("id", F.lit(1).cast("int").alias("label"), F.lit(None).cast("string").alias("name"))
        else:
            name = F.max("name") if "name" in labels.columns else F.lit(None).cast("string")
            known = labels.filter("id is not null").groupBy(F.col("id").cast("long").alias("id")).agg(F.min("label").cast("int").alias("label"), name.alias("name"))
            vertices = ends.join(known, "id", "full" if isolated else "left").withColumn("label", F.coalesce("label", F.lit(1)))
            vertices = vertices.withColumn("label", F.when(F.col("label") >= 1, F.col("label")).otherwise(F.raise_error(F.lit("labels start at 1")).cast("int")))
        return cls(materialise(vertices.select("id", "label", "name"), "vertices"), edges)

    @cached_property
    def sym(self) -> DataFrame:
        """(u, v, eid, elabel): every edge in both directions."""
        there = self.edges.select(F.col("src").alias("u"), F.col("dst").alias("v"), "eid", "elabel")
        return there.unionByName(there.select(F.col("v").alias("u"), F.col("u").alias("v"), "eid", "elabel"))

    def adjacency(self, chunk: int = 4096) -> DataFrame:
        """(id, chunk, nbrs sorted, deg): sparse adjacency; a hub's list is cut so that no row grows with its degree."""
        per = F.floor((F.row_number().over(_by("u", "v")) - 1) / chunk).cast("int")
        deg = self.degrees()
        cut = self.sym.select("u", "v", per.alias("chunk")).groupBy("u", "chunk").agg(F.sort_array(F.collect_list("v")).alias("nbrs"))
        return cut.join(deg, F.col("u") == F.col("id")).select("id", "chunk", "nbrs", "deg")

    @cached_property
    def _lists(self) -> DataFrame:
        labelled = self.sym.join(self.vertices.select(F.col("id").alias("v"), F.col("label").alias("l")), "v")
        lists = labelled.groupBy("u").agg(F.sort_array(F.collect_list(F.struct("v", "l"))).alias("nbrs"))
        return materialise(lists.join(self.vertices.select(F.col("id").alias("u"), "label"), "u").select(F.col("u").alias("id"), "label", "nbrs"), "neighbours")

    def neighbours(self) -> DataFrame:
        """(id, label, nbrs array<struct<v, l>>): whole lists, for graphs whose degrees fit a row; written once, as
        every round of an exploration joins them."""
        return self._lists

    def degrees(self) -> DataFrame:
        return self.sym.groupBy(F.col("u").alias("id")).agg(F.count("*").alias("deg"))

    def stats(self) -> DataFrame:
        """n_vertices, n_edges, n_labels, avg_degree, max_degree of vertices with an edge or a label."""
        size = self.vertices.agg(F.count("*").alias("n_vertices"), F.countDistinct("label").alias("n_labels"))
        deg = self.degrees().agg(F.coalesce(F.max("deg"), F.lit(0)).alias("max_degree"), F.coalesce(F.sum("deg"), F.lit(0)).alias("ends"))
        n = F.col("n_vertices")
        return size.join(deg).select("n_vertices", (F.col("ends") / 2).cast("long").alias("n_edges"), "n_labels", F.round(F.when(n > 0, F.col("ends") / n), 6).alias("avg_degree"), "max_degree")

    def max_degree(self) -> int:
        return self.degrees().agg(F.max("deg")).first()[0] or 0

    def induced(self, vertex_set: DataFrame) -> PropertyGraph:
        """The subgraph on vertex_set(id)."""
        chosen = vertex_set.select("id").distinct()
        edges = self.edges.join(chosen.withColumnRenamed("id", "src"), "src", "left_semi").join(chosen.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return PropertyGraph(self.vertices.join(chosen, "id", "left_semi"), edges.select("eid", "src", "dst", "elabel"))

    def relabelled(self, labels: DataFrame) -> PropertyGraph:
        kept = self.vertices.drop("label").join(labels.select("id", F.col("label").cast("int").alias("label")), "id", "left")
        return PropertyGraph(kept.select("id", F.coalesce("label", F.lit(1)).alias("label"), "name"), self.edges)


def _by(key: str, order: str):
    from pyspark.sql import Window

    return Window.partitionBy(key).orderBy(order)
