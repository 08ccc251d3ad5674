"""Frequent subgraph mining: edge-induced levels, pruned after each round to the embeddings of frequent patterns."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.explore import edge
from levelmine.explore.loop import numbered_links
from levelmine.explore.vertex import Level
from levelmine.graph.model import PropertyGraph
from levelmine.plans.planner import plan
from levelmine.session import materialise
from levelmine.support import mni


def _supports(level: DataFrame, known: mni.Forms, support: int, measure: str, exact: bool) -> DataFrame:
    if measure == "count":
        return mni.count(level, known).withColumn("capped", F.lit(False))
    if measure != "mni":
        raise ValueError("measures: mni, count")
    return mni.exact(level, known).withColumn("capped", F.lit(False)) if exact else mni.capped(level, support, known)


def _reaches(support: int, strict: bool):
    return F.col("mni") > support if strict else F.col("mni") >= support


def _edge_supports(graph: PropertyGraph, support: int, measure: str, exact: bool, strict: bool) -> tuple[DataFrame, mni.Forms, DataFrame]:
    """The one-edge level, its forms, and (code, mni, capped, embeddings) of the frequent ones."""
    level = materialise(edge.init(graph, carry=False).df, "fsm1")
    known = mni.forms(level)
    good = _supports(level, known, support, measure, exact).filter(_reaches(support, strict)).join(known.counts(), "code")
    return level, known, materialise(good, "frequent1")


def _only(graph: PropertyGraph, level: DataFrame, known: mni.Forms, good: DataFrame) -> PropertyGraph:
    kept = known.joined(level).join(good, "code", "left_semi").select(F.col("eids")[0].alias("eid"))
    return PropertyGraph(graph.vertices, materialise(graph.edges.join(kept, "eid", "left_semi").select("eid", "src", "dst", "elabel"), "frequent"))


def frequent_edges(graph: PropertyGraph, support: int, strict: bool = False) -> PropertyGraph:
    """The graph without the edges of infrequent one-edge patterns."""
    return _only(graph, *_edge_supports(graph, support, "mni", True, strict))


def fsm(graph: PropertyGraph, n_edges: int, support: int, measure: str = "mni", exact: bool = True, prune: bool = True, strict: bool = False, strategy: str | None = None) -> DataFrame:
    """(pattern, n_edges, mni, embeddings, capped) of every frequent pattern of 1..n_edges edges.

    The count measure is not anti-monotone, so it is never pruned. Where a vertex has more edges than a row should hold,
    levels are grown by joins with the edges and a distinct (strategy: 'carry' or 'distinct' to choose).
    """
    prune = prune and measure == "mni"
    found = []

    def tell(good: DataFrame, size: int) -> None:
        found.append(good.select(F.col("code").alias("pattern"), F.lit(size).alias("n_edges"), F.col("mni").cast("long").alias("mni"), "embeddings", "capped"))

    first, known, good = _edge_supports(graph, support, measure, exact, strict)
    tell(good, 1)
    if n_edges == 1 or good.isEmpty():
        return found[0]
    if prune:
        graph = _only(graph, first, known, good)
    carry = plan(graph, n_edges, strategy).carry if strategy != "distinct" else False
    level = edge.init(graph, carry=carry)
    for size in range(2, n_edges + 1):
        last = size == n_edges
        if not carry:
            rows = materialise(edge.expand(graph, level, unique="distinct").df, f"fsm{size}")
        elif last:
            rows = materialise(edge.expand(graph, level, last=True).df, f"fsm{size}")
        else:
            rows = numbered_links(edge.children(graph, level), f"fsm{size}")
        known = mni.forms(rows)
        good = _supports(rows, known, support, measure, exact).filter(_reaches(support, strict)).join(known.counts(), "code")
        good = materialise(good, f"frequent{size}")
        tell(good, size)
        if last or good.isEmpty():
            break
        if prune:
            kept = known.rows.join(good, "code", "left_semi").select("labels", "bits", "form")
            rows = mni.formed(rows).join(F.broadcast(kept) if known.few else kept, ["labels", "bits", "form"], "left_semi").drop("form")
        level = edge.attached(graph, level, rows) if carry else Level(rows, size)
    return reduce(DataFrame.unionByName, found)
