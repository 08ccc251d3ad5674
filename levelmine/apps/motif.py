"""Motif counting: vertex-induced subgraphs of k vertices by shape."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.explore.loop import explore
from levelmine.graph.model import PropertyGraph
from levelmine.pattern.classify import pattern_counts
from levelmine.pattern.exact import canonical
from levelmine.pattern.names import name_of
from levelmine.session import materialise
from levelmine.store import packed


def motifs(graph: PropertyGraph, k: int, labelled: bool = False, engine: str = "exact", fuse_last: bool = True, strategy: str | None = None) -> DataFrame:
    """(code, frequency). fuse_last: the last level flows into the counts and is never stored."""
    for level in explore(graph, k, strategy=strategy):  # noqa: B007
        pass
    if level.k < k:
        raise ValueError("the exploration ended early")
    rows = level.df if fuse_last else materialise(level.df, "last")
    return pattern_counts(rows, labelled, engine)


def motifs_3(cells: DataFrame, blocks: int) -> DataFrame:
    """(code, frequency) of three vertices from packed edges, without a row for any of the sets: two edges with a common end
    are a chain or one of the three corners of a triangle."""
    spark, n = cells.sparkSession, packed.triangles(cells, blocks)
    wedges = packed.degrees(cells).agg(F.coalesce(F.sum(F.expr("deg * (deg - 1) div 2")), F.lit(0))).first()[0]
    counts = [(canonical((1, 1, 1), bits)[0], k) for bits, k in ((3, wedges - 3 * n), (7, n)) if k]
    return spark.createDataFrame(counts, "code string, frequency long")


def named(counts: DataFrame) -> DataFrame:
    """(motif, frequency): shapes without a name keep their code."""
    name = F.udf(lambda c: name_of(c) or c, "string")  # over the few patterns only
    return counts.select(name("code").alias("motif"), "frequency")


def match(graph: PropertyGraph, code: str, k: int, labelled: bool = False) -> DataFrame:
    """(path) of all vertex-induced instances of the pattern with this canonical code."""
    from levelmine.explore.loop import embeddings
    from levelmine.pattern.classify import classify

    rows = embeddings(graph, k)
    if not labelled:
        rows = rows.withColumn("labels", F.array_repeat(F.lit(1), k))
    good = classify(rows.select("labels", "bits").distinct(), "exact").filter(F.col("code") == code)
    return rows.join(good, ["labels", "bits"], "left_semi").select("path")
