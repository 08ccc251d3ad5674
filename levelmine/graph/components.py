"""Connected components of an edge list by alternating star contractions, all in DataFrames.

Every round halves the depth of the trees at least; edges are cut from their lineage by a written table each round.
Joins are on one vertex against its minimum, so Spark may split a hub's rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.session import materialise, release


def _towards_least(edges: DataFrame, both_ways: bool) -> DataFrame:
    """Large star (both ways): a vertex hands its larger neighbours to the least of all.
    Small star: it hands its smaller neighbours and itself to the least."""
    pairs = edges.select("a", "b")
    if both_ways:
        pairs = pairs.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = pairs.groupBy("a").agg(F.min("b").alias("low")).select(F.col("a").alias("u"), F.least("a", "low").alias("low"))
    told = pairs.join(least, F.col("a") == F.col("u"))
    if both_ways:
        out = told.filter("b > a").select(F.col("b").alias("a"), F.col("low").alias("b"))
    else:
        out = told.select(F.col("b").alias("a"), F.col("low").alias("b")).unionByName(least.select(F.col("u").alias("a"), F.col("low").alias("b")))
    return out.filter("a > b").distinct()


def _mark(edges: DataFrame) -> tuple:
    """What tells whether the edges have changed: number, and sums of hashes."""
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    return tuple(row)


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(a, b) pairs -> (vertex, least): each vertex of an edge and the least vertex of its component."""
    now = materialise(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    mark = _mark(now)
    for _ in range(rounds):
        if not mark[0]:
            break
        before, now = now, materialise(_towards_least(_towards_least(now, True), False), "edges")
        release(before)
        was, mark = mark, _mark(now)
        if was == mark:
            break
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    stars = now.select(F.col("a").alias("vertex"), F.col("b").alias("least"))
    return stars.unionByName(now.select(F.col("b").alias("vertex"), F.col("b").alias("least")).distinct())
