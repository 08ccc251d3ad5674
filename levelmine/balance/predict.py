"""Work per embedding, predicted before it is done, and splits of a level into parts of equal number or equal work."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.explore.vertex import Level
from levelmine.graph.model import PropertyGraph
from levelmine.graph.numbering import numbered, running


def predict(level: Level) -> DataFrame:
    """Adds pred: the number of candidates, the merged neighbour lists without the path itself. Exact."""
    own = "path" if "path" in level.df.columns else "eids"
    return level.df.withColumn("pred", F.size(F.array_except(F.map_keys("ext"), F.col(own))).cast("long"))


def degree_bound(graph: PropertyGraph, level: Level) -> DataFrame:
    """(path, pred): the sum of the degrees, a cheap upper bound that needs no merging."""
    deg = graph.degrees()
    each = level.df.select("path", F.explode("path").alias("id")).join(deg, "id")
    return each.groupBy("path").agg(F.sum("deg").alias("pred"))


def split_even(level: DataFrame, parts: int, *order: str) -> DataFrame:
    """Adds pos and part: runs of equal length in the given order."""
    rows = numbered(level, *order)
    n = rows.count()
    return rows.withColumn("part", F.floor(F.col("pos") * parts / max(1, n)).cast("int"))


def split_predicted(level: DataFrame, parts: int, *order: str) -> DataFrame:
    """level with pred: adds pos and part: runs of equal predicted work, by a running sum in two passes."""
    rows = numbered(level, *order)
    total = rows.agg(F.sum("pred")).first()[0] or 1
    ahead = running(rows, "pos", "pred", F.sum, lambda a, b: a + b, "ahead")
    part = F.floor(F.coalesce("ahead", F.lit(0)) * parts / total)
    return ahead.withColumn("part", F.least(part, F.lit(parts - 1)).cast("int")).drop("ahead")


def dealt(level: Level, parts: int, predicted: bool) -> Level:
    """The level's rows in parts of equal number, or of equal predicted work, a task each. Only keys and work are sorted."""
    key = "path" if "path" in level.df.columns else "eids"
    slim = predict(level).select("pos", F.col(key).alias("key"), "pred").withColumnRenamed("pos", "of")
    split = (split_predicted if predicted else split_even)(slim, parts, "key").select("of", "part")
    both = level.df.join(split, F.col("pos") == F.col("of")).drop("of")
    return Level(both.repartitionById(parts, F.col("part")).drop("part"), level.k, True)


def skew(parted: DataFrame) -> DataFrame:
    """(parts, max_pred, mean_pred, skew): how unequal the parts' predicted work is."""
    per = parted.groupBy("part").agg(F.sum("pred").alias("w"))
    return per.agg(F.count("*").alias("parts"), F.max("w").alias("max_pred"), F.round(F.avg("w"), 6).alias("mean_pred"), F.round(F.max("w") / F.avg("w"), 6).alias("skew"))
