"""All queries of the engine, by key, with their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.apps import motif
from levelmine.operators import exploration, inputs, mining, relational, storing, streams  # noqa: F401  they enter their queries
from levelmine.operators.registry import ORACLES, QUERIES
from levelmine.session import ship_library
from levelmine.sources.graphs import load, vector_knn

SMOKE_DIR = "/root/testdata/sf0.001"


def entry(spark: SparkSession) -> DataFrame:
    """Named motifs of three and four vertices of the vector neighbour graph."""
    ship_library(spark)
    graph = load(vector_knn, spark, SMOKE_DIR)
    counts = [motif.named(motif.motifs(graph, k)).withColumn("k", F.lit(k)) for k in (3, 4)]
    return counts[0].unionByName(counts[1]).select("k", "motif", "frequency")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
