"""Exploring a level part by part as a stream of files: a part is a micro-batch, the checkpoint a point to start again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.balance.predict import split_even
from levelmine.explore import vertex
from levelmine.explore.vertex import Level
from levelmine.graph.model import PropertyGraph
from levelmine.session import scratch_path


def expand_stream(graph: PropertyGraph, level: Level, parts: int) -> DataFrame:
    """The next level, one file of the present one a batch."""
    spark = graph.edges.sparkSession
    source, target = scratch_path(spark, "parts"), scratch_path(spark, "grown")
    placed = split_even(level.df.drop("ext", "pos"), parts, "path").drop("pos")
    placed.repartitionByRange(parts, "part").drop("part").write.parquet(source)
    rows = spark.readStream.schema(level.df.drop("ext", "pos").schema).option("maxFilesPerTrigger", 1).parquet(source)

    def grow(batch: DataFrame, n: int) -> None:
        grown = vertex.expand(graph, vertex.with_ext(graph, batch, level.k), last=True).df
        grown.write.mode("overwrite").parquet(f"{target}/batch_of={n}")  # a batch run again replaces itself

    rows.writeStream.foreachBatch(grow).trigger(availableNow=True).option("checkpointLocation", f"{target}-state").start().awaitTermination()
    schema = vertex.expand(graph, level, last=True).df.schema
    return spark.read.schema(schema).parquet(f"{target}/*").select(*[F.col(c) for c in schema.fieldNames()])
