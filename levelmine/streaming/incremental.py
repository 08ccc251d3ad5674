"""Triangles and wedges of a growing graph: each batch of edges adds what it closes, on packed edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.session import scratch_path
from levelmine.store import packed


class TriangleCount:
    """Edges, degrees and counts so far, in tables of one folder a batch: (state=N) holds the counts after batch N, the
    cells of packed edges that it added and the degrees that it changed. blocks: as many as `packed.block_count` has for the
    vertices that are to come; a counter goes on with those of its path. A batch run again after a failure replaces its own folder, and a
    counter opened on the same path goes on where the last whole batch ended."""

    def __init__(self, spark: SparkSession, path: str | None = None, blocks: int = 4):
        self.spark, self.path = spark, path or scratch_path(spark, "triangles")
        self.blocks, self.batches = blocks, []
        self.triangles, self.wedges, self.history = 0, 0, []
        folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        system = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        if system.exists(folder):
            for f in system.listStatus(folder):
                name = f.getPath().getName()
                if name.startswith("counts="):
                    self.batches.append(int(name.removeprefix("counts=")))
            for n in sorted(self.batches):
                row = spark.read.parquet(f"{self.path}/counts={n}").first()
                self.triangles, self.wedges, self.blocks = row["triangles"], row["wedges"], row["blocks"]
                self.history.append((n, self.triangles, self.wedges))

    @property
    def last(self) -> int:
        return max(self.batches, default=-1)

    def _parts(self, kind: str, schema: str) -> DataFrame:
        if not self.batches:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[f"{self.path}/{kind}={n}" for n in self.batches])

    @property
    def cells(self) -> DataFrame:
        return self._parts("cells", packed.CELL)

    @property
    def edges(self) -> DataFrame:
        return packed.rows_of(self.cells)

    def add(self, pairs: DataFrame, batch: int) -> None:
        if batch > self.last:
            self.add_packed(packed.packed(pairs, self.blocks), batch)

    def add_packed(self, pieces: DataFrame, batch: int) -> None:
        """A batch of edges that are packed in pieces of this counter's blocks."""
        if batch <= self.last:
            return
        old = self.cells if self.batches else None
        packed.merged(pieces, old).write.mode("overwrite").parquet(f"{self.path}/cells={batch}")
        new = self.spark.read.schema(packed.CELL).parquet(f"{self.path}/cells={batch}")
        triangles = self.triangles + packed.triangles(new, self.blocks, old)
        more = packed.degrees(new).withColumnRenamed("deg", "more")
        more.write.mode("overwrite").parquet(f"{self.path}/degrees={batch}")
        more = self.spark.read.parquet(f"{self.path}/degrees={batch}")
        # a vertex that had d neighbours and gets m more has d m + m (m - 1) / 2 more wedges
        had = self._parts("degrees", "v long, more long").join(more.select("v"), "v", "left_semi").groupBy("v").agg(F.sum("more").alias("had"))
        both = more.join(had, "v", "left").select("more", F.coalesce("had", F.lit(0)).alias("had"))
        wedges = self.wedges + (both.agg(F.sum(F.col("had") * F.col("more") + F.expr("more * (more - 1) div 2"))).first()[0] or 0)
        self.spark.createDataFrame([(triangles, wedges, self.blocks)], "triangles long, wedges long, blocks int").write.mode("overwrite").parquet(f"{self.path}/counts={batch}")
        self.batches.append(batch)
        self.triangles, self.wedges = triangles, wedges
        self.history.append((batch, triangles, wedges))
