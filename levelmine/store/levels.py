"""The level store: embeddings kept level by level as links to their parents, not as whole paths.

Level k is a table (pos, parent, vert, label, mask): pos numbers the embeddings in the order of (parent, vert), parent is
the pos of the prefix in level k-1, vert the last vertex. Its offset table (parent, start, stop) says which run of pos
shares a parent. As rows are sorted by parent, Parquet's encodings keep the column small, and ranges of pos prune files.
The exploration writes its levels here (`stored`) and grows the next one from what it reads back.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.explore import vertex
from levelmine.explore.loop import explore
from levelmine.explore.vertex import EFilter, Level
from levelmine.graph.model import PropertyGraph
from levelmine.graph.numbering import numbered, running
from levelmine.session import path_bytes, scratch_path

#: Rows of a written file at most: the write buffer of a task is a row group of one such file.
FILE_ROWS = 4_000_000


class LevelStore:
    """layout='links' keeps parent links; layout='paths' keeps whole paths, for comparison."""

    def __init__(self, spark: SparkSession, layout: str = "links", root: str | None = None):
        if layout not in ("links", "paths"):
            raise ValueError("layouts: links, paths")
        self.spark, self.layout, self.root = spark, layout, root or scratch_path(spark, "store")
        self.k, self._prefix = 0, None

    def _write(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").option("maxRecordsPerFile", FILE_ROWS).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def append(self, level: DataFrame) -> None:
        """Adds the next level, given as whole paths in any order."""
        self.k += 1
        placed = numbered(level.select("path"), "path")
        if self.layout == "paths":
            self._write(placed, f"level={self.k}")
            return
        vert = F.element_at("path", -1).alias("vert")
        if self.k == 1:
            rows = placed.select("pos", F.lit(None).cast("long").alias("parent"), vert)
        else:
            before = self._prefix.select(F.col("path").alias("prefix"), F.col("pos").alias("parent"))
            rows = placed.withColumn("prefix", F.slice("path", 1, self.k - 1)).join(before, "prefix").select("pos", "parent", vert)
        self._write(rows.repartitionByRange("pos").sortWithinPartitions("pos"), f"level={self.k}")
        self._prefix = placed

    def append_links(self, links: DataFrame) -> DataFrame:
        """Adds the next level, given as (parent, vert, label, mask) by the parents' pos; returns it with its own pos."""
        self.k += 1
        rows = numbered(links, "parent", "vert")
        return self._write(rows.select("pos", "parent", "vert", "label", "mask"), f"level={self.k}")

    def keep(self, graph: PropertyGraph, level: Level, efilter: EFilter = None) -> Level:
        """A round of the exploration: the next level goes into this store, and is read back for growth."""
        return vertex.attached(graph, level, self.append_links(vertex.children(level, efilter)))

    def level(self, k: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.root}/level={k}")

    def offsets(self, k: int) -> DataFrame:
        """(parent, start, stop) for every embedding of level k-1; without children the slice is empty.

        Positions follow the parents' order, so the first and last child say where a slice is; an empty one begins
        where the slices before it end.
        """
        runs = self.level(k).groupBy("parent").agg(F.min("pos").alias("lo"), (F.max("pos") + 1).alias("hi"))
        parents = self.level(k - 1).select(F.col("pos").alias("parent"))
        both = numbered(parents.join(runs, "parent", "left"), "parent", name="n")
        filled = running(both, "n", "hi", F.max, F.greatest)
        before = F.coalesce("before", F.lit(0))
        return filled.select("parent", F.coalesce("lo", before).alias("start"), F.coalesce("hi", before).alias("stop"))

    def children(self, k: int, parent: int | Column) -> DataFrame:
        """The slice of level k that shares the parent."""
        return self.level(k).filter(F.col("parent") == parent)

    def paths(self, k: int, lo: int | None = None, hi: int | None = None) -> DataFrame:
        """(pos, path) of level k, or of its positions lo <= pos < hi, by walking down the parent links."""
        rows = self.level(k)
        if lo is not None:
            rows = rows.filter(F.col("pos") >= lo)
        if hi is not None:
            rows = rows.filter(F.col("pos") < hi)
        if self.layout == "paths":
            return rows.select("pos", "path")
        out = rows.select("pos", F.col("parent").alias("link"), F.array("vert").alias("path"))
        for j in range(k - 1, 0, -1):
            up = self.level(j).select(F.col("pos").alias("at"), F.col("parent").alias("next"), "vert")
            out = out.join(up, F.col("link") == F.col("at")).select("pos", F.col("next").alias("link"), F.concat(F.array("vert"), "path").alias("path"))
        return out.select("pos", "path")

    def decode(self, k: int, pos: int) -> list[int]:
        """One embedding: k point look-ups, each pruned by pos."""
        if self.layout == "paths":
            return list(self.level(k).filter(F.col("pos") == pos).first()["path"])
        out, at = [], pos
        for j in range(k, 0, -1):
            row = self.level(j).filter(F.col("pos") == at).first()
            if row is None:
                raise KeyError(f"level {j} has no position {at}")
            out.append(row["vert"])
            at = row["parent"]
        return out[::-1]

    def contains(self, wanted: DataFrame, k: int) -> DataFrame:
        """wanted(path): the paths that are cells of the tensor, found level by level."""
        rows = wanted.select("path").filter(F.size("path") == k).distinct().withColumn("link", F.lit(None).cast("long"))
        for j in range(1, k + 1):
            here = self.level(j).select(F.col("pos").alias("at"), F.col("parent").alias("up"), "vert")
            rows = rows.join(here, (F.element_at("path", j) == F.col("vert")) & F.col("link").eqNullSafe(F.col("up"))).select("path", F.col("at").alias("link"))
        return rows.select("path", F.col("link").alias("pos"))

    def write_parts(self, k: int, parted: DataFrame) -> str:
        """Writes level rows by their part column; each part is a folder that can be read alone. Rows with links have
        their offsets written beside them, part by part."""
        path = f"{self.root}/parts={k}"
        parted.write.mode("overwrite").option("maxRecordsPerFile", FILE_ROWS).partitionBy("part").parquet(path)
        if {"pos", "parent"} <= set(parted.columns):
            runs = self.spark.read.parquet(path).groupBy("part", "parent").agg(F.min("pos").alias("start"), (F.max("pos") + 1).alias("stop"))
            runs.write.mode("overwrite").partitionBy("part").parquet(f"{self.root}/parts_offsets={k}")
        return path

    def part(self, k: int, number: int, offsets: bool = False) -> DataFrame:
        """One part of a level written by write_parts, or its offsets, read from its own folder alone."""
        return self.spark.read.parquet(f"{self.root}/{'parts_offsets' if offsets else 'parts'}={k}/part={number}")

    def windows(self, k: int, rows: DataFrame) -> Iterator[tuple[int, DataFrame]]:
        """For a run of level k the runs of the levels above that it needs: of each level the range of pos that the
        window below points to. Two numbers a level go through the driver."""
        for j in range(k, 0, -1):
            yield j, rows
            if j > 1:
                span = rows.agg(F.min("parent").alias("lo"), F.max("parent").alias("hi")).first()
                rows = self.level(j - 1).filter(F.col("pos").between(span["lo"] or 0, -1 if span["hi"] is None else span["hi"]))

    def window_paths(self, k: int, rows: DataFrame) -> DataFrame:
        """(pos, path, labels, bits) of a run of level k, decoded from the windows of the levels above it alone."""
        held = dict(self.windows(k, rows))
        out = held[k].select("pos", F.col("parent").alias("link"), F.array("vert").alias("path"), F.array("label").alias("labels"), F.shiftleft("mask", vertex.bit_base(k - 1)).alias("bits"))
        for j in range(k - 1, 0, -1):
            up = held[j].select(F.col("pos").alias("at"), F.col("parent").alias("next"), "vert", "label", F.shiftleft("mask", vertex.bit_base(j - 1)).alias("own"))
            both = out.join(up, F.col("link") == F.col("at"))
            out = both.select("pos", F.col("next").alias("link"), F.concat(F.array("vert"), "path").alias("path"), F.concat(F.array("label"), "labels").alias("labels"), F.col("bits").bitwiseOR(F.col("own")).alias("bits"))
        return out.select("pos", "path", "labels", "bits")

    def bytes(self, k: int) -> int:
        return path_bytes(self.spark, f"{self.root}/level={k}")


def stored(graph: PropertyGraph, k: int, layout: str = "links") -> LevelStore:
    """A store with levels 1..k of the vertex-induced exploration. With links, the exploration grows each level from the
    store's own rows."""
    store = LevelStore(graph.edges.sparkSession, layout)
    if layout == "paths":
        for level in explore(graph, k):
            store.append(level.df)
        return store
    first = graph.vertices.select(F.lit(None).cast("long").alias("parent"), F.col("id").alias("vert"), "label", F.lit(0).cast("long").alias("mask"))
    rows = store.append_links(first)
    base = vertex.init(graph).df.drop("pos")
    level = Level(base.join(rows.select("pos", "vert"), F.col("path")[0] == F.col("vert")).drop("vert"), 1, True)
    while level.k < k:
        level = store.keep(graph, level)
    return store
