"""Edge lists: a Python data source for text files of "src dst [label]" lines, and adjacency-line text."""

from __future__ import annotations

import io
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import datasource as ds
from pyspark.sql import functions as F


class EdgeListReader(ds.DataSourceReader):
    """One partition a file, or `splits` byte ranges of each; a line belongs to the range it begins in."""

    def __init__(self, options: dict):
        self.path, self.splits = options["path"], max(1, int(options.get("splits", "1")))

    def _open(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path)

    def partitions(self):
        from pyarrow import fs

        system, base = self._open()
        info = system.get_file_info(base)
        files = [info] if info.is_file else [f for f in system.get_file_info(fs.FileSelector(base, recursive=True)) if f.is_file and not f.base_name.startswith(("_", "."))]
        out = []
        for f in sorted(files, key=lambda f: f.path):
            cuts = [f.size * i // self.splits for i in range(self.splits + 1)]
            out += [ds.InputPartition((f.path, a, b)) for a, b in zip(cuts[:-1], cuts[1:], strict=True) if b > a]
        return out or [ds.InputPartition(("", 0, 0))]

    def read(self, partition: ds.InputPartition) -> Iterator[pa.RecordBatch]:
        file, start, stop = partition.value
        if not file:
            return
        system, _ = self._open()
        with io.BufferedReader(system.open_input_file(file), 1 << 20) as f:
            at = start
            if start:
                f.seek(start - 1)
                at = start - 1 + len(f.readline())
            else:
                f.seek(0)
            rows: list[tuple[int, int, int]] = []
            while at < stop:
                line = f.readline()
                if not line:
                    break
                at += len(line)
                parts = line.decode("utf-8", "replace").split("#")[0].split()
                if len(parts) >= 2:
                    rows.append((int(parts[0]), int(parts[1]), int(parts[2]) if len(parts) > 2 else 1))
                if len(rows) >= 50_000:
                    yield self._batch(rows)
                    rows = []
            if rows:
                yield self._batch(rows)

    @staticmethod
    def _batch(rows: list[tuple[int, int, int]]) -> pa.RecordBatch:
        src, dst, label = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array(label, pa.int32())], ["src", "dst", "elabel"])


class EdgeListSource(ds.DataSource):
    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src long, dst long, elabel int"

    def reader(self, schema) -> EdgeListReader:
        return EdgeListReader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeListSource)


def read_delimited(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """(src, dst) of CSV or TSV files."""
    return spark.read.schema("src long, dst long").option("sep", sep).csv(path)


def read_adjacency_lines(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) of lines "vertex neighbour neighbour ..."."""
    parts = F.split(F.trim("value"), r"\s+")
    return spark.read.text(path).filter("trim(value) <> ''").select(parts[0].cast("long").alias("src"), F.explode(F.slice(parts, 2, F.size(parts)).cast("array<bigint>")).alias("dst"))
