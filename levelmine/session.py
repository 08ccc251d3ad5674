"""Session helpers: table reading, and lineage cuts in the folder the cluster shares."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; the path may be of any store that Spark reads."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_width(spark: SparkSession) -> int:
    """The session's number of shuffle partitions, the one knob that follows the input's size."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def scratch_root(spark: SparkSession) -> str:
    """The folder all executors share. The cluster names it in spark.checkpoint.dir; only where that is unset and all
    executors are threads of this machine (tests) a folder of this machine serves."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(named)
        uri = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(path).toString()
        return re.sub("^file:/+", "file:///", uri).rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return f"file://{os.path.join(tempfile.gettempdir(), 'levelmine-scratch')}"


_marked: set[str] = set()


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in this application's scratch folder, which goes when the driver ends."""
    home = f"{scratch_root(spark)}/levelmine/{spark.sparkContext.applicationId}"
    if home not in _marked:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(home)
        system = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        system.mkdirs(path)
        system.deleteOnExit(path)
        _marked.add(home)
    return f"{home}/{name}-{uuid.uuid4().hex}"


def drop_path(spark: SparkSession, path: str) -> None:
    """Deletes a scratch folder through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def path_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of a file, or of all files of a folder."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(target).getLength()


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Writes df to the shared folder and reads it back: computed once, and a lost executor loses none of it."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch = path
    return out


def release(*tables: DataFrame) -> None:
    """Deletes written tables that nothing lazy depends on any more; those that are not from `materialise` are left."""
    for t in tables:
        if path := t.__dict__.get("scratch"):
            drop_path(t.sparkSession, path)


_shipped: set[str] = set()


def ship_library(spark: SparkSession) -> None:
    """Sends this package to the executors, once a session, so that they need no copy of their own."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    home = Path(__file__).resolve().parent.parent
    box = Path(tempfile.mkdtemp()) / "levelmine_library.zip"
    with zipfile.ZipFile(box, "w", zipfile.ZIP_DEFLATED) as z:
        for f in [*home.glob("levelmine/**/*.py"), *home.glob("corpus_pipeline.py")]:
            z.write(f, f.relative_to(home))
    spark.sparkContext.addPyFile(str(box))
    _shipped.add(app)
