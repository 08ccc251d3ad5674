"""Graphs from streams of events: windowed activity, co-activity edges, labels, duplicates."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from levelmine.session import scratch_path
from levelmine.store import packed

EVENT = T.StructType([T.StructField(n, t) for n, t in (("event_id", T.LongType()), ("ts", T.TimestampType()), ("user_id", T.LongType()), ("event_type", T.StringType()), ("value", T.DoubleType()), ("props", T.StringType()))])
DELAY = "10 minutes"


def spread(spark: SparkSession, events: DataFrame, files: int) -> str:
    """Writes events as so many files in time order, one after the other, each to be one micro-batch: the source takes
    files by their age, and a younger one first would make the older one's rows late."""
    path = scratch_path(spark, "events")
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).select(*EVENT.fieldNames())
    at = F.unix_micros("ts")
    cuts = rows.select(F.percentile_approx(at, [i / files for i in range(1, files)]).alias("q")).first()["q"] or []
    edges = [None, *cuts, None]
    for lo, hi in zip(edges[:-1], edges[1:], strict=True):
        part = (F.lit(True) if lo is None else at > lo) & (F.lit(True) if hi is None else at <= hi)
        rows.filter(part).coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    """Events as they come, with the watermark."""
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files_a_batch).parquet(path).withWatermark("ts", DELAY)


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    return _counted(events, F.window("ts", size))


def dropped_late(df: DataFrame) -> int:
    """Runs a windowed stream over all that is there; the rows that came behind the watermark and were dropped."""
    path = scratch_path(df.sparkSession, "late")
    query = df.writeStream.outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{path}-state").format("noop").start()
    query.awaitTermination()
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def with_late(spark: SparkSession, events: DataFrame, seconds: int) -> str:
    """Three files: all events, the newest once more, then those of the hour before the newest minus `seconds` once more,
    so that they come behind the watermark if `seconds` exceeds its delay. The one in between is needed since a batch drops
    rows by the watermark with which the batch before it began."""
    path = scratch_path(spark, "late_events")
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).select(*EVENT.fieldNames())
    newest = rows.agg(F.max("ts").alias("m")).first()["m"]
    rows.coalesce(1).write.mode("append").parquet(path)
    rows.filter(F.col("ts") == F.lit(newest)).coalesce(1).write.mode("append").parquet(path)
    edge = F.lit(newest) - F.expr(f"interval {seconds} seconds")
    rows.filter((F.col("ts") < edge) & (F.col("ts") >= edge - F.expr("interval 1 hour"))).coalesce(1).write.mode("append").parquet(path)
    return path


def sliding(events: DataFrame, size: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    return _counted(events, F.window("ts", size, step))


def _counted(events: DataFrame, window) -> DataFrame:
    out = events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.unix_micros("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    out = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return out.select(F.unix_micros("w.start").alias("start"), "user_id", "n")


def coactive(events: DataFrame, seconds: int = 10) -> DataFrame:
    """(src, dst) by a stream-stream join within the interval; both sides' state ends with the watermark."""
    a = events.select(F.col("user_id").alias("src"), F.col("ts").alias("ta"))
    b = events.select(F.col("user_id").alias("dst"), F.col("ts").alias("tb"))
    near = F.expr(f"src < dst AND tb >= ta - interval {seconds} seconds AND tb <= ta + interval {seconds} seconds")
    return a.join(b, near).select("src", "dst", F.col("ta").alias("at"))


def coactive_bucketed(events: DataFrame, seconds: int = 10) -> DataFrame:
    """The same with an equality on time buckets, which a stream-stream join needs to spread its state."""
    span = seconds * 1_000_000
    bucket = F.floor(F.unix_micros("ts") / span)
    a = events.select(F.col("user_id").alias("src"), F.col("ts").alias("ta"), bucket.alias("ka"))
    b = events.select(F.col("user_id").alias("dst"), F.col("ts").alias("tb"), F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("kb"))
    near = F.expr(f"ka = kb AND src < dst AND tb >= ta - interval {seconds} seconds AND tb <= ta + interval {seconds} seconds")
    return a.join(b, near).select("src", "dst", F.col("ta").alias("at"))


def labelled(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """A static table of vertex labels joined to the stream."""
    v = labels.select("id", "label")
    return edges.join(v.toDF("src", "src_label"), "src").join(v.toDF("dst", "dst_label"), "dst")


def without_duplicates(edges: DataFrame) -> DataFrame:
    """The first of equal edges within the watermark's reach."""
    return edges.dropDuplicatesWithinWatermark(["src", "dst"])


def drained(df: DataFrame, mode: str = "append", batch: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Runs a stream over all that is there and reads what it has written.

    update and complete results are kept batch by batch, with the batch's number; append results as they are.
    """
    spark, path = df.sparkSession, scratch_path(df.sparkSession, "stream")
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}-state")
    if batch is not None:
        writer.foreachBatch(batch).start().awaitTermination()
        return spark.createDataFrame([], df.schema)
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(path)

    def keep(rows: DataFrame, n: int) -> None:
        rows.withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{path}/batch_of={n}")

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(T.StructType([*df.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(f"{path}/*")


def drained_packed(df: DataFrame, blocks: int) -> list[str]:
    """Runs a stream of edges over all that is there; each batch writes a folder of packed cells."""
    path, folders = scratch_path(df.sparkSession, "packed"), {}

    def keep(rows: DataFrame, n: int) -> None:
        folders[n] = f"{path}/batch_of={n}"
        packed.merged(packed.packed(rows.select("src", "dst"), blocks)).write.mode("overwrite").parquet(folders[n])

    df.writeStream.outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}-state").foreachBatch(keep).start().awaitTermination()
    return [folders[n] for n in sorted(folders)]
