"""Streaming queries, each checked against its batch twin."""

from __future__ import annotations

from pyspark.sql import functions as F

from levelmine.explore import vertex
from levelmine.operators.exploration import COP, _text
from levelmine.operators.registry import query
from levelmine.session import read_table
from levelmine.sources import ctes
from levelmine.sources.ctes import sql
from levelmine.sources.graphs import load, part_copurchase, user_coactivity
from levelmine.store import packed
from levelmine.streaming import edges as st
from levelmine.streaming.incremental import TriangleCount
from levelmine.streaming.parts import expand_stream

_HOUR = "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"


#: Events of a batch of the stream whose joins keep them in their state.
_FILE_ROWS = 1_000_000


def _events(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    return e.withColumn("ts", F.col("ts").cast("timestamp"))


def _stream(spark, sf_dir, files=4):
    return st.stream(spark, st.spread(spark, _events(spark, sf_dir), files))


@query(_HOUR)
def window_tumbling(spark, sf_dir):
    return st.tumbling(_events(spark, sf_dir))


@query("SELECT epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) - k * 900000000 AS start, event_type, count(*) AS n FROM events, range(4) r(k) GROUP BY 1, 2")
def window_sliding(spark, sf_dir):
    return st.sliding(_events(spark, sf_dir))


_SESSIONS = """
WITH g AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT user_id, ts, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g)
SELECT epoch_us(min(ts)) AS start, user_id, count(*) AS n FROM n GROUP BY user_id, s
"""


@query(_SESSIONS)
def window_session(spark, sf_dir):
    return st.sessions(_events(spark, sf_dir))


@query(_HOUR)
def stream_tumbling(spark, sf_dir):
    """The counts by hour from a stream in update mode: the last that was said of each window."""
    out = st.drained(st.tumbling(_stream(spark, sf_dir)), "update")
    return out.groupBy("start", "event_type").agg(F.max_by("n", "batch").alias("n"))


@query("SELECT count(*) AS dropped FROM events, (SELECT max(ts) AS m FROM events) WHERE CAST(ts AS TIMESTAMP) < CAST(m AS TIMESTAMP) - INTERVAL 2 HOUR AND CAST(ts AS TIMESTAMP) >= CAST(m AS TIMESTAMP) - INTERVAL 3 HOUR")
def stream_late_rows(spark, sf_dir):
    """An hour of events comes once more, far behind the watermark: its rows are dropped, and counted. The operator that
    drops them takes rows as they are; one behind a partial aggregate would count groups."""
    events = read_table(spark, sf_dir, "events")
    rows = st.stream(spark, st.with_late(spark, events, 7200)).select(F.window("ts", "1 minute").alias("w"))
    late = st.dropped_late(rows.dropDuplicates(["w"]))
    return spark.createDataFrame([(late,)], "dropped long")


@query(_HOUR)
def stream_complete(spark, sf_dir):
    """The same in complete mode: the last batch's table."""
    out = st.drained(st.tumbling(_stream(spark, sf_dir)), "complete")
    last = out.agg(F.max("batch").alias("m"))
    return out.join(F.broadcast(last), F.col("batch") == F.col("m")).select("start", "event_type", "n")


@query(sql(ctes.COACTIVE, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM e"))
def stream_coactive(spark, sf_dir):
    """Co-activity edges by a stream-stream join."""
    return st.drained(st.coactive_bucketed(_stream(spark, sf_dir))).select("src", "dst").distinct()


@query(sql(ctes.COACTIVE, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, a.label AS src_label, b.label AS dst_label FROM e JOIN v a ON a.id = src JOIN v b ON b.id = dst"))
def stream_labelled(spark, sf_dir):
    """The stream joined to the static labels of its vertices."""
    g = load(user_coactivity, spark, sf_dir)
    rows = st.labelled(st.coactive_bucketed(_stream(spark, sf_dir)), g.vertices)
    return st.drained(rows).select("src", "dst", "src_label", "dst_label").distinct()


@query(sql(ctes.COACTIVE, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM e"))
def stream_duplicates(spark, sf_dir):
    rows = st.without_duplicates(st.coactive_bucketed(_stream(spark, sf_dir)))
    return st.drained(rows).select("src", "dst").distinct()


@query(sql(ctes.COACTIVE, ctes.SYM, select="SELECT (SELECT count(*) FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst) AS triangles, (SELECT CAST(sum(d * (d - 1) / 2) AS BIGINT) FROM (SELECT count(*) AS d FROM s GROUP BY a)) AS wedges"))
def stream_triangles(spark, sf_dir):
    """Triangles and wedges after the last batch of an incremental count: three batches, each of the same number of the
    stream's. A batch of the stream leaves its edges packed, never as rows."""
    events = _events(spark, sf_dir)
    rows, users = events.agg(F.count("*"), F.countDistinct("user_id")).first()
    count = TriangleCount(spark, blocks=packed.block_count(users))
    files = 3 * max(1, -(-rows // (3 * _FILE_ROWS)))
    found = st.drained_packed(st.coactive_bucketed(st.stream(spark, st.spread(spark, events, files))), count.blocks)
    for n in range(3):
        if part := found[n * len(found) // 3 : (n + 1) * len(found) // 3]:
            count.add_packed(spark.read.schema(packed.CELL).parquet(*part), n)
    return spark.createDataFrame([(count.triangles, count.wedges)], "triangles long, wedges long")


@query(sql(COP, ctes.SYM, ctes.SETS3, select="SELECT array_to_string(w, '-') AS verts FROM c3"))
def stream_parts(spark, sf_dir):
    """A level grown part by part as a stream of files."""
    g = load(part_copurchase, spark, sf_dir)
    return expand_stream(g, vertex.init(g, 2), 3).select(_text())
