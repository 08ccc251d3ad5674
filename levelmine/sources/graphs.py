"""Graph builders on the given tables. A graph is built once a session and kept in the shared folder."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levelmine.graph.model import PropertyGraph
from levelmine.graph.numbering import numbered
from levelmine.session import materialise, read_table, shuffle_width
from levelmine.store import packed

SHIFT = 1 << 40

#: The worked example: edges, and labels by vertex. Fixed values.
TOY_EDGES = [(1, 2), (1, 5), (2, 3), (2, 5), (3, 4), (3, 5), (4, 5)]
TOY_LABELS = [(1, 1), (2, 2), (3, 1), (4, 4), (5, 3)]


def toy7(spark: SparkSession, sf_dir: str = "") -> PropertyGraph:
    return PropertyGraph.from_pairs(spark.createDataFrame(TOY_EDGES, "src long, dst long"), spark.createDataFrame(TOY_LABELS, "id long, label int"))


def coded(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, label, name): labels are the texts' ranks from 1; the distinct texts are ranked, not the rows."""
    texts = df.select(F.col(text_col).alias("name")).filter(F.col(text_col).isNotNull()).distinct()
    codes = numbered(texts, "name", name="label", start=1).select("name", F.col("label").cast("int").alias("label"))
    return df.select(F.col(id_col).alias("id"), F.col(text_col).alias("name")).join(codes, "name").select("id", "label", "name")


def paired(rows: DataFrame, group: str, item: str, least: int = 1) -> DataFrame:
    """(src, dst, together): items that share at least `least` groups."""
    one = rows.select(group, item).distinct()
    a, b = one.select(group, F.col(item).alias("src")), one.select(group, F.col(item).alias("dst"))
    both = a.join(b, group).filter("src < dst").groupBy("src", "dst").agg(F.count("*").alias("together"))
    return both.filter(F.col("together") >= least)


def default_min_orders(spark: SparkSession, sf_dir: str) -> int:
    return 4 if read_table(spark, sf_dir, "part").count() <= 200 else 2


def part_copurchase(spark: SparkSession, sf_dir: str, label: str = "p_type", min_orders: int | None = None) -> PropertyGraph:
    least = min_orders or default_min_orders(spark, sf_dir)
    labels = coded(read_table(spark, sf_dir, "part"), "p_partkey", label)
    return PropertyGraph.from_pairs(paired(read_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", least), labels)


#: Vectors of one side of a block of the exact neighbour search at most, on average, and at least where tasks are short of work.
KNN_BLOCK, KNN_LEAST = 8192, 256
#: How far two orders of additions can move the inner product of unit vectors apart, at most by far.
KNN_ROUNDING = 1e-9


def _exactly(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of pairs of rows, in one order of additions for all, so that equal vectors tie."""
    cuts = [(lo, lo + 65536) for lo in range(0, len(a), 65536)]
    return np.concatenate([np.zeros(0), *[np.einsum("ij,ij->i", x[a[lo:hi]], x[b[lo:hi]]) for lo, hi in cuts]])


def _nearest_in_block(k: int):
    """A block: for each of its asking rows the k most similar of its offered rows.

    A matrix product finds those that can be among the k; only they are worked out exactly and sorted."""

    def run(table: pa.Table) -> pa.Table:
        ids, asks = table["vec_id"].to_numpy(), table["asks"].to_numpy(zero_copy_only=False)
        x = table["x"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1).astype(np.float64)
        x = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
        mine, theirs = np.flatnonzero(asks), np.flatnonzero(~asks)
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        offered = np.ascontiguousarray(x[theirs].T)
        for lo in range(0, len(mine) if len(theirs) else 0, 256):
            part = mine[lo : lo + 256]
            sim = x[part] @ offered
            sim[ids[part][:, None] == ids[theirs][None, :]] = -np.inf
            at = max(0, len(theirs) - k)
            least = np.partition(sim, at, axis=1)[:, at] - KNN_ROUNDING
            row, col = np.nonzero((sim >= least[:, None]) & np.isfinite(sim))
            exact = _exactly(x, part[row], theirs[col])
            other = ids[theirs[col]]
            order = np.lexsort((other, -exact, row))
            row, other, exact = row[order], other[order], exact[order]
            first = np.arange(len(row)) - np.searchsorted(row, row) < k
            out.append((ids[part[row]][first], other[first], exact[first]))
        vec_id, other, sim = map(np.concatenate, zip(*out, strict=True))
        return pa.table({"vec_id": vec_id, "other": other, "sim": sim})

    return run


def vector_knn(spark: SparkSession, sf_dir: str, k: int = 5) -> PropertyGraph:
    """Each vector and its k most similar ones by cosine, exactly: a grid of blocks of rows against blocks of rows.

    The work grows with the square of the table, as the definition asks; for tables too large for that, the
    approximate search among the training-data operators finds the neighbours.
    """
    v = read_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("x"), "label")
    if v.schema["x"].dataType.simpleString() != "array<float>":  # floats are widened in the block, and shuffled as they are
        v = v.withColumn("x", F.col("x").cast("array<double>"))
    n = v.count()
    cuts = max(1, -(-n // KNN_BLOCK), min(math.ceil(math.sqrt(2 * shuffle_width(spark))), -(-n // KNN_LEAST)))
    block = F.pmod(F.xxhash64("vec_id"), F.lit(cuts)).cast("int")
    each = F.explode(F.sequence(F.lit(0), F.lit(cuts - 1)))
    asking = v.select("vec_id", "x", F.lit(True).alias("asks"), block.alias("a"), each.alias("b"))
    offered = v.select("vec_id", "x", F.lit(False).alias("asks"), each.alias("a"), block.alias("b"))
    found = asking.unionByName(offered).groupBy("a", "b").applyInArrow(_nearest_in_block(k), "vec_id long, other long, sim double")
    near = Window.partitionBy("vec_id").orderBy(F.desc("sim"), "other")
    top = found.withColumn("r", F.row_number().over(near)).filter(F.col("r") <= k)
    labels = v.select(F.col("vec_id").alias("id"), (F.col("label") + 1).alias("label"))
    return PropertyGraph.from_pairs(top.select(F.col("vec_id").alias("src"), F.col("other").alias("dst")), labels)


def coactive_pairs(events: DataFrame, seconds: int) -> DataFrame:
    """Users who act within so many seconds of each other: an interval join on buckets of that length."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    span = seconds * 1_000_000
    e = events.select("user_id", at.alias("t")).withColumn("bucket", F.floor(F.col("t") / span))
    near = e.select(F.col("user_id").alias("u2"), F.col("t").alias("t2"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    both = e.join(near, "bucket").filter((F.abs(F.col("t") - F.col("t2")) <= span) & (F.col("user_id") < F.col("u2")))
    return both.select(F.col("user_id").alias("src"), F.col("u2").alias("dst")).distinct()


#: Pairs of events that a task holds at once, and slices of time for each shuffle partition.
EVENT_PAIRS, SLICES = 1 << 21, 4


def _coactive_in_slice(span: int, length: int, blocks: int):
    """Cells of the users who act within a span of each other, the later of the two within the slice."""

    def run(table: pa.Table) -> pa.Table:
        order = np.lexsort((table["user_id"].to_numpy(), table["t"].to_numpy()))
        t, user = table["t"].to_numpy()[order], table["user_id"].to_numpy()[order]
        once = np.ones(len(t), np.bool_)
        once[1:] = (np.diff(t) != 0) | (np.diff(user) != 0)
        t, user = t[once], user[once]
        ids, at = np.unique(user, return_inverse=True)
        later = np.flatnonzero(t // length == table["slice"][0].as_py())
        low = np.searchsorted(t, t[later] - span)
        ends = np.cumsum(later - low)
        codes, held, lo = [np.zeros(0, np.int64)], 0, 0
        while lo < len(later):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + EVENT_PAIRS, "right")))
            n = later[lo:hi] - low[lo:hi]
            b = np.repeat(later[lo:hi], n)
            a = np.arange(len(b)) - np.repeat(np.cumsum(n) - n - low[lo:hi], n)
            x, y = at[a], at[b]
            codes.append(np.unique((np.minimum(x, y) * len(ids) + np.maximum(x, y))[x != y]))
            held, lo = held + len(codes[-1]), hi
            if held > 8 * EVENT_PAIRS:
                codes = [np.unique(np.concatenate(codes))]
                held = 0
        one = np.unique(np.concatenate(codes))
        return packed.cells_of(ids[one // max(1, len(ids))], ids[one % max(1, len(ids))], blocks)

    return run


def coactive_cells(events: DataFrame, seconds: int = 10) -> tuple[DataFrame, int]:
    """The edges of user_coactivity as packed cells, and their blocks. Events meet in slices of time, each with the events
    of the span before it, and a slice's pairs leave its task packed."""
    span = seconds * 1_000_000
    e = events.select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).filter("user_id is not null and t is not null")
    users, first, last = e.agg(F.countDistinct("user_id"), F.min("t"), F.max("t")).first()
    blocks = packed.block_count(users)
    length = max(2 * span, 1, ((last or 0) - (first or 0)) // (SLICES * shuffle_width(events.sparkSession)) + 1)
    own = lambda t: F.floor(F.expr(t) / length)
    cut = e.select("user_id", "t", F.explode(F.array_distinct(F.array(own("t"), own(f"t + {span}")))).alias("slice"))
    pieces = cut.groupBy("slice").applyInArrow(_coactive_in_slice(span, length, blocks), packed.CELL)
    return materialise(packed.merged(pieces), "cells"), blocks


def user_coactivity(spark: SparkSession, sf_dir: str, seconds: int = 10) -> PropertyGraph:
    events = read_table(spark, sf_dir, "events")
    most = Window.partitionBy("user_id").orderBy(F.desc("n"), "event_type")
    usual = events.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).withColumn("r", F.row_number().over(most)).filter("r = 1")
    return PropertyGraph.from_pairs(coactive_pairs(events, seconds), coded(usual, "user_id", "event_type"))


def default_supplier_orders(spark: SparkSession, sf_dir: str) -> int:
    n = read_table(spark, sf_dir, "supplier").count()
    return 150 if n <= 10 else 24 if n <= 100 else 5


def supplier_coorder(spark: SparkSession, sf_dir: str, level: str = "nation", min_orders: int | None = None) -> PropertyGraph:
    least = min_orders or default_supplier_orders(spark, sf_dir)
    nation = read_table(spark, sf_dir, "nation")
    key = "n_nationkey" if level == "nation" else "n_regionkey"
    labels = read_table(spark, sf_dir, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("id"), (F.col(key) + 1).cast("int").alias("label"))
    return PropertyGraph.from_pairs(paired(read_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_suppkey", least), labels)


def part_supplier(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    pairs = read_table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + SHIFT).alias("dst")).distinct()
    sides = pairs.select(F.col("src").alias("id"), F.lit(1).alias("label")).union(pairs.select("dst", F.lit(2))).distinct()
    return PropertyGraph.from_pairs(pairs, sides)


def page_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, target): distinct anchor targets of each page."""
    pages = read_table(spark, sf_dir, "pages")
    found = F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), 1)
    return pages.select("page_id", F.explode(found).alias("target")).distinct()


def page_links(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Targets are strings: each distinct one gets a number of its own above SHIFT."""
    anchors = page_anchors(spark, sf_dir)
    keys = numbered(anchors.select("target").distinct(), "target", name="key", start=SHIFT)
    pairs = anchors.join(keys, "target").select(F.col("page_id").alias("src"), F.col("key").alias("dst"))
    host = F.regexp_extract("url", r"^https?://[^/?#]*?([a-z]+)(?:[/?#:]|$)", 1)
    suffix = coded(read_table(spark, sf_dir, "pages").select("page_id", host.alias("suffix")), "page_id", "suffix")
    labels = suffix.withColumn("label", F.col("label") + 1).unionByName(keys.select(F.col("key").alias("id"), F.lit(1).alias("label"), F.col("target").alias("name")))
    return PropertyGraph.from_pairs(pairs, labels)


def document_overlap(spark: SparkSession, sf_dir: str, shared: int = 3) -> PropertyGraph:
    """Documents that share so many 8-word shingles.

    Documents of equal shingle sets are joined as one and take their copies' edges afterwards."""
    docs = read_table(spark, sf_dir, "documents")
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    grams = docs.select("doc_id", words.alias("w")).filter(F.size("w") >= 8).select("doc_id", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 8), " ")))).alias("g")).distinct()
    held = grams.groupBy("g").agg(F.count("*").alias("n")).filter("n >= 2").select("g")
    grams = materialise(grams.join(held, "g"), "shingles")
    sets = grams.groupBy("doc_id").agg(F.count("*").alias("n"), F.xxhash64(F.sort_array(F.collect_list("g"))).alias("h"))
    sets = materialise(sets.withColumn("first", F.min("doc_id").over(Window.partitionBy("h", "n"))).select("doc_id", "first", "n"), "copies")
    links = paired(grams.join(sets.filter("doc_id = first").select("doc_id"), "doc_id"), "g", "doc_id", shared).select("src", "dst")
    a, b = sets.select(F.col("doc_id").alias("x"), F.col("first").alias("src")), sets.select(F.col("doc_id").alias("y"), F.col("first").alias("dst"))
    within = a.join(sets.filter(F.col("n") >= shared).select(F.col("doc_id").alias("y"), F.col("first").alias("src")), "src").filter("x < y")
    pairs = links.join(a, "src").join(b, "dst").select("x", "y").unionByName(within.select("x", "y")).toDF("src", "dst")
    return PropertyGraph.from_pairs(pairs, coded(docs, "doc_id", "lang"), isolated=True)


def turn_chain(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    turns = read_table(spark, sf_dir, "conversations").select((F.col("conv_id") * 100_000 + F.col("turn")).alias("id"), "conv_id", "turn", "role")
    order = Window.partitionBy("conv_id").orderBy("turn")
    pairs = turns.withColumn("next", F.lead("id").over(order)).filter("next is not null").select(F.col("id").alias("src"), F.col("next").alias("dst"))
    return PropertyGraph.from_pairs(pairs, coded(turns, "id", "role"))


def customer_part(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    lines = read_table(spark, sf_dir, "lineitem").filter("l_returnflag = 'R' and l_quantity >= 45")
    pairs = lines.join(read_table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + SHIFT).alias("dst"))
    segment = coded(read_table(spark, sf_dir, "customer"), "c_custkey", "c_mktsegment").withColumn("label", F.col("label") + 1)
    return PropertyGraph.from_pairs(pairs, segment)


_BUILT: dict[tuple, PropertyGraph] = {}


def forget() -> None:
    """Drops what this process remembers of built graphs; the next use builds them anew."""
    _BUILT.clear()


def load(builder: Callable[..., PropertyGraph], spark: SparkSession, sf_dir: str, **params) -> PropertyGraph:
    """The graph, built at first use in this session."""
    key = (spark.sparkContext.applicationId, builder.__name__, sf_dir, tuple(sorted(params.items())))
    if key not in _BUILT:
        _BUILT[key] = builder(spark, sf_dir, **params)
    return _BUILT[key]
