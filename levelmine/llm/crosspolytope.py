"""Nearest neighbours by cross-polytope hashing.

A table's hash: three rounds of random signs and a fast Hadamard transform turn a vector pseudo-randomly; the nearest
signed axis of the turned vector is its cell, or the axes of several such turns together (`turns`, for cells of a more
or less constant size as the table grows). A query looks into its `probes` nearest cells in each of `tables` tables.

Index. Every row is hashed once, into one cell of each table; (table, cell) is the key by which rows and probes meet. A
cell of many rows or many probes is cut into a grid of blocks of bounded size, so a vector that a third of all rows
share spreads. A block multiplies its probes by its rows, ranks what is near the top by the exact inner product in
double precision on the original vectors, and passes on the k best of each query; a pair that an earlier table has met
is left to that table, so no pair is ranked twice. A query that has met fewer than k rows is answered by a full scan,
in blocks too. For vectors of unequal length the largest inner product is found by one more component that makes all
rows equally long (zero for queries).

Defined results. Vectors that are null, zero, or hold null or non-finite components take no part; nor do null ids and
vectors of another dimension than most. Rows that repeat an id count once, with the best score. Ties go to smaller ids.
An empty table has no queries. Vectors are of bounded length; ids may be any longs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelmine.session import materialise, shuffle_width

TABLES, PROBES, TURNS, SEED = 16, 6, 1, 5
#: Rows and probes of a block at most, on average.
BLOCK = 2048


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of the rows, scaled to keep lengths."""
    rows, n = x.shape
    h = 1
    while h < n:
        x = x.reshape(rows, n // (2 * h), 2, h)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2).reshape(rows, n)
        h *= 2
    return x / np.sqrt(n)


class Turns:
    """The tables' pseudo-rotations for vectors of dimension dim, with one more component if `lifted`."""

    def __init__(self, dim: int, longest: float, lifted: bool, tables: int = TABLES, turns: int = TURNS, seed: int = SEED):
        self.longest, self.lifted, self.dim = longest, lifted, dim
        self.size = 1 << max(1, (dim + lifted - 1).bit_length())
        self.signs = np.random.default_rng(seed).choice([-1.0, 1.0], (tables, turns, 3, self.size))

    def _padded(self, x: np.ndarray, query: bool) -> np.ndarray:
        out = np.zeros((len(x), self.size))
        scale = np.linalg.norm(x, axis=1, keepdims=True) if query else self.longest
        out[:, : self.dim] = x / scale
        if self.lifted and not query:
            out[:, self.dim] = np.sqrt(np.maximum(0, 1 - (out[:, : self.dim] ** 2).sum(axis=1)))
        return out

    def _turned(self, x: np.ndarray, table: int, turn: int) -> np.ndarray:
        for signs in self.signs[table, turn]:
            x = hadamard(x * signs)
        return x

    def cells(self, x: np.ndarray) -> np.ndarray:
        """(rows, tables): the nearest signed axis of each turn; axis a is digit a, its opposite a + size."""
        x = self._padded(x, False)
        out = np.zeros((len(x), len(self.signs)), np.int64)
        for t in range(len(self.signs)):
            for turn in range(self.signs.shape[1]):
                y = self._turned(x, t, turn)
                axis = np.abs(y).argmax(axis=1)
                out[:, t] = out[:, t] * 2 * self.size + axis + self.size * (y[np.arange(len(y)), axis] < 0)
        return out

    def probes(self, x: np.ndarray, probes: int = PROBES) -> np.ndarray:
        """(queries, tables, probes): the nearest cells, by the sum of the components along their axes."""
        x = self._padded(x, True)
        out = []
        for t in range(len(self.signs)):
            total, cell = np.zeros((len(x), 1)), np.zeros((len(x), 1), np.int64)
            for turn in range(self.signs.shape[1]):
                y = self._turned(x, t, turn)
                both = np.concatenate([y, -y], axis=1)
                axis = np.argpartition(-both, min(probes, both.shape[1]) - 1, axis=1)[:, :probes]
                total = (total[:, :, None] + np.take_along_axis(both, axis, 1)[:, None, :]).reshape(len(x), -1)
                cell = (cell[:, :, None] * 2 * self.size + axis[:, None, :]).reshape(len(x), -1)
                best = np.argpartition(-total, min(probes, total.shape[1]) - 1, axis=1)[:, :probes]
                total, cell = np.take_along_axis(total, best, 1), np.take_along_axis(cell, best, 1)
            out.append(cell)
        return np.stack(out, axis=1)


def _best(query: np.ndarray, vec: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each query, each id once."""
    order = np.lexsort((-score, vec, query))
    query, vec, score = query[order], vec[order], score[order]
    new = np.ones(len(query), np.bool_)
    new[1:] = (query[1:] != query[:-1]) | (vec[1:] != vec[:-1])
    query, vec, score = query[new], vec[new], score[new]
    order = np.lexsort((vec, -score, query))
    query, vec, score = query[order], vec[order], score[order]
    start = np.searchsorted(query, query, "left")
    top = np.arange(len(query)) - start < k
    return query[top], vec[top], score[top]


def _matrix(column: pa.ChunkedArray | pa.Array, dim: int) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


def _ranked_block(table: pa.Table, k: int, dim: int, tables: int, probes: int) -> pa.Table:
    """A block's rows (table >= 0 or -1 for a scan, is_query, id, v, cells) -> the k best of each of its queries."""
    asks = table["is_query"].to_numpy(zero_copy_only=False)
    ids, x = table["id"].to_numpy(), _matrix(table["v"], dim).astype(np.float64)
    q, r = np.flatnonzero(asks), np.flatnonzero(~asks)
    r = r[np.argsort(ids[r], kind="stable")]
    at = table["at"][0].as_py()
    copies = np.unique(ids[r], return_counts=True)[1]
    room = k + 1 if not len(r) or copies.max() == 1 else len(r)  # ids that repeat may not crowd out others
    found = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]]
    met = None
    if at > 0:
        flat = table["cells"].combine_chunks()
        met = flat.take(pa.array(r)).flatten().to_numpy().reshape(len(r), tables), flat.take(pa.array(q)).flatten().to_numpy().reshape(len(q), tables, probes)
    for lo in range(0, len(q), 256):
        part = q[lo : lo + 256]
        near = x[part] @ x[r].T
        near[ids[part][:, None] == ids[r][None, :]] = -np.inf
        if len(r) > room:
            edge = np.partition(near, len(r) - room, axis=1)[:, len(r) - room]
            mask = near >= (edge - 1e-9 * (1 + np.abs(edge)))[:, None]
        else:
            mask = np.ones(near.shape, np.bool_)
        a, b = np.nonzero(mask & np.isfinite(near))
        found[0].append(ids[part[a]])
        found[1].append(ids[r[b]])
        score = np.concatenate([(x[r[b[i : i + 50_000]]] * x[part[a[i : i + 50_000]]]).sum(axis=1) for i in range(0, len(a), 50_000)] or [np.zeros(0)])
        if met is not None and len(a):  # an earlier table has the pair
            before = np.zeros(len(a), np.bool_)
            for t in range(at):
                before |= (met[0][b, t][:, None] == met[1][lo + a, t]).any(axis=1)
            score[before] = -np.inf
        found[2].append(score)
    query, vec, score = _best(*map(np.concatenate, found), k)
    kept = np.isfinite(score)
    return pa.table({"query_id": query[kept], "vec_id": vec[kept], "score": score[kept]})


def _blocks(index: DataFrame, asked: DataFrame, key: list[str], block: int) -> DataFrame:
    """index and asked (key, id, v, cells) -> the same rows by block: a grid over each key's rows and queries."""
    size = index.groupBy(*key).agg(F.count("*").alias("n")).join(asked.groupBy(*key).agg(F.count("*").alias("m")), key)
    size = materialise(size.select(*key, F.ceil(F.col("n") / block).cast("int").alias("down"), F.ceil(F.col("m") / block).cast("int").alias("over")), "cells")

    def placed(rows: DataFrame, own: str, other: str) -> DataFrame:
        mine = F.pmod(F.xxhash64("id", F.lit(7)), F.col(own)).cast("int")
        each = rows.join(size, key).withColumns({f"at_{own}": mine, f"at_{other}": F.explode(F.sequence(F.lit(0), F.col(other) - 1))})
        return each.drop("down", "over")

    down = placed(index.withColumn("is_query", F.lit(False)), "down", "over")
    return down.unionByName(placed(asked.withColumn("is_query", F.lit(True)), "over", "down"))


def _ranked(found: DataFrame, k: int, unique: bool = False) -> DataFrame:
    once = found if unique else found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return once.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def usable(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """(vec_id, v) of the rows that take part, v as doubles."""
    v = F.col(embedding).cast("array<double>")
    fine = F.forall(v, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists(v, lambda c: c != 0)
    return vectors.filter(F.col(vec_id).isNotNull() & F.coalesce(fine, F.lit(False))).select(F.col(vec_id).cast("long").alias("vec_id"), v.alias("v"))


def _hashed(turns: Turns, probes: int | None):
    """Rows -> one row for each cell: at (the table), cell, id, v, cells (of all tables: a row's, or a query's probes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, len(batch), 1024):
                part = batch.slice(lo, 1024)
                x = _matrix(part.column(1), turns.dim).astype(np.float64)
                if not len(x):
                    continue
                cells = turns.cells(x)[:, :, None] if probes is None else turns.probes(x, probes)
                n, tables, each = cells.shape
                row = np.repeat(np.arange(n), tables * each)
                ends = pa.array(np.arange(n + 1) * tables * each, pa.int32())
                every = pa.ListArray.from_arrays(ends, pa.array(cells.reshape(-1).astype(np.int32))).take(pa.array(row))
                at = np.tile(np.repeat(np.arange(tables, dtype=np.int32), each), n)
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(cells.reshape(-1)), part.column(0).take(pa.array(row)), part.column(1).take(pa.array(row)), every], ["at", "cell", "id", "v", "cells"])

    return run


def nearest(vectors: DataFrame, is_query, k: int = 20, tables: int = TABLES, probes: int = PROBES, turns: int = TURNS, block: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: the k rows of largest inner product with each query row, the row itself left out."""
    rows, spark = usable(vectors), vectors.sparkSession
    length = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, c: s + c * c))
    stats = rows.groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n"), F.min(length).alias("least"), F.max(length).alias("most")).orderBy(F.desc("n"), "dim").first()
    if stats is None:
        return _ranked(spark.createDataFrame([], "query_id long, vec_id long, score double"), k)
    dim, longest = stats["dim"], stats["most"]
    rows = rows.filter(F.size("v") == dim)
    asked = rows.filter(is_query).groupBy("vec_id").agg(F.min("v").alias("v")).select("vec_id", "v")
    hashes = Turns(dim, longest, longest - stats["least"] > 1e-6 * longest, tables, turns)
    if (cells := (2 * hashes.size) ** turns) >= 1 << 31:
        raise ValueError("cells are numbered by 31 bits; take fewer turns")
    probes = min(probes, cells)
    cell = "at int, cell long, id long, v array<double>, cells array<int>"
    index = rows.select("vec_id", "v").mapInArrow(_hashed(hashes, None), cell)
    probed = asked.mapInArrow(_hashed(hashes, probes), cell)
    out = "query_id long, vec_id long, score double"
    met = _blocks(index, probed, ["at", "cell"], block).groupBy("at", "cell", "at_down", "at_over").applyInArrow(lambda t: _ranked_block(t, k, dim, tables, probes), out)
    ids = rows.agg(F.count("*").alias("n"), F.countDistinct("vec_id").alias("d")).first()
    unique = ids["n"] == ids["d"]
    best = materialise(_ranked(met, k, unique), "nearest")
    enough = best.groupBy("query_id").count().filter(F.col("count") >= min(k, ids["d"] - 1))
    short = materialise(asked.join(enough, F.col("vec_id") == F.col("query_id"), "left_anti"), "short")
    if short.isEmpty() or ids["d"] < 2:
        return best
    plain = lambda df: df.select(F.lit(-1).alias("at"), F.pmod(F.xxhash64("vec_id"), F.lit(shuffle_width(spark))).alias("cell"), F.col("vec_id").alias("id"), "v", F.array().cast("array<int>").alias("cells"))
    everywhere = plain(short).withColumn("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shuffle_width(spark) - 1).cast("long"))))
    full = _blocks(plain(rows), everywhere, ["at", "cell"], block).groupBy("at", "cell", "at_down", "at_over").applyInArrow(lambda t: _ranked_block(t, k, dim, tables, probes), out)
    rest = best.join(short.select(F.col("vec_id").alias("query_id")), "query_id", "left_anti")
    return rest.unionByName(_ranked(full, k, unique))
