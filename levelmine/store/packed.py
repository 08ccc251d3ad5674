"""Edges packed in cells, and triangles counted on them without a row for any edge or triangle.

A vertex is in one of `blocks` blocks by a hash of its id, and edges go from the lesser (block, id) to the greater, so that
cell (i, j) with i <= j holds the edges between two blocks. A cell has its own numbering of both sides' vertices and the
differences of its sorted edge numbers, byte planes apart and compressed: one or two bytes an edge.

Triangles of blocks (a, b, c) meet the cells ab, ac and bc in one task: ac and bc become bitmaps, and each edge of ab counts
the bits that its ends' rows share. Memory of a task is of a block's vertices squared, in bits.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Vertices of a block on average, at most.
BLOCK = 16384
#: Edges that are sorted together, edges of a step of the count, and bytes of a step of building a bitmap.
SORTED, STEP, DENSE = 4 << 20, 256, 16 << 20
CELL = "i int, j int, n long, edges binary"
_CODEC = "zstd"


def _give_back() -> None:
    """What a worker has freed goes back before its next group."""
    pa.default_memory_pool().release_unused()


def block_count(vertices: int) -> int:
    return max(1, -(-vertices // BLOCK))


def _block(ids: np.ndarray, blocks: int) -> np.ndarray:
    x = ids.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((x >> np.uint64(33)) % np.uint64(blocks)).astype(np.int32)


def _planes(values: np.ndarray) -> bytes:
    """Sorted numbers as compressed byte planes of their differences."""
    steps = np.diff(values, prepend=values[:1] * 0).view(np.uint8).reshape(len(values), 8)
    raw = np.ascontiguousarray(steps.T).tobytes()
    return pa.compress(raw, codec=_CODEC, asbytes=True)


def _numbers(data: bytes, n: int) -> np.ndarray:
    raw = np.frombuffer(pa.decompress(data, decompressed_size=8 * n, codec=_CODEC, asbytes=True), np.uint8)
    return np.cumsum(np.ascontiguousarray(raw.reshape(8, n).T).view(np.int64).reshape(n))


def pack(u: np.ndarray, v: np.ndarray) -> bytes:
    """Distinct edges, of one cell."""
    us, iu = np.unique(u, return_inverse=True)
    vs, iv = np.unique(v, return_inverse=True)
    codes = np.unique(iu.astype(np.int64) * len(vs) + iv)
    parts = [_planes(x) for x in (us, vs, codes)]
    head = np.array([len(us), len(vs), len(codes), *map(len, parts)], np.int64)
    return head.tobytes() + b"".join(parts)


def unpack(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Vertices of both sides, and each edge's places in them."""
    n_u, n_v, n, a, b, c = np.frombuffer(data[:48], np.int64).tolist()
    at = np.cumsum([48, a, b, c])
    us, vs, codes = (_numbers(data[lo:hi], k) for lo, hi, k in zip(at[:-1], at[1:], (n_u, n_v, n), strict=True))
    return us, vs, codes // n_v, codes % n_v


def by_cell(a: np.ndarray, b: np.ndarray, blocks: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(i, j, u, v) of the edges between a and b; loops are left out."""
    real = a != b
    a, b = np.minimum(a[real], b[real]), np.maximum(a[real], b[real])
    i, j = _block(a, blocks), _block(b, blocks)
    turn = i > j
    a, b, i, j = np.where(turn, b, a), np.where(turn, a, b), np.minimum(i, j), np.maximum(i, j)
    cell = i.astype(np.int64) * blocks + j
    order = np.argsort(cell, kind="stable")
    starts = np.flatnonzero(np.diff(cell[order], prepend=-1))
    for lo, hi in zip(starts, np.append(starts, len(order))[1:], strict=True):
        at = order[lo:hi]
        yield int(i[at[0]]), int(j[at[0]]), a[at], b[at]


def cells_of(a: np.ndarray, b: np.ndarray, blocks: int) -> pa.Table:
    rows = [(i, j, len(u), pack(u, v)) for i, j, u, v in by_cell(a, b, blocks)]
    i, j, n, data = zip(*rows, strict=True) if rows else ((), (), (), ())
    return pa.table({"i": pa.array(i, pa.int32()), "j": pa.array(j, pa.int32()), "n": pa.array(n, pa.int64()), "edges": pa.array(data, pa.binary())})


def packed(pairs: DataFrame, blocks: int) -> DataFrame:
    """Pieces of cells from rows (src, dst), made where the rows are; repeats are left out within a piece."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, n = [], 0

        def out() -> Iterator[pa.RecordBatch]:
            both = pa.Table.from_batches(kept)
            yield from cells_of(both.column(0).to_numpy(), both.column(1).to_numpy(), blocks).to_batches()

        for batch in batches:
            if batch.num_rows:
                kept.append(batch)
                n += batch.num_rows
            if n >= SORTED:
                yield from out()
                kept, n = [], 0
        if n:
            yield from out()
        _give_back()

    rows = pairs.filter("src is not null and dst is not null").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    return rows.mapInArrow(run, CELL)


def _united(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Vertices of both sides, and each distinct edge's places, in order."""
    if len(pieces) == 1:
        return unpack(pieces[0])
    found = [unpack(p) for p in pieces]
    us, vs = (np.unique(np.concatenate([f[k] for f in found])) for k in (0, 1))
    codes = [np.searchsorted(us, u)[iu] * len(vs) + np.searchsorted(vs, v)[iv] for u, v, iu, iv in found]
    codes = np.unique(np.concatenate(codes))
    return us, vs, codes // len(vs), codes % len(vs)


def _merge(table: pa.Table) -> pa.Table:
    """The edges of one cell that are in no piece marked as old."""
    old = table["old"].to_numpy(zero_copy_only=False)
    pieces = table["edges"].to_pylist()
    us, vs, iu, iv = _united([p for p, o in zip(pieces, old, strict=True) if not o] or [pack(np.zeros(0, np.int64), np.zeros(0, np.int64))])
    for p in (p for p, o in zip(pieces, old, strict=True) if o):
        u, v, ju, jv = unpack(p)
        at_u, at_v = (np.minimum(np.searchsorted(x, y), max(0, len(x) - 1)) for x, y in ((us, u), (vs, v)))
        if not len(us):
            break
        both = (us[at_u] == u)[ju] & (vs[at_v] == v)[jv]
        fresh = ~np.isin(iu * len(vs) + iv, at_u[ju[both]] * len(vs) + at_v[jv[both]], assume_unique=True)
        iu, iv = iu[fresh], iv[fresh]
    data = [pack(us[iu], vs[iv])] if len(iu) else []
    k = len(data)
    out = pa.table({"i": table["i"].slice(0, k), "j": table["j"].slice(0, k), "n": pa.array([len(iu)] * k, pa.int64()), "edges": pa.array(data, pa.binary())})
    _give_back()
    return out


def merged(pieces: DataFrame, old: DataFrame | None = None) -> DataFrame:
    """One row a cell; edges of `old` cells are taken out."""
    rows = pieces.withColumn("old", F.lit(False))
    if old is not None:
        rows = rows.unionByName(old.withColumn("old", F.lit(True)))
    return rows.groupBy("i", "j").applyInArrow(_merge, CELL)


def rows_of(cells: DataFrame) -> DataFrame:
    """(src, dst) with src < dst."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0).to_pylist():
                us, vs, iu, iv = unpack(data)
                for lo in range(0, len(iu), 1 << 16):
                    u, v = us[iu[lo : lo + (1 << 16)]], vs[iv[lo : lo + (1 << 16)]]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v))], ["src", "dst"])

    return cells.select("edges").mapInArrow(run, "src long, dst long")


def degrees(cells: DataFrame) -> DataFrame:
    """(v, deg)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0).to_pylist():
                us, vs, iu, iv = unpack(data)
                n = np.concatenate([np.bincount(iu, minlength=len(us)), np.bincount(iv, minlength=len(vs))])
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([us, vs])), pa.array(n.astype(np.int64))], ["v", "n"])

    return cells.select("edges").mapInArrow(run, "v long, n long").groupBy("v").agg(F.sum("n").alias("deg"))


def _bitmap(rows: np.ndarray, cols: np.ndarray, shape: tuple[int, int]) -> np.ndarray:
    """Bits of sorted rows, in words."""
    width = 64 * -(-shape[1] // 64)
    out = np.zeros((shape[0], width // 64), np.uint64)
    step = max(1, DENSE // max(1, width))
    for lo in range(0, shape[0], step):
        a, b = np.searchsorted(rows, (lo, lo + step))
        if a == b:
            continue
        flat = np.zeros((min(step, shape[0] - lo), width), np.bool_)
        flat[rows[a:b] - lo, cols[a:b]] = True
        out[lo : lo + step] = np.packbits(flat, axis=1).view(np.uint64)
    return out


def _shared(x: np.ndarray, y: np.ndarray, u: np.ndarray, v: np.ndarray) -> int:
    """Bits that rows u of x and rows v of y share, over all pairs."""
    n = 0
    for lo in range(0, len(u), STEP):
        both = x[u[lo : lo + STEP]]
        both &= y[v[lo : lo + STEP]]
        n += int(np.bitwise_count(both).sum(dtype=np.int64))
    return n


def _closed(table: pa.Table) -> pa.Table:
    """Triangles of three blocks with at least one edge that is not old, each once."""
    a, b, c = (table[x][0].as_py() for x in ("a", "b", "c"))
    parts: dict[tuple[int, int, bool], list[bytes]] = {}
    for i, j, old, data in zip(*(table[x].to_pylist() for x in ("i", "j", "old", "edges")), strict=True):
        parts.setdefault((i, j, old), []).append(data)
    found = {k: _united(p) for k, p in parts.items()}
    side = lambda block: np.unique(np.concatenate([np.zeros(0, np.int64), *[f[0] for (i, _, _), f in found.items() if i == block], *[f[1] for (_, j, _), f in found.items() if j == block]]))
    ids = {x: side(x) for x in {a, b, c}}

    def places(i: int, j: int, old: bool) -> tuple[np.ndarray, np.ndarray]:
        if (i, j, old) not in found:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        us, vs, iu, iv = found[i, j, old]
        return np.searchsorted(ids[i], us)[iu], np.searchsorted(ids[j], vs)[iv]

    total = 0
    is_old = any(old for _, _, old in found)
    bits = lambda i, old: _bitmap(*places(i, c, old), (len(ids[i]), len(ids[c])))
    new_a, new_b = bits(a, False), bits(b, False) if a != b else None
    new_b = new_a if new_b is None else new_b
    if is_old:
        old_a = bits(a, True)
        old_b = bits(b, True) if a != b else old_a
        all_a = old_a | new_a
        all_b = old_b | new_b if a != b else all_a
        u, v = places(a, b, True)
        touched = new_a.any(axis=1)[u]
        total += _shared(new_a, all_b, u[touched], v[touched])
        touched = new_b.any(axis=1)[v]
        total += _shared(old_a, new_b, u[touched], v[touched])
    else:
        all_a, all_b = new_a, new_b
    total += _shared(all_a, all_b, *places(a, b, False))
    _give_back()
    return pa.table({"n": pa.array([total], pa.int64())})


def triangles(cells: DataFrame, blocks: int, old: DataFrame | None = None) -> int:
    """Triangles of cells and old ones together with at least one edge of `cells`."""
    rows = cells.withColumn("old", F.lit(False))
    if old is not None:
        rows = rows.unionByName(old.withColumn("old", F.lit(True)))
    three = rows.select("i", "j", "old", "edges", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("x"))
    three = three.withColumn("s", F.array_sort(F.array("i", "j", "x"))).select("i", "j", "old", "edges", *[F.col("s")[k].alias(n) for k, n in enumerate("abc")])
    return three.groupBy("a", "b", "c").applyInArrow(_closed, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]
