"""Documents that share word shingles: each one's class and number of links, without a row for a pair.

Tasks hash the shingles of a batch of texts and send them packed by hash; a bucket of hashes finds those that two
documents hold at least, and shingles of the same holders become one, with a weight. A block of documents then gets
the holders of every such shingle of its own, adds up the weights by numpy, and keeps the number of its documents'
links and the edges of a forest. All pairs are counted, however many documents hold a shingle.

Documents without an id have no links. Texts that share an id are one document.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.graph.components import components
from levelmine.session import materialise, shuffle_width

WORDS = 8
#: Bytes of texts that are hashed at once, and shingles that a task holds before it sends them on.
TEXT_BYTES, SEND = 1 << 22, 1 << 20
_U = np.uint64
_SPACE = np.isin(np.arange(256), list(b" \t\n\f\r"))
_BYTES = np.random.default_rng(3).integers(1, 2**63, 256, dtype=np.int64).astype(_U)
_IN_WORD, _IN_SHINGLE = 0x9E3779B97F4A7C15, 0xD1342543DE82EF95
_HELD = "bucket int, h binary, k binary, weight binary, size binary, holder binary"


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> _U(shift))) * _U(factor)
    return x ^ (x >> _U(31))


def _powers(base: int, n: int) -> np.ndarray:
    steps = np.full(n, base, _U)
    steps[:1] = 1
    return np.multiply.accumulate(steps)


def shingle_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every WORDS consecutive words of a text."""
    texts = texts.cast(pa.large_binary())
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    if not len(texts) or data is None or at[0] == at[-1]:
        return np.zeros(0, np.int64), np.zeros(0, _U)
    buf, at = np.frombuffer(data, np.uint8)[at[0] : at[-1]], at - at[0]
    inside = ~_SPACE[buf]
    cut = np.zeros(len(buf) + 1, np.bool_)
    cut[at] = True
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1] | cut[1:-1]
    last[:-1] &= ~inside[1:] | cut[1:-1]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    if len(start) < WORDS:
        return np.zeros(0, np.int64), np.zeros(0, _U)
    size = end - start
    place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    word = np.add.reduceat(_BYTES[buf[inside]] * _powers(_IN_WORD, int(size.max()))[place], np.cumsum(size) - size)
    word = _mixed(word + size.astype(_U))
    row = np.searchsorted(at, start, "right") - 1
    shingle = np.zeros(len(word) - WORDS + 1, _U)
    for k, p in enumerate(_powers(_IN_SHINGLE, WORDS)):
        shingle += word[k : k + len(shingle)] * p
    whole = row[: len(shingle)] == row[WORDS - 1 :]
    return row[: len(shingle)][whole], _mixed(shingle[whole])


def _narrow(ids: np.ndarray) -> np.ndarray:
    return ids.astype(np.int32) if not len(ids) or -(1 << 31) <= ids.min() and ids.max() < 1 << 31 else ids


def _wide(cell: bytes, n: int) -> np.ndarray:
    return np.frombuffer(cell, np.int32 if len(cell) == 4 * n else np.int64).astype(np.int64)


def _cells(table: pa.Table, name: str, kind: type) -> list[np.ndarray]:
    return [np.frombuffer(x, kind) for x in table[name].to_pylist()]


def _joined(parts: list[np.ndarray], kind: type) -> np.ndarray:
    return np.concatenate([np.zeros(0, kind), *parts])


def _sent(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def flush() -> pa.RecordBatch:
            doc, g = (_joined([x[i] for x in held], kind) for i, kind in ((0, np.int64), (1, _U)))
            held.clear()
            bucket = (g >> _U(40)) % _U(buckets)
            order = np.argsort(bucket, kind="stable")
            doc, g, ends = doc[order], g[order], np.searchsorted(bucket[order], np.arange(buckets + 1, dtype=_U))
            rows = [(k, g[a:b].tobytes(), _narrow(doc[a:b]).tobytes()) for k, (a, b) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)) if a < b]
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], ["bucket", "g", "doc"])

        for batch in batches:
            ids, texts = batch.column(0).to_numpy(), batch.column(1)
            size = np.cumsum(pc.binary_length(texts).to_numpy(), dtype=np.int64)
            lo = 0
            while lo < len(ids):
                hi = max(lo + 1, int(np.searchsorted(size, (size[lo - 1] if lo else 0) + TEXT_BYTES, "right")))
                row, g = shingle_hashes(texts.slice(lo, hi - lo))
                held.append((ids[lo:hi][row], g))
                if sum(len(x[1]) for x in held) >= SEND:
                    yield flush()
                lo = hi
        yield flush()

    return run


def _held_in_bucket(buckets: int):
    """Of a bucket's shingles those of two documents or more; those of the same holders as one."""

    def run(table: pa.Table) -> pa.Table:
        g = _cells(table, "g", _U)
        doc = _joined([_wide(x, len(y)) for x, y in zip(table["doc"].to_pylist(), g, strict=True)], np.int64)
        g = _joined(g, _U)
        order = np.lexsort((doc, g))
        g, doc = g[order], doc[order]
        new = np.ones(len(g), np.bool_)
        new[1:] = (g[1:] != g[:-1]) | (doc[1:] != doc[:-1])
        g, doc = g[new], doc[new]
        start = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
        size = np.diff(np.append(start, len(g)))
        code = doc.astype(_U)
        h, k = (np.add.reduceat(_mixed(code * _U(2) + _U(salt)), start) for salt in (0, 1))
        many = size >= 2
        return _dealt(h[many], k[many], np.ones(many.sum(), np.int64), start[many], size[many], doc, buckets)

    return run


def _merged(h: np.ndarray, k: np.ndarray, weight: np.ndarray, start: np.ndarray, size: np.ndarray, holder: np.ndarray):
    """Rows of equal (h, k, size) as one, with the sum of their weights; holders of row i are at start[i], size[i] of them."""
    order = np.lexsort((size, k, h))
    h, k, weight, start, size = (x[order] for x in (h, k, weight, start, size))
    new = np.ones(len(h), np.bool_)
    new[1:] = (h[1:] != h[:-1]) | (k[1:] != k[:-1]) | (size[1:] != size[:-1])
    first = np.flatnonzero(new)
    weight = np.add.reduceat(weight, first) if len(first) else weight
    return h[first], k[first], weight, *_gathered(start[first], size[first], holder)


def _gathered(start: np.ndarray, size: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sizes, and values[start : start + size] of all rows one after the other."""
    ends = np.cumsum(size)
    return size, values[np.repeat(start - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)]


def _dealt(h: np.ndarray, k: np.ndarray, weight: np.ndarray, start: np.ndarray, size: np.ndarray, holder: np.ndarray, buckets: int) -> pa.Table:
    h, k, weight, size, holder = _merged(h, k, weight, start, size, holder)
    start, bucket, rows = np.cumsum(size) - size, h % _U(buckets), []
    order = np.argsort(bucket, kind="stable")
    ends = np.searchsorted(bucket[order], np.arange(buckets + 1, dtype=_U)).tolist()
    for b in range(buckets):
        at = order[ends[b] : ends[b + 1]]
        if len(at):
            own = _gathered(start[at], size[at], holder)[1]
            rows.append((b, *[x.tobytes() for x in (h[at], k[at], weight[at], size[at], _narrow(own))]))
    return pa.table([pa.array([r[i] for r in rows], pa.int32() if i == 0 else pa.binary()) for i in range(6)], ["bucket", "h", "k", "weight", "size", "holder"])


def _for_blocks(blocks: int):
    """Shingles of the same holders, from all buckets, for each block that has one of the holders."""

    def run(table: pa.Table) -> pa.Table:
        h, k = (_joined(_cells(table, c, _U), _U) for c in ("h", "k"))
        weight, sizes = _joined(_cells(table, "weight", np.int64), np.int64), _cells(table, "size", np.int64)
        holder = _joined([_wide(x, int(s.sum())) for x, s in zip(table["holder"].to_pylist(), sizes, strict=True)], np.int64)
        size = _joined(sizes, np.int64)
        _, _, weight, size, holder = _merged(h, k, weight, np.cumsum(size) - size, size, holder)
        start, rows = np.cumsum(size) - size, []
        block = (_mixed(holder.astype(_U)) % _U(blocks)).astype(np.int64)
        pairs = np.unique(block * len(size) + np.repeat(np.arange(len(size)), size))
        ends = np.searchsorted(pairs, np.arange(blocks + 1) * len(size)).tolist()
        for b in range(blocks):
            at = pairs[ends[b] : ends[b + 1]] - b * len(size)
            if len(at):
                rows.append((b, weight[at].tobytes(), size[at].tobytes(), _narrow(_gathered(start[at], size[at], holder)[1]).tobytes()))
        return pa.table([pa.array([r[i] for r in rows], pa.int32() if i == 0 else pa.binary()) for i in range(4)], ["block", "weight", "size", "holder"])

    return run


def _counted(blocks: int, shared: int):
    """(a, null, links) of each of the block's documents, and (a, b, null) of a forest of its links."""

    def run(table: pa.Table) -> pa.Table:
        weight, sizes = _joined(_cells(table, "weight", np.int64), np.int64), _cells(table, "size", np.int64)
        holder = _joined([_wide(x, int(s.sum())) for x, s in zip(table["holder"].to_pylist(), sizes, strict=True)], np.int64)
        size = _joined(sizes, np.int64)
        start = np.cumsum(size) - size
        ids, holder = np.unique(holder, return_inverse=True)
        mine = (_mixed(ids.astype(_U)) % _U(blocks)).astype(np.int64) == table["block"][0].as_py()
        group = np.repeat(np.arange(len(size)), size)
        at = np.flatnonzero(mine[holder])
        at = at[np.argsort(holder[at], kind="stable")]
        doc, group = holder[at], group[at]
        edge = np.append(np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]])), len(doc)).tolist()
        total, place, root = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64), np.arange(len(ids))
        known: dict[bytes, int] = {}
        links = np.zeros(len(edge) - 1, np.int64)
        for i in range(len(edge) - 1):
            own = group[edge[i] : edge[i + 1]]
            key = own.tobytes()
            if key not in known:  # documents of the same shingles have the same links, each other's included
                size_of, other = _gathered(start[own], size[own], holder)
                np.add.at(total, other, np.repeat(weight[own], size_of))
                near = other[total[other] >= shared]
                place[near] = np.arange(len(near))
                near = near[place[near] == np.arange(len(near))]
                total[other] = 0
                known[key] = len(near)
                if len(near):
                    tops = root[near]
                    while (up := root[tops]).tobytes() != tops.tobytes():
                        tops = up
                    root[tops] = root[near] = tops.min()
            links[i] = max(0, known[key] - 1)  # itself
        while (up := root[root]).tobytes() != root.tobytes():
            root = up
        joined = np.flatnonzero(root != np.arange(len(ids)))
        none = lambda n: pa.nulls(n, pa.int64())
        docs, forest = ids[doc[edge[:-1]]], (ids[joined], ids[root[joined]])
        return pa.table({"a": pa.chunked_array([docs, forest[0]]), "b": pa.chunked_array([none(len(docs)), pa.array(forest[1])]), "links": pa.chunked_array([pa.array(links), none(len(joined))])})

    return run


def overlap_classes(docs: DataFrame, shared: int = 3) -> DataFrame:
    """(doc_id, class_id, links): for each document the least one that links reach, and with how many others it shares so many shingles."""
    width = shuffle_width(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("text")).filter("doc_id is not null and text is not null")
    sent = texts.mapInArrow(_sent(4 * width), "bucket int, g binary, doc binary")
    held = sent.groupBy("bucket").applyInArrow(_held_in_bucket(4 * width), _HELD)
    dealt = held.groupBy("bucket").applyInArrow(_for_blocks(width), "block int, weight binary, size binary, holder binary")
    found = materialise(dealt.groupBy("block").applyInArrow(_counted(width, shared), "a long, b long, links long"), "overlap")
    tops = components(found.filter("b is not null").select("a", "b")).select(F.col("vertex").alias("doc_id"), F.col("least").alias("top"))
    links = found.filter("b is null").select(F.col("a").alias("doc_id"), "links")
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id")).distinct().join(links, "doc_id", "left").join(tops, "doc_id", "left")
    return out.select("doc_id", F.coalesce("top", "doc_id").alias("class_id"), F.coalesce("links", F.lit(0)).cast("long").alias("links"))
