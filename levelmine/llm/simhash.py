"""SimHash fingerprints, and their links by BK-trees.

Fingerprints: 64 majority bits over the XXH64 of all word shingles, repeats included.
Links: fingerprints within `radius` bits agree in one of radius + 1 blocks of bits, so each block value is a shard.
A shard's fingerprints form a BK-tree: children are keyed by their integer Hamming distance to the parent, and a search
follows only the edges within the radius. Trees are built and searched for all shards of a task at once, level by level.
Shards are dealt out by a shuffle, not broadcast: their total grows with the data. A shard of more than SHARD
fingerprints is cut into pieces and each pair of pieces is a task's unit of its own, so one hot block spreads.
Equal fingerprints are one vertex, whatever their number. Tasks return spanning edges, never all pairs. As fingerprints
grow in number, the bits are cut into more blocks, so that the keys grow longer and shards stay small.

Defined results. Null or wordless text: fingerprint 0, linked like any other. Null doc_id: it takes part and is
returned, but names a component only if no other id does. Repeated rows are returned as often as given. An empty table
gives no rows. A long text is cut into shingles whole, in one task, whose memory is a small multiple of the text.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.llm.components import components
from levelmine.llm.kernel import NON_SPACE, Words, word_blocks, xxh64
from levelmine.session import materialise, shuffle_width

SHARD = 1024
_U = np.uint64


def shingles(column: pa.Array, shingle: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, edges, hashes) of blocks of texts: row i's shingles are hashes[edges[i] : edges[i + 1]]."""
    for lo, hi, words in word_blocks(column, lower=True):
        body, at = words.joined()
        words = Words(body, at, NON_SPACE)
        count = words.counts()
        grams = np.where(count == 0, 0, np.maximum(count - shingle + 1, 1))
        edge = np.concatenate([[0], np.cumsum(grams)])
        row = np.repeat(np.arange(hi - lo), grams)
        first = np.arange(edge[-1]) - edge[row] + words.ptr[row]
        last = np.minimum(first + shingle, words.ptr[row + 1]) - 1
        yield lo, edge, xxh64(body, words.start[first], words.end[last]) if len(first) else np.zeros(0, _U)


def fingerprints(column: pa.Array, shingle: int = 3) -> np.ndarray:
    """The 64-bit fingerprint of each text."""
    out = np.zeros(len(column), _U)
    for lo, edge, hashes in shingles(column, shingle):
        octets = hashes.view(np.uint8).reshape(-1, 8)
        for i in np.flatnonzero(np.diff(edge)).tolist():
            a, b = edge[i], edge[i + 1]
            ones = np.unpackbits(octets[a:b], axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
            out[lo + i] = np.packbits(ones * 2 > b - a, bitorder="little").view(_U)[0]
    return out


class BKForest:
    """BK-trees over fp, one per group; node i is item i, the first item of a group is its root."""

    def __init__(self, fp: np.ndarray, group: np.ndarray):
        self.fp = fp
        self.groups, roots, which = np.unique(group, return_index=True, return_inverse=True)
        self.roots = roots
        at = roots[which]
        left = np.flatnonzero(at != np.arange(len(fp)))
        edges, nodes = [], []
        while len(left):
            distance = np.bitwise_count(fp[left] ^ fp[at[left]]).astype(np.int64)
            key, first, which = np.unique(at[left] * 65 + distance, return_index=True, return_inverse=True)
            edges.append(key)
            nodes.append(left[first])
            at[left] = left[first][which]
            left = np.delete(left, first)
        edges = np.concatenate(edges) if edges else np.zeros(0, np.int64)
        order = np.argsort(edges, kind="stable")
        self.edges, self.child = edges[order], (np.concatenate(nodes) if nodes else edges)[order]

    def search(self, fp: np.ndarray, group: np.ndarray, radius: int, step: int = 20_000) -> tuple[np.ndarray, np.ndarray]:
        """(query, node) pairs within the radius, queries against their own group's tree."""
        hit_q, hit_n = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for lo in range(0, len(fp), step):
            part = np.arange(lo, min(lo + step, len(fp)))
            slot = np.searchsorted(self.groups, group[part])
            ok = (slot < len(self.groups)) & (self.groups[np.minimum(slot, len(self.groups) - 1)] == group[part]) if len(self.groups) else np.zeros(len(part), bool)
            query, node = part[ok], self.roots[slot[ok]]
            while len(query):
                distance = np.bitwise_count(fp[query] ^ self.fp[node]).astype(np.int64)
                near = distance <= radius
                hit_q.append(query[near])
                hit_n.append(node[near])
                a = np.searchsorted(self.edges, node * 65 + np.maximum(distance - radius, 0), "left")
                b = np.searchsorted(self.edges, node * 65 + np.minimum(distance + radius, 64), "right")
                wide = b - a
                query = np.repeat(query, wide)
                node = self.child[np.repeat(a - np.concatenate([[0], np.cumsum(wide)[:-1]]), wide) + np.arange(len(query))]
        return np.concatenate(hit_q), np.concatenate(hit_n)


def spanning(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least member of each item's component."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        while (jump := new[new]).tobytes() != new.tobytes():
            new = jump
        if np.array_equal(new, root):
            return root
        root = new


def _linked(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held)
        unit, fp, side = (table[c].to_numpy() for c in ("unit", "fp", "side"))
        fp = fp.view(_U)
        tree, ask = np.flatnonzero(side != 1), np.flatnonzero(side != 0)  # 2: both
        forest = BKForest(fp[tree], unit[tree])
        q, node = forest.search(fp[ask], unit[ask], radius)
        value, item = np.unique(fp, return_inverse=True)
        a, b = item[ask[q]], item[tree[node]]
        root = spanning(len(value), a, b)
        moved = np.flatnonzero(root != np.arange(len(root)))
        yield pa.RecordBatch.from_arrays([pa.array(value[moved].view(np.int64)), pa.array(value[root[moved]].view(np.int64))], ["a", "b"])

    return run


def links(distinct: DataFrame, radius: int = 2, shard: int = SHARD, blocks: int | None = None) -> DataFrame:
    """fp (distinct longs) -> (a, b): edges that span every component of fingerprints within radius bits.

    blocks: into so many the bits are cut, radius + 1 unless given. Fingerprints within the radius agree in all but
    `radius` of them, so every choice of the others is a key. More blocks mean longer keys and smaller shards, but more
    keys: for radius 2, three blocks give 3 keys of 21 bits, four give 6 of 32 bits, for more than some 10**8 fingerprints.
    """
    blocks = blocks or radius + 1
    cuts = [64 * i // blocks for i in range(blocks + 1)]
    values = []
    for chosen in combinations(range(blocks), blocks - radius):
        key = F.lit(0).cast("long")
        for i in chosen:
            width = cuts[i + 1] - cuts[i]
            key = F.shiftleft(key, width).bitwiseOR(F.shiftrightunsigned("fp", cuts[i]).bitwiseAND((1 << width) - 1))
        values.append(key)
    keyed = distinct.select("fp", F.posexplode(F.array(*values)).alias("block", "value"))
    many = keyed.groupBy("block", "value").agg(F.count("*").alias("n")).filter("n > 1").select("block", "value", F.ceil(F.col("n") / shard).cast("int").alias("pieces"))
    own = F.pmod(F.xxhash64("fp"), F.col("pieces")).cast("int")
    held = keyed.join(many, ["block", "value"]).select("fp", "block", "value", own.alias("own"), F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)).alias("other"))
    unit = F.xxhash64("block", "value", F.least("own", "other"), F.greatest("own", "other"))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    dealt = held.select(unit.alias("unit"), "fp", side.cast("int").alias("side")).repartition(shuffle_width(distinct.sparkSession), "unit")
    return dealt.mapInArrow(_linked(radius), "a long, b long")


def _fingerprint_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fingerprints(batch.column(1)).view(np.int64))], ["doc_id", "fp"])


def blocks_for(distinct: int, radius: int, fill: int = 64) -> int:
    """The fewest blocks whose keys hold about `fill` of so many fingerprints each, if they were spread evenly."""
    blocks = radius + 1
    while blocks < radius + 5 and distinct > fill << 64 * (blocks - radius) // blocks:
        blocks += 1
    return blocks


def near_duplicates(docs: DataFrame, radius: int = 2, blocks: int | None = None) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (the least doc_id reachable through links).

    blocks: as in links; by the number of distinct fingerprints unless given. The links are the same for all."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    fps = materialise(rows.mapInArrow(_fingerprint_rows, "doc_id long, fp long"), "fingerprints")
    vertices = materialise(fps.groupBy("fp").agg(F.min("doc_id").alias("low")), "vertices")
    of = components(links(vertices.select("fp"), radius, blocks=blocks or blocks_for(vertices.count(), radius))).select(F.col("vertex").alias("fp"), F.col("least").alias("top"))
    known = vertices.join(of, "fp", "left").select("fp", F.coalesce("top", "fp").alias("top"), "low")
    named = known.groupBy("top").agg(F.min("low").alias("component_id"))
    full = known.select("fp", "top").join(named, "top").select("fp", "component_id")
    return fps.join(full, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
