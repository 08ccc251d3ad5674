"""Edges in packed cells, and what is counted on them."""

from __future__ import annotations

import datetime
import itertools
import math
import random
import time

import pytest

from levelmine.operators import mining, streams
from levelmine.sources.graphs import coactive_cells
from levelmine.store import packed
from levelmine.streaming.edges import EVENT
from levelmine.streaming.incremental import TriangleCount

START = datetime.datetime(2024, 1, 1)


def events(spark, path, rows):
    """rows: (user_id, seconds)."""
    made = [(i, None if s is None else START + datetime.timedelta(seconds=s), u, "view", 1.0, None) for i, (u, s) in enumerate(rows)]
    spark.createDataFrame(made, EVENT).write.parquet(f"file://{path}/events.parquet")
    return f"file://{path}"


def triangles(edges):
    near = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    return sum(len(near[a] & near[b]) for a, b in edges) // 3, sum(len(x) * (len(x) - 1) // 2 for x in near.values())


def test_cells_hold_the_edges_and_their_triangles(spark):
    rng = random.Random(3)
    ids = [rng.randrange(-(1 << 62), 1 << 62) for _ in range(70)]
    pairs = [tuple(rng.sample(ids, 2)) for _ in range(700)]
    want = {(min(p), max(p)) for p in pairs}
    rows = [*pairs, *pairs[:90], (ids[0], ids[0]), (None, ids[1])]
    cells = packed.merged(packed.packed(spark.createDataFrame(rows, "src long, dst long"), 4))
    assert cells.count() == 10
    got = [tuple(r) for r in packed.rows_of(cells).collect()]
    assert len(got) == len(want) and set(got) == want
    assert packed.triangles(cells, 4) == triangles(want)[0] > 100
    old = packed.merged(packed.packed(spark.createDataFrame([p for p in want if sum(p) % 3], "src long, dst long"), 4))
    fresh = packed.merged(cells, old)
    assert {tuple(r) for r in packed.rows_of(fresh).collect()} == {p for p in want if not sum(p) % 3}
    assert packed.triangles(fresh, 4, old) == triangles(want)[0] - triangles({p for p in want if sum(p) % 3})[0]
    assert packed.merged(old, cells).count() == 0 and packed.triangles(packed.merged(old, cells), 4, cells) == 0


@pytest.mark.parametrize("block", [9, 1000])
def test_coactive_cells_at_the_edges_of_slices(spark, tmp_path, monkeypatch, block):
    monkeypatch.setattr(packed, "BLOCK", block)
    rng = random.Random(block)
    rows = [(rng.randrange(30), rng.choice((rng.randrange(4000), 10 * rng.randrange(400)))) for _ in range(500)] + [(None, 5), (3, None), (7, 50), (7, 50)]
    sf_dir = events(spark, tmp_path, rows)
    real = [(u, s) for u, s in rows if u is not None and s is not None]
    want = {(a, b) for (a, s), (b, t) in itertools.product(real, real) if a < b and abs(s - t) <= 10}
    cells, blocks = coactive_cells(spark.read.parquet(f"{sf_dir}/events.parquet"))
    assert blocks == (4 if block == 9 else 1)
    assert {tuple(r) for r in packed.rows_of(cells).collect()} == want
    n, wedges = triangles(want)
    assert {tuple(r) for r in mining.motif_3_coactivity(spark, sf_dir).collect()} == {("triangle", n), ("chain", wedges - 3 * n)}


def test_motifs_of_many_users_at_one_instant(spark, tmp_path):
    n = 3000
    sf_dir = events(spark, tmp_path, [(u, 0) for u in range(n)] + [(n, 10), (n + 1, 21)])
    began = time.monotonic()
    assert [tuple(r) for r in mining.motif_3_coactivity(spark, sf_dir).collect()] == [("triangle", math.comb(n + 1, 3))]
    assert time.monotonic() - began < 90  # 4.5e9 sets of three, each of which was a row before


def test_motifs_without_an_edge(spark, tmp_path):
    assert mining.motif_3_coactivity(spark, events(spark, tmp_path, [(1, 0), (1, 3), (2, 100)])).count() == 0


def test_stream_of_many_users_at_one_instant(spark, tmp_path):
    n = 1200
    sf_dir = events(spark, tmp_path, [(u, 0) for u in range(n)] + [(n + k, 600 * k) for k in range(1, 90)] + [(k, 3000) for k in range(40)])
    began = time.monotonic()
    got = streams.stream_triangles(spark, sf_dir).first()
    assert tuple(got) == (math.comb(n, 3) + math.comb(40, 2), n * math.comb(n - 1, 2) + 40 * (n - 1) + math.comb(40, 2))
    assert time.monotonic() - began < 120  # a row for each of 2.9e8 triangles, three times, before


def test_incremental_counts_in_blocks(spark):
    rng = random.Random(6)
    pairs = [tuple(rng.sample(range(60), 2)) for _ in range(900)]
    count, whole = TriangleCount(spark, blocks=3), set()
    for n in range(3):
        part = pairs[200 * n : 200 * n + 300]
        count.add(spark.createDataFrame(part, "src long, dst long"), n)
        whole |= {(min(p), max(p)) for p in part}
        assert (count.triangles, count.wedges) == triangles(whole)
    assert {tuple(r) for r in count.edges.collect()} == whole
