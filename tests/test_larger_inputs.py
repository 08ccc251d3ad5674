"""Inputs on which a query once failed or gave other rows than its SQL."""

from __future__ import annotations

import datetime
import math
import random
import time
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from levelmine.apps.motif import motifs, named
from levelmine.baselines import relational as baseline
from levelmine.baselines.relational import cliques
from levelmine.explore import loop
from levelmine.graph.model import PropertyGraph
from levelmine.operators import mining, relational, streams
from levelmine.pattern import spectral
from levelmine.pattern.encode import bits_of, matrix
from levelmine.sources.graphs import _nearest_in_block
from levelmine.streaming.edges import EVENT


def test_late_rows_are_counted_one_by_one(spark, tmp_path):
    at = lambda minutes: datetime.datetime(2024, 1, 1, 12) + datetime.timedelta(minutes=minutes)
    # of one minute and one event_id are several rows; the hour is [-180, -120) minutes from the newest
    rows = [(i % 3, at(m), i, "view", 1.0, None) for i, m in enumerate([-200, -181, -180, -180, -180, -179, -150, -150, -121, -120, -119, -30, 0])]
    spark.createDataFrame(rows, EVENT).write.parquet(f"file://{tmp_path}/events.parquet")
    assert streams.stream_late_rows(spark, f"file://{tmp_path}").first()["dropped"] == 7


def test_recursion_beyond_a_million_rows(spark, monkeypatch):
    hub, n = 5000, 1100
    pairs = spark.range(n).select(F.col("id").alias("src"), F.lit(hub).alias("dst")).union(spark.range(n).select(F.lit(hub), F.col("id") + hub + 1))
    graph = PropertyGraph.from_pairs(pairs)
    monkeypatch.setattr(relational, "_s", lambda spark, sf_dir: graph)
    assert dict(map(tuple, relational.recursive_paths(spark, "").collect())) == {2: 2 * n, 3: n * n}


def test_relational_cliques_beside_a_hub(spark):
    n = 1500
    pairs = spark.range(1, n).select(F.lit(0).alias("src"), F.col("id").alias("dst")).union(spark.createDataFrame([(1, 2), (1, 3), (2, 3), (3, 4)], "src long, dst long"))
    began = time.monotonic()
    assert [r["path"] for r in cliques(PropertyGraph.from_pairs(pairs), 4).collect()] == [[0, 1, 2, 3]]
    assert time.monotonic() - began < 90  # every wedge of the hub met all its neighbours before


def test_relational_motifs_beside_a_hub(spark, monkeypatch):
    monkeypatch.setattr(baseline, "PAIRS", 5000)  # the hub's sets are dealt to many pieces
    n = 250
    pairs = spark.range(1, n + 1).select(F.lit(0).alias("src"), F.col("id").alias("dst")).union(spark.createDataFrame([(1, 2), (1, 3), (2, 3), (3, 4)], "src long, dst long"))
    began = time.monotonic()
    got = dict(map(tuple, named(baseline.motifs(PropertyGraph.from_pairs(pairs), 4, "exact")).collect()))
    one = 4 * (n - 2) - 2 * 2 - 3  # threes beside the hub that hold one of the four edges; two hold two, one holds three
    assert got == {"star": math.comb(n, 3) - one - 3, "tailed_triangle": one + 1, "diamond": 2, "clique": 1}
    assert time.monotonic() - began < 120  # every star met all neighbours of the hub once more before


@pytest.mark.parametrize("k, n, edges", [(3, 14, 30), (4, 9, 24), (4, 14, 26), (5, 9, 14)])
def test_relational_motifs_of_random_graphs(spark, k, n, edges):
    pairs = random.Random(k * n).sample(list(combinations(range(n), 2)), edges)
    graph = PropertyGraph.from_pairs(spark.createDataFrame(pairs, "src long, dst long"))
    assert sorted(map(tuple, baseline.motifs(graph, k, "exact").collect())) == sorted(map(tuple, motifs(graph, k).collect()))


def test_sizes_of_levels_beside_a_hub(spark):
    """A hub of n leaves with a triangle behind it: the sets are counted, for no level of them can be made."""
    n, k = 500, 7
    pairs = spark.range(3, n + 3).select(F.lit(0).alias("src"), F.col("id").alias("dst")).union(spark.createDataFrame([(0, 1), (0, 2), (1, 2)], "src long, dst long"))
    # sets with the hub have any of the other two and any leaves; without it there are 1, 2, 1-2 and the leaves alone
    want = [math.comb(n + 2, i) + (n + 2 if i == 0 else int(i == 1)) for i in range(k)]
    assert [r["n"] for r in loop.level_sizes(PropertyGraph.from_pairs(pairs), k).orderBy("k").collect()] == want


@pytest.mark.parametrize("seed, edges", [(1, 9), (2, 11), (3, 13)])
def test_sizes_of_levels_of_trees_and_cycles(spark, seed, edges):
    pairs = random.Random(seed).sample(list(combinations(range(12), 2)), edges)

    def linked(some):
        seen, todo = set(), [some[0]]
        while todo:
            seen.add(v := todo.pop())
            todo += [w for p in pairs if v in p for w in p if w in some and w not in seen]
        return len(seen) == len(some)

    at = sorted({v for p in pairs for v in p})
    want = [sum(map(linked, combinations(at, i))) for i in range(1, 7)]
    graph = PropertyGraph.from_pairs(spark.createDataFrame(pairs, "src long, dst long"))
    assert [r["n"] for r in loop.level_sizes(graph, 6).orderBy("k").collect()] == want


def test_nearest_of_a_block_with_ties():
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.integers(-2, 3, (300, 6)) + 0.5, np.full((40, 6), 0.25)]).astype(np.float32)
    ids, n = rng.permutation(2 * len(x))[: len(x)], len(x)
    one = lambda asks: pa.table({"vec_id": ids, "x": pa.array(list(x), pa.list_(pa.float32())), "asks": np.full(n, asks)})
    got = _nearest_in_block(5)(pa.concat_tables([one(True), one(False)])).to_pandas()
    u = x.astype(float) / np.sqrt((x.astype(float) ** 2).sum(axis=1, keepdims=True))
    sim = np.einsum("ij,kj->ik", u, u)
    want = {(ids[i], ids[j]) for i in range(n) for j in sorted((j for j in range(n) if j != i), key=lambda j: (-sim[i, j], ids[j]))[:5]}
    assert len(got) == 5 * n and set(zip(got["vec_id"], got["other"], strict=True)) == want


def test_polynomials_worked_out_by_hand():
    """Chain, triangle, path, star, cycle, clique of four."""
    shapes = [(3, [(0, 1), (1, 2)]), (3, [(0, 1), (1, 2), (0, 2)]), (4, [(0, 1), (1, 2), (2, 3)]), (4, [(0, 1), (0, 2), (0, 3)]), (4, [(0, 1), (1, 2), (2, 3), (0, 3)]), (4, [(i, j) for j in range(4) for i in range(j)])]
    want = [(0, -2, 0), (0, -3, -2), (0, -3, 0, 1), (0, -3, 0, 0), (0, -4, 0, 0), (0, -6, -8, -3)]
    assert [spectral.charpoly(matrix(k, bits_of(k, edges))) for k, edges in shapes] == want


@pytest.mark.parametrize("name", ["charpoly_fixture", "eigenvalue_check"])
def test_small_graphs_are_read_from_the_lines(spark, tmp_path, name):
    at = datetime.datetime(2024, 1, 1)
    lines = [(1, n, at + datetime.timedelta(days=300 * n), "ANR"[n % 3]) for n in (1, 2, 3, 4, 5)] + [(2, n, at, "AN"[n % 2]) for n in (1, 2, 3, 4, 4)] + [(3, n, at, "A") for n in (1, 2, 3)] + [(4, 1, at, "A")]
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int, l_shipdate timestamp_ntz, l_returnflag string").write.parquet(f"file://{tmp_path}/lineitem.parquet")
    got = {(r["labels"], r["bits"]): r for r in getattr(mining, name)(spark, f"file://{tmp_path}").collect()}
    cycle, diamond, none = ("1-1-1-1", bits_of(4, [(0, 1), (1, 2), (2, 3), (0, 3)])), ("1-1-1-1", bits_of(4, [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)])), ("1-1-1", 0)
    assert set(got) == {cycle, diamond, none} and all(r["n"] == 1 for r in got.values())
    column, want = ("polynomial", ["0.-4.0.0", "0.-5.-4.0", "0.0.0"]) if name == "charpoly_fixture" else ("squares", [8, 10, 0])
    assert [got[f][column] for f in (cycle, diamond, none)] == want
