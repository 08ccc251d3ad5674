"""Motifs, cliques, triangles, frequent subgraphs, the programming interface, baselines and measures."""

from __future__ import annotations

import math
from collections import defaultdict
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from levelmine import api
from levelmine.apps import clique, fsm, motif, triangle
from levelmine.baselines import relational
from levelmine.explore import edge, loop
from levelmine.graph.model import PropertyGraph
from levelmine.measure import run, stats
from levelmine.pattern import exact
from levelmine.sources.graphs import load, part_copurchase, part_supplier, supplier_coorder, toy7, vector_knn
from levelmine.support import mni


@pytest.fixture(scope="module")
def toy(spark):
    return load(toy7, spark, "")


@pytest.fixture(scope="module")
def cop(spark, sf_dir):
    return load(part_copurchase, spark, sf_dir)


@pytest.fixture(scope="module")
def knn(spark, sf_dir):
    return load(vector_knn, spark, sf_dir)


def counts(df):
    return {r["motif"]: r["frequency"] for r in motif.named(df).collect()}


def test_toy_motifs(toy):
    assert counts(motif.motifs(toy, 3)) == {"chain": 5, "triangle": 3}
    four = {"diamond": 2, "tailed_triangle": 2, "path": 1}
    assert counts(motif.motifs(toy, 4)) == four
    assert counts(motif.motifs(toy, 4, fuse_last=False)) == four
    assert counts(motif.motifs(toy, 4, strategy="rejoin")) == four


def test_motifs_of_the_neighbour_graph(knn):
    """Counted once with throw-away scripts."""
    assert counts(motif.motifs(knn, 3)) == {"chain": 8156, "triangle": 124}
    assert counts(motif.motifs(knn, 4)) == {"path": 42257, "star": 12409, "tailed_triangle": 1707, "cycle": 148, "diamond": 28}


@pytest.mark.parametrize("engine", ["spectral", "exact", "verified", "search_tree"])
def test_engines_count_alike(cop, engine):
    got = sorted(r["frequency"] for r in motif.motifs(cop, 4, labelled=True, engine=engine).collect())
    assert got == sorted(r["frequency"] for r in motif.motifs(cop, 4, labelled=True).collect())


def test_wedges_and_triangles_add_up(knn):
    n = counts(motif.motifs(knn, 3))
    deg = [r["deg"] for r in knn.degrees().collect()]
    assert n["chain"] == sum(d * (d - 1) // 2 for d in deg) - 3 * n["triangle"]


def test_toy_cliques_and_triangles(toy):
    assert sorted(tuple(r[0]) for r in clique.cliques(toy, 3).collect()) == [(1, 2, 5), (2, 3, 5), (3, 4, 5)]
    assert clique.clique_count(toy, 4).first()["n"] == 0
    for method in ("intersect", "oriented", "join"):
        assert triangle.triangles(toy, method).first()["n"] == 3
    assert relational.triangles(toy).first()["n"] == 3
    with pytest.raises(ValueError):
        triangle.triangles(toy, "guess")


def test_cliques_of_the_dense_graph(spark, sf_dir):
    g = load(supplier_coorder, spark, sf_dir)
    near = defaultdict(set)
    for r in g.edges.collect():
        near[r["src"]].add(r["dst"])
        near[r["dst"]].add(r["src"])
    for k in (3, 4, 5):
        want = sorted(s for s in combinations(sorted(near), k) if all(b in near[a] for a, b in combinations(s, 2)))
        assert sorted(tuple(r[0]) for r in clique.cliques(g, k).collect()) == want
        assert sorted(tuple(r[0]) for r in clique.cliques(g, k, oriented=True).collect()) == want
        assert clique.clique_count(g, k).first()["n"] == len(want) == clique.clique_count(g, k, oriented=False).first()["n"]
        assert relational.cliques(g, k).count() == len(want)
    assert [clique.clique_count(g, k).first()["n"] for k in (3, 4, 5)] == [82, 107, 91]
    per = triangle.per_vertex(g)
    assert per.agg(F.sum("triangles")).first()[0] == 3 * 82


def test_bipartite_graph_has_no_triangle(spark, sf_dir):
    assert triangle.triangles(load(part_supplier, spark, sf_dir), "oriented").first()["n"] == 0


def test_match_finds_the_instances(toy):
    code = exact.canonical((1, 1, 1), 7)[0]
    assert sorted(tuple(sorted(r[0])) for r in motif.match(toy, code, 3).collect()) == [(1, 2, 5), (2, 3, 5), (3, 4, 5)]


def brute_mni(graph, n_edges):
    """{pattern: minimum image number} by walking all edge sets and all their automorphisms."""
    label = {r["id"]: r["label"] for r in graph.vertices.collect()}
    images = defaultdict(lambda: defaultdict(set))
    for r in loop.embeddings(graph, n_edges, mode="edge").select("verts", "labels", "bits").collect():
        code, place, orbit = exact.canonical(tuple(r["labels"]), r["bits"])
        assert [label[v] for v in r["verts"]] == list(r["labels"])
        for o, v in zip(orbit, r["verts"], strict=True):
            images[code][o].add(v)
    return {c: min(map(len, o.values())) for c, o in images.items()}


@pytest.mark.parametrize("n_edges", [1, 2, 3])
def test_frequent_patterns_against_brute_force(cop, n_edges):
    want = {c: n for c, n in brute_mni(cop, n_edges).items() if n >= 2}
    for how in ({}, {"prune": False}):
        found = fsm.fsm(cop, n_edges, 2, **how).filter(F.col("n_edges") == n_edges)
        assert {r["pattern"]: r["mni"] for r in found.collect()} == want
    capped = fsm.fsm(cop, n_edges, 2, exact=False).filter(F.col("n_edges") == n_edges).collect()
    assert {r["pattern"] for r in capped} == set(want) and all(r["mni"] == 2 and r["capped"] for r in capped)


def test_levels_of_the_sparse_graph(cop):
    """Counted once with throw-away scripts: edge sets and patterns of 1, 2, 3 edges."""
    for n, (rows, patterns) in {1: (62, 18), 2: (36, 28), 3: (27, 25)}.items():
        assert loop.embeddings(cop, n, mode="edge").count() == rows
        assert len(brute_mni(cop, n)) == patterns


def test_support_shrinks_as_patterns_grow(cop):
    found = fsm.fsm(cop, 3, 1).groupBy("n_edges").agg(F.max("mni").alias("m")).orderBy("n_edges").collect()
    assert [r["m"] for r in found] == sorted((r["m"] for r in found), reverse=True)
    assert fsm.fsm(cop, 2, 10**6).count() == 0
    strict = fsm.fsm(cop, 1, 2, strict=True).count()
    assert strict == fsm.fsm(cop, 1, 3).count()


def test_counts_and_sketches(cop):
    n = {r["pattern"]: r["mni"] for r in fsm.fsm(cop, 2, 1, measure="count").filter("n_edges = 2").collect()}
    assert sum(n.values()) == 36
    level = edge.init(cop, carry=False).df
    near = {r["code"]: r["mni"] for r in mni.approximate(level, 0.01).collect()}
    assert near == {r["code"]: r["mni"] for r in mni.exact(level).collect()}  # exact at this size


def test_edge_labels_split_patterns(spark):
    pairs = [(1, 2, 1), (2, 3, 2), (3, 4, 1), (4, 5, 2)]
    g = PropertyGraph.from_pairs(spark.createDataFrame(pairs, "src long, dst long, elabel int"))
    one = {r["pattern"]: r["mni"] for r in fsm.fsm(g, 1, 1).collect()}
    assert sorted(one.values()) == [4, 4] and len(one) == 2
    two = fsm.fsm(g, 2, 1).filter("n_edges = 2").collect()
    assert [(r["mni"], r["embeddings"]) for r in two] == [(3, 3)]


def test_jobs(toy, cop):
    got = {r["pattern"]: r["value"] for r in api.MiningJob(toy, 3, labelled=False).run().collect()}
    assert sorted(got.values()) == [3, 5]
    some = api.MiningJob(toy, 3, labelled=False, pfilter=F.col("value") > 3).run().collect()
    assert [r["value"] for r in some] == [5]
    assert api.MiningJob(toy, 3, mapper=None).run().first()["n"] == 8
    with pytest.raises(RuntimeError, match="max_rows"):
        api.MiningJob(toy, 3, max_rows=1).run()
    each = api.MiningJob(cop, 2, mode="edge", loop="each").run()
    assert each.agg(F.sum("value")).first()[0] == 36
    total = api.MiningJob(toy, 3, labelled=False, mapper=lambda df: df.select("labels", "bits", F.array_max("path").alias("value")), reducer=lambda p: p.groupBy("pattern").agg(F.max("value").alias("value"))).run()
    assert {r["value"] for r in total.collect()} == {5}


def test_relational_baseline_needs_more_rounds(cop):
    _, made = relational.vertex_sets(cop, 4)
    assert len(made) == 6 or made[-1] == 0
    ours = sorted(r["frequency"] for r in motif.motifs(cop, 4).collect())
    assert sorted(r["frequency"] for r in relational.motifs(cop, 4).collect()) == ours


#: Run times of one task on three graphs, one system's and another's, and the mean of their ratios: fixed values.
PRINTED = {"a": ([7.35, 8.19, 7.84, 3.97], [101.77, 70.74, 46.65, 29.67], 8.5), "b": ([25.47, 26.41, 28.71, 31.51], [139.8, 133, 119.4, 102.6], 4.4), "c": ([132.59, 133.31, 136.24, 155.04], [426.67, 409.23, 397.19, 396.11], 2.9)}


@pytest.mark.parametrize("name", sorted(PRINTED))
def test_speed_up_formula(spark, name):
    ours, theirs, want = PRINTED[name]
    assert round(stats.speed_up(ours, theirs), 1) == want
    df = spark.createDataFrame([(name, a, float(b)) for a, b in zip(ours, theirs, strict=True)], "task string, ours double, theirs double")
    assert round(stats.speed_ups(df).first()["speed_up"], 1) == want


def test_figures():
    assert stats.geometric_mean([1, 100]) == pytest.approx(10)
    assert stats.reduction(2, 6) == 3 and stats.skew([1, 1, 4]) == 2
    assert stats.space_formula(10, 20, 3) == 40 and stats.time_formula(10, 4, 3) == 160
    assert stats.partition_agreement({1: "a", 2: "a", 3: "b"}, {1: "x", 2: "y", 3: "y"}) == (1, 1)


def test_runs_record_failures(spark):
    ok = run.measured(spark, "ok", lambda: spark.range(10).count())
    bad = run.measured(spark, "bad", lambda: 1 / 0)
    assert ok.seconds > 0 and ok.failure is None and ok.peak_bytes > 0
    assert bad.seconds is None and bad.failure.startswith("ZeroDivisionError")
    assert run.timed(lambda: math.sqrt(2), repeats=3) >= 0
