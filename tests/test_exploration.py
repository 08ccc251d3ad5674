"""The worked example, and exploration against brute force."""

from __future__ import annotations

from itertools import combinations

import pytest
from pyspark.sql import functions as F

from levelmine.balance import predict as balance
from levelmine.baselines import brute, layered_dag
from levelmine.explore import edge, loop, vertex
from levelmine.explore.vertex import Level
from levelmine.graph.model import PropertyGraph
from levelmine.graph.numbering import numbered
from levelmine.sources.graphs import TOY_EDGES, load, part_copurchase, toy7, vector_knn
from levelmine.store.hybrid import Storage, WindowReader, expand_by_part, explore_stored
from levelmine.store.levels import LevelStore, stored
from levelmine.streaming.parts import expand_stream


@pytest.fixture(scope="module")
def toy(spark):
    return load(toy7, spark, "")


@pytest.fixture(scope="module")
def store(toy):
    return stored(toy, 3)


def words(df, col="path"):
    return sorted("".join(map(str, r[col])) for r in df.select(col).collect())


THIRD = ["123", "125", "153", "154", "234", "235", "254", "345"]


def test_level_sizes(toy):
    assert [r["n"] for r in loop.level_sizes(toy, 7).orderBy("k").collect()] == [5, 7, 8, 5, 1, 0, 0]


@pytest.mark.parametrize("strategy", ["carry", "rejoin"])
def test_third_level(toy, strategy):
    assert words(loop.embeddings(toy, 3, strategy=strategy)) == THIRD


def test_second_level_from_edges(toy):
    assert words(vertex.init(toy, 2).df) == ["12", "15", "23", "25", "34", "35", "45"]
    grown = vertex.expand(toy, vertex.init(toy, 2), last=True)
    assert words(grown.df) == THIRD


def test_candidates_and_kept_children(toy):
    two = vertex.init(toy, 2)
    cand = {(tuple(r["path"]), r["v"]) for r in vertex.candidates(toy, two).collect()}
    assert {v for p, v in cand if p == (2, 3)} == {1, 4, 5}
    plain = vertex.candidates(toy, Level(two.df.drop("ext"), 2))
    assert {(tuple(r["path"]), r["v"]) for r in plain.collect()} == cand
    assert [p[2:] for p in words(loop.embeddings(toy, 3)) if p.startswith("23")] == ["4", "5"]


def test_predicted_candidates(toy):
    level = [x for x in loop.explore(toy, 4) if x.k == 3][0]
    pred = {"".join(map(str, r["path"])): r["pred"] for r in balance.predict(level).collect()}
    assert pred["123"] == 2
    assert loop.predicted_rows(level) == 5


def test_store_golden_facts(store):
    assert [tuple(r) for r in store.offsets(3).orderBy("parent").collect()] == [(0, 0, 2), (1, 2, 4), (2, 4, 6), (3, 6, 7), (4, 7, 8), (5, 8, 8), (6, 8, 8)]
    assert [(r["start"], r["stop"]) for r in store.offsets(2).orderBy("parent").collect()][0] == (0, 2)
    assert store.decode(3, 5) == [2, 3, 5]
    assert sorted(r["vert"] for r in store.children(3, 2).collect()) == [4, 5]
    assert words(store.paths(3)) == THIRD
    assert words(store.paths(3, 2, 5)) == THIRD[2:5]
    with pytest.raises(KeyError):
        store.decode(3, 99)


def test_store_invariants(store):
    for k in (2, 3):
        off = store.offsets(k).orderBy("parent").collect()
        assert len(off) == store.level(k - 1).count() and off[-1]["stop"] == store.level(k).count()
        assert all(a["stop"] == b["start"] for a, b in zip(off, off[1:], strict=False))


def test_tensor_cells(spark, store):
    wanted = spark.createDataFrame([([1, 2, 3],), ([3, 2, 1],), ([2, 5, 4],), ([1, 2],)], "path array<long>")
    assert words(store.contains(wanted, 3)) == ["123", "254"]


def test_layouts_agree(toy, store):
    other = stored(toy, 3, "paths")
    assert words(other.paths(3)) == words(store.paths(3)) and other.decode(3, 5) == [2, 3, 5]
    with pytest.raises(ValueError):
        LevelStore(toy.edges.sparkSession, "trees")


@pytest.fixture(scope="module", params=["copurchase", "knn"])
def graph(request, spark, sf_dir):
    return load({"copurchase": part_copurchase, "knn": vector_knn}[request.param], spark, sf_dir)


def connected_sets(graph, k):
    near = {}
    for r in graph.edges.collect():
        near.setdefault(r["src"], set()).add(r["dst"])
        near.setdefault(r["dst"], set()).add(r["src"])
    found = {frozenset([v]) for v in near}
    for _ in range(k - 1):
        found = {s | {w} for s in found for v in s for w in near[v] if w not in s}
    return sorted(tuple(sorted(s)) for s in found)


@pytest.mark.parametrize("k", [3, 4])
def test_every_connected_set_once(graph, k):
    got = sorted(tuple(sorted(r["path"])) for r in loop.embeddings(graph, k).select("path").collect())
    assert got == connected_sets(graph, k)


def test_strategies_and_baselines_agree(graph):
    want = connected_sets(graph, 3)
    rejoin = loop.embeddings(graph, 3, strategy="rejoin").select("path")
    assert sorted(tuple(sorted(r[0])) for r in rejoin.collect()) == want
    assert sorted(tuple(sorted(r[0])) for r in layered_dag.explore(graph, 3).collect()) == want
    assert sorted(tuple(r[0]) for r in brute.subsets(graph, 3).collect()) == want


def test_edge_sets_once(spark, sf_dir):
    graph = load(part_copurchase, spark, sf_dir)
    ends = {r["eid"]: {r["src"], r["dst"]} for r in graph.edges.collect()}
    for k in (2, 3):
        want = set()
        for s in combinations(sorted(ends), k):
            left, seen = set(s[1:]), set(ends[s[0]])
            while hit := {e for e in left if ends[e] & seen}:
                seen |= set().union(*(ends[e] for e in hit))
                left -= hit
            if not left:
                want.add(s)
        got = [tuple(sorted(r[0])) for r in loop.embeddings(graph, k, mode="edge").select("eids").collect()]
        assert len(got) == len(set(got)) and set(got) == want
        level = edge.init(graph, carry=False)
        for _ in range(k - 1):
            level = edge.expand(graph, level, unique="distinct")
        assert {tuple(sorted(r[0])) for r in level.df.select("eids").collect()} == want


def test_filter_is_applied_in_every_round(toy):
    odd = loop.embeddings(toy, 3, efilter=lambda path, v: v != 4)
    assert words(odd) == [w for w in THIRD if "4" not in w]


def test_row_guard_and_size_guard(toy):
    with pytest.raises(RuntimeError, match="max_rows"):
        list(loop.explore(toy, 4, max_rows=6))
    with pytest.raises(ValueError):
        vertex.expand(toy, Level(toy.edges, 8, True))


@pytest.mark.parametrize("kind", ["memory", "disk", "hybrid"])
def test_storage_changes_no_answer(toy, kind):
    storage = Storage(kind, 1500)
    assert words(explore_stored(toy, 4, storage)) == words(loop.embeddings(toy, 4))
    assert storage.placed == {"memory": ["memory"] * 2, "disk": ["disk"] * 2, "hybrid": ["memory", "disk"]}[kind]


def test_parts_and_streams_change_no_answer(toy):
    two = vertex.init(toy, 2)
    assert words(expand_by_part(toy, two, 3)) == THIRD
    assert words(expand_stream(toy, two, 3)) == THIRD


def test_windows_come_in_order_and_cover(spark):
    seen = []
    for part, df in WindowReader(lambda p: spark.range(p * 10, p * 10 + 10), 4, prefetch=2):
        seen.append((part, sorted(r[0] for r in df.collect())))
    assert seen == [(p, list(range(p * 10, p * 10 + 10))) for p in range(4)]


def test_splits(graph):
    level = balance.predict(vertex.init(graph, 2)).select("path", "pred")
    even = balance.split_even(level, 5, "path").groupBy("part").count().collect()
    assert max(r["count"] for r in even) - min(r["count"] for r in even) <= 1 and len(even) == 5
    parted = balance.split_predicted(level, 5, "path")
    assert parted.count() == level.count()
    a, b = (balance.skew(x).first()["skew"] for x in (parted, balance.split_even(level, 5, "path")))
    assert a <= b + 0.05
    bound = {tuple(r["path"]): r["pred"] for r in balance.degree_bound(graph, vertex.init(graph, 2)).collect()}
    assert all(bound[tuple(r["path"])] >= r["pred"] for r in level.collect())


def test_numbers_are_dense_and_ordered(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("x")).repartition(7)
    got = numbered(df, "x").collect()
    assert sorted((r["pos"], r["x"]) for r in got) == [(i, i) for i in range(1000)]
    assert numbered(df.limit(0), "x").count() == 0


def test_odd_graphs(spark):
    def graph(pairs, **how):
        return PropertyGraph.from_pairs(spark.createDataFrame(pairs, "src long, dst long"), **how)

    empty = graph([(1, 1), (None, 2)])
    assert empty.edges.count() == 0 and loop.embeddings(empty, 3).count() == 0
    one = graph([(2, 1), (1, 2), (2, 1)])
    assert [(r["src"], r["dst"]) for r in one.edges.collect()] == [(1, 2)]
    assert [r["n"] for r in loop.level_sizes(one, 3).orderBy("k").collect()] == [2, 1, 0]
    star = graph([(1 << 40, i) for i in range(30)])
    assert loop.embeddings(star, 3).count() == 435 and loop.embeddings(star, 3, strategy="rejoin").count() == 435
    labels = spark.createDataFrame([(1, None), (9, 4)], "id long, label int")
    kept = graph([(1, 2)], labels=labels, isolated=True)
    assert {(r["id"], r["label"]) for r in kept.vertices.collect()} == {(1, 1), (2, 1), (9, 4)}
    assert sorted(r["path"][0] for r in vertex.init(kept).df.collect()) == [1, 2, 9]
    with pytest.raises(Exception, match="labels start at 1"):
        graph([(1, 2)], labels=spark.createDataFrame([(1, 0)], "id long, label int"))


def test_adjacency_is_cut_at_hubs(spark):
    star = PropertyGraph.from_pairs(spark.createDataFrame([(0, i) for i in range(1, 11)], "src long, dst long"))
    rows = star.adjacency(chunk=4).filter("id = 0").orderBy("chunk").collect()
    assert [len(r["nbrs"]) for r in rows] == [4, 4, 2] and rows[0]["deg"] == 10
    assert sum((r["nbrs"] for r in rows), []) == list(range(1, 11))


def test_stats_and_induced(spark, toy):
    s = toy.stats().first()
    assert (s["n_vertices"], s["n_edges"], s["n_labels"], s["avg_degree"], s["max_degree"]) == (5, 7, 4, 2.8, 4)
    sub = toy.induced(spark.createDataFrame([(1,), (2,), (5,)], "id long"))
    assert {(r["src"], r["dst"]) for r in sub.edges.collect()} == {(1, 2), (1, 5), (2, 5)} <= set(TOY_EDGES)
