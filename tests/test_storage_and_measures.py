"""Levels as links, windows, running values, balance in jobs, resumable counts, and what runs are measured by."""

from __future__ import annotations

from itertools import combinations

import pytest
from pyspark.sql import functions as F

from levelmine import api
from levelmine.apps import fsm
from levelmine.baselines import relational
from levelmine.explore import loop, vertex
from levelmine.graph import numbering
from levelmine.measure import run
from levelmine.pattern.classify import pattern_counts
from levelmine.pattern.encode import bits_of
from levelmine.pattern.exact import canonical
from levelmine.pattern.names import SHAPES, names
from levelmine.session import scratch_path
from levelmine.sources.graphs import load, toy7, vector_knn
from levelmine.store.hybrid import Storage, expand_windows, predicted
from levelmine.store.levels import stored
from levelmine.streaming.incremental import TriangleCount


@pytest.fixture(scope="module")
def toy(spark):
    return load(toy7, spark, "")


@pytest.fixture(scope="module")
def knn(spark, sf_dir):
    return load(vector_knn, spark, sf_dir, k=2)


def words(df, col="path"):
    return sorted("".join(map(str, r[col])) for r in df.select(col).collect())


def test_written_levels_hold_links_alone(toy):
    for level in loop.explore(toy, 4):
        if 1 < level.k < 4:
            held = {c for f in level.df.inputFiles() if f"level{level.k}" in f for c in level.df.sparkSession.read.parquet(f).columns}
            assert held == {"pos", "parent", "vert", "label", "mask"}


def test_store_is_what_exploration_grows_from(toy):
    store = stored(toy, 4)
    assert [store.level(k).count() for k in (1, 2, 3, 4)] == [5, 7, 8, 5]
    for k in (2, 3, 4):
        rows = store.level(k).orderBy("pos").collect()
        assert [r["pos"] for r in rows] == list(range(len(rows)))
        assert [(r["parent"], r["vert"]) for r in rows] == sorted((r["parent"], r["vert"]) for r in rows)
    assert words(store.paths(4)) == words(loop.embeddings(toy, 4))


def test_windows_hold_what_a_part_needs(toy):
    store = stored(toy, 3)
    part = store.level(3).filter("pos between 4 and 5")  # 234, 235
    held = {k: {r["pos"] for r in rows.collect()} for k, rows in store.windows(3, part)}
    assert held == {3: {4, 5}, 2: {2}, 1: {1}}
    got = store.window_paths(3, part).orderBy("pos").collect()
    assert [r["path"] for r in got] == [[2, 3, 4], [2, 3, 5]]
    assert words(expand_windows(toy, store, 3)) == words(loop.embeddings(toy, 4))


def test_rows_regain_their_candidates(toy):
    level = [x for x in loop.explore(toy, 4) if x.k == 3][0]
    again = vertex.with_ext(toy, level.df.drop("ext"), 3)
    as_dict = lambda df: {tuple(r["path"]): dict(r["ext"]) for r in df.collect()}
    assert as_dict(again.df) == as_dict(level.df)


def test_prediction_is_exact_in_rows_and_no_less_in_bytes(toy):
    for level in loop.explore(toy, 4):
        if level.k < 4:
            said = predicted(toy, level)
            assert said.rows == vertex.expand(toy, level, last=True).df.count() and said.bytes >= said.rows * 8 * level.k


@pytest.mark.parametrize("block", [4, 1000])
def test_running_values(spark, monkeypatch, block):
    monkeypatch.setattr(numbering, "BLOCK", block)
    rows = spark.range(50).select(F.col("id").alias("n"), (F.col("id") % 7).alias("x"))
    got = {r["n"]: r["before"] for r in numbering.running(rows, "n", "x", F.sum, lambda a, b: a + b).collect()}
    assert got == {n: (sum(i % 7 for i in range(n)) if n else None) for n in range(50)}


@pytest.mark.parametrize("kind", ["memory", "hybrid", "disk"])
@pytest.mark.parametrize("mode", ["vertex", "edge"])
def test_job_is_the_same_for_all_storage_and_balance(knn, kind, mode):
    def told(**how):
        return sorted(map(tuple, api.MiningJob(knn, 3, mode=mode, **how).run().collect()))

    want = told()
    assert told(storage=Storage(kind, 20_000)) == want
    assert told(balance="predicted", parts=3, storage=Storage(kind, 20_000)) == want


def test_job_refuses_unknown_balance(toy):
    with pytest.raises(ValueError, match="balance"):
        api.MiningJob(toy, 3, balance="fair").run()


def test_partial_rows_lie_between(knn):
    row = api.combine_rows(loop.embeddings(knn, 3)).first()
    assert row["final"] <= row["partial"] <= row["mapped"] == loop.embeddings(knn, 3).count()


def test_frequent_subgraphs_by_all_ways(knn):
    two = knn.relabelled(knn.vertices.select("id", (F.col("label") % 2 + 1).alias("label")))
    told = lambda **how: sorted((r["pattern"], r["n_edges"], r["mni"]) for r in fsm.fsm(two, 3, 20, **how).collect())
    want = told()
    assert want and told(strategy="distinct") == want and told(prune=False) == want
    assert sorted(x[:2] for x in told(exact=False)) == sorted(x[:2] for x in want)
    assert {x[2] for x in told(exact=False)} == {20}


def test_engines_tell_the_same_classes(knn):
    rows = loop.embeddings(knn, 4)
    bags = {e: sorted(r["frequency"] for r in pattern_counts(rows, True, e).collect()) for e in ("exact", "verified", "spectral", "search_tree")}
    assert len({tuple(b) for b in bags.values()}) == 1


def test_all_shapes_of_five_have_names():
    pairs = list(combinations(range(5), 2))
    codes = set()
    for n in range(1 << len(pairs)):
        edges = [p for b, p in enumerate(pairs) if n >> b & 1]
        seen, todo = {0}, [0]
        while todo:
            x = todo.pop()
            more = {b if a == x else a for a, b in edges if x in (a, b)} - seen
            seen |= more
            todo += more
        if len(seen) == 5:
            codes.add(canonical((1,) * 5, bits_of(5, edges))[0])
    known = names()
    assert len(codes) == 21 and codes <= set(known) and len({known[c] for c in codes}) == 21
    assert len(SHAPES) == len({canonical((1,) * k, bits_of(k, e))[0] for k, e in SHAPES.values()})


def test_cliques_by_rounds_of_edges(toy):
    assert words(relational.cliques(toy, 3)) == ["125", "235", "345"]
    assert relational.cliques(toy, 4).count() == 0


def test_best_number_of_partitions(spark, toy):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    got = relational.best_partitions(toy, lambda g: g.edges.groupBy("src").count().collect(), (2, 3))
    assert {n for n, _ in got} == {2, 3} and got[0][1] <= got[1][1]
    assert spark.conf.get("spark.sql.shuffle.partitions") == before


def test_triangle_count_goes_on_where_it_ended(spark):
    path = scratch_path(spark, "count")
    pairs = lambda *e: spark.createDataFrame(list(e), "src long, dst long")
    first = TriangleCount(spark, path)
    first.add(pairs((1, 2), (2, 3), (2, 1)), 0)
    assert (first.triangles, first.wedges) == (0, 1)
    first.add(pairs((3, 1), (3, 4), (4, 1), (1, 1)), 1)
    again = TriangleCount(spark, path)
    assert (again.triangles, again.wedges, again.last) == (first.triangles, first.wedges, 1) == (2, 8, 1)
    again.add(pairs((9, 10)), 1)  # run before
    again.add(pairs((2, 4)), 2)
    assert (again.triangles, again.wedges) == (4, 12) and again.history == [(0, 0, 1), (1, 2, 8), (2, 4, 12)]


def test_measured_runs_tell_bytes_and_use(spark, tmp_path):
    r = run.measured(spark, "write", lambda: spark.range(100_000).repartition(3).write.parquet(f"file://{tmp_path}/out"))
    assert r.failure is None and r.detail["written"] > 0 and r.detail["shuffled"] > 0 and r.process_bytes > 0
    assert r.detail["cpu"] > 0 and 0 < r.detail["cpu_percent"]
    rows = r.detail["over_time"]
    assert sum(x["written_mb_s"] for x in rows) == pytest.approx(r.detail["written"] / 1e6, abs=0.01)


def test_use_over_time_spreads_a_stage():
    rows = run.over_time([run.Stage(0, 10.0, 12.0, 4_000_000, 0, 0, 0, 2.0, 2.0)], cores=2)
    assert [x["read_mb_s"] for x in rows] == [2.0, 2.0] and [x["cpu_percent"] for x in rows] == [50.0, 50.0]
