from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from levelmine.llm.crosspolytope import Turns, hadamard, nearest

SCHEMA = "vec_id long, embedding array<float>, label int, v string, query_id string, score string"


def frame(spark, rows):
    return spark.createDataFrame([(i, None if v is None else [None if c is None else float(c) for c in v], 0, "v", "q", "s") for i, v in rows], SCHEMA).repartition(3)


def brute(rows, k):
    good = {}
    for i, v in rows:
        if i is None or v is None or len(v) != 16 or any(c is None or not np.isfinite(c) for c in v) or not any(v):
            continue
        good.setdefault(i, []).append(np.array(v, np.float32).astype(float))
    out = {}
    for q, vs in good.items():
        if q % 20:
            continue
        x = min(vs, key=list)
        scored = sorted((-max(float((x * y).sum()) for y in ys), i) for i, ys in good.items() if i != q)
        out[q] = [(i, -s) for s, i in scored[:k]]
    return out


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(5)
    centres = rng.normal(size=(8, 16))
    vectors = centres[rng.integers(0, 8, 1500)] + 0.4 * rng.normal(size=(1500, 16))
    out = [(i, v.tolist()) for i, v in enumerate(vectors)]
    same = out[40][1]
    out += [(2000 + i, same) for i in range(60)]  # ties
    out += [(3000, None), (3020, [0.0] * 16), (3040, [1.0] * 15 + [None]), (3060, [float("nan")] * 16), (3080, [float("inf")] + [1.0] * 15), (3100, [1.0] * 8), (None, same), (40, same), (60, out[61][1]), (3120, []), (3140, (10 * np.array(same)).tolist())]
    return out


def test_recall_order_and_scores(spark, rows):
    want = brute(rows, 20)
    got = {}
    for r in nearest(frame(spark, rows), F.col("vec_id") % 20 == 0).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert got.keys() == want.keys()
    hit = total = 0
    for q, found in got.items():
        found.sort()
        assert [f[0] for f in found] == list(range(1, 21))
        assert [(-s, i) for _, i, s in found] == sorted((-s, i) for _, i, s in found)
        truth = dict(want[q])
        for _, i, s in found:
            if i in truth:
                assert s == pytest.approx(truth[i], abs=1e-9)
        hit += len(truth.keys() & {f[1] for f in found})
        total += 20
    assert hit / total >= 0.9


def test_all_candidates_if_fewer(spark, rows):
    few = [r for r in rows[:9]]
    got = nearest(frame(spark, few), F.col("vec_id") % 20 == 0).collect()
    assert [(r["vec_id"], round(r["score"], 6)) for r in got] == [(i, round(s, 6)) for i, s in brute(few, 20)[0]]


def test_blocks_of_queries_change_nothing(spark, rows):
    key = lambda df: sorted(map(tuple, df.collect()))
    is_query = F.col("vec_id") % 20 == 0
    assert key(nearest(frame(spark, rows), is_query, block=16)) == key(nearest(frame(spark, rows), is_query))


def test_empty_and_unusable(spark, rows):
    none = frame(spark, rows).limit(0)
    assert nearest(none, F.col("vec_id") % 20 == 0).count() == 0
    assert nearest(frame(spark, [(0, [0.0] * 4), (20, None)]), F.col("vec_id") % 20 == 0).count() == 0


def test_turns_keep_lengths_and_angles():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(50, 16))
    assert np.allclose(hadamard(x) @ hadamard(x).T, x @ x.T)
    turns = Turns(16, 1.0, False, tables=4)
    assert turns.cells(x).max() < 32
    both = Turns(16, 1.0, False, tables=4, turns=2)
    cells, probes = both.cells(x), both.probes(x, 3)
    assert cells.max() < 32 * 32 and probes.shape == (50, 4, 3)
    assert (probes == cells[:, :, None]).any(axis=2).all()  # a vector's own cell is the nearest


def test_ids_that_repeat_crowd_nobody_out(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=16)
    rows = [(0, base.tolist())] + [(7, (base * (1 + i / 1000)).tolist()) for i in range(60)] + [(i, (base + 0.3 * rng.normal(size=16)).tolist()) for i in range(100, 140)]
    got = nearest(frame(spark, rows), F.col("vec_id") % 20 == 0, block=16).filter("query_id = 0").orderBy("rank").collect()
    assert [(r["vec_id"], round(r["score"], 5)) for r in got] == [(i, round(s, 5)) for i, s in brute(rows, 20)[0]]


def test_longer_keys(spark, rows):
    """Two turns a cell: fewer candidates, scores as exact."""
    want, hit = brute(rows, 20), 0
    got = nearest(frame(spark, rows), F.col("vec_id") % 20 == 0, turns=2, probes=24, tables=8).collect()
    for r in got:
        truth = dict(want[r["query_id"]])
        hit += r["vec_id"] in truth
        assert r["score"] == pytest.approx(truth.get(r["vec_id"], r["score"]), abs=1e-9)
    assert len({(r["query_id"], r["vec_id"]) for r in got}) == len(got) and hit / len(got) > 0.7


def test_recall_on_the_given_table(spark):
    """The query's parameters on the given vectors, which are nearly without structure."""
    docs = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    kept = docs.toPandas()
    x = np.stack(kept["embedding"].to_numpy()).astype(float)
    ids = kept["vec_id"].to_numpy()
    asked = np.flatnonzero(ids % 20 == 0)
    near = x[asked] @ x.T
    near[np.arange(len(asked)), asked] = -np.inf
    truth = {int(ids[q]): set(ids[np.lexsort((ids, -near[i]))[:20]].tolist()) for i, q in enumerate(asked)}
    got = nearest(docs, F.col("vec_id") % 20 == 0).toPandas()
    assert len(got) == 20 * len(asked)
    hit = sum(v in truth[q] for q, v in zip(got["query_id"], got["vec_id"], strict=True))
    assert hit / len(got) >= 0.9
