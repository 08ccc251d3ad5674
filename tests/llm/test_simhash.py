from __future__ import annotations

import random

import numpy as np
import pytest
import xxhash

from levelmine.llm.components import components
from levelmine.llm.simhash import BKForest, links, near_duplicates, spanning
from tests.llm.support import LOWER, corpus, frame, space_words


def fingerprint(text):
    words = space_words((text or "").translate(LOWER))
    grams = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    count = [0] * 64
    for g in grams:
        h = xxhash.xxh64_intdigest(g.encode(), seed=42)
        for b in range(64):
            count[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * count[b] > len(grams))


class Union:
    def __init__(self):
        self.up = {}

    def find(self, x):
        self.up.setdefault(x, x)
        while self.up[x] != x:
            x = self.up[x]
        return x

    def join(self, a, b):
        a, b = self.find(a), self.find(b)
        self.up[max(a, b)] = min(a, b)


def test_same_as_brute_force(spark):
    rows = corpus()
    fps = [fingerprint(t) for _, t in rows]
    union = Union()
    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                union.join(fps[i], fps[j])
    least = {}
    for (d, _), f in zip(rows, fps, strict=True):
        if d is not None:
            least[union.find(f)] = min(least.get(union.find(f), d), d)
    want = sorted(((d, f"{f:016x}", least.get(union.find(f))) for (d, _), f in zip(rows, fps, strict=True)), key=str)
    got = near_duplicates(frame(spark, rows))
    assert got.columns == ["doc_id", "fingerprint", "component_id"]
    assert sorted(map(tuple, got.collect()), key=str) == want


def test_empty_table(spark):
    assert near_duplicates(frame(spark, []).limit(0)).count() == 0


def test_tree_search_finds_all_and_only_links():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 20, dtype=np.int64).astype(np.uint64)
    fp = np.unique(np.concatenate([base ^ (np.uint64(1) << rng.integers(0, 64, 20).astype(np.uint64)) for _ in range(12)] + [base]))
    group = rng.integers(0, 3, len(fp))
    for radius in (0, 1, 2, 5):
        q, n = BKForest(fp, group).search(fp, group, radius, step=50)
        want = {(i, j) for i in range(len(fp)) for j in range(len(fp)) if group[i] == group[j] and (int(fp[i]) ^ int(fp[j])).bit_count() <= radius}
        assert set(zip(q.tolist(), n.tolist(), strict=True)) == want


@pytest.mark.parametrize("blocks", [None, 4, 5])
def test_hot_shards_are_cut_without_losing_links(spark, blocks):
    rng = random.Random(5)
    base = rng.getrandbits(64)
    fps = {base}
    while len(fps) < 300:  # one dense group that shares its blocks
        x = rng.choice(sorted(fps))
        fps.add(x ^ 1 << rng.randrange(64) ^ 1 << rng.randrange(64))
    fps |= {rng.getrandbits(64) for _ in range(50)}
    signed = lambda x: x - (x >> 63 << 64)
    df = spark.createDataFrame([(signed(x),) for x in fps], "fp long")
    union = Union()
    for a, b in links(df, 2, shard=16, blocks=blocks).collect():
        assert (a ^ b) != 0
        union.join(a, b)
    want = Union()
    all_ = sorted(fps)
    for i, a in enumerate(all_):
        for b in all_[:i]:
            if (a ^ b).bit_count() <= 2:
                want.join(signed(a), signed(b))
    for a in all_:
        for b in all_:
            assert (union.find(signed(a)) == union.find(signed(b))) == (want.find(signed(a)) == want.find(signed(b)))


def test_components_of_long_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 50)] + [(7, 7)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert got == {**{i: 0 for i in range(41)}, **{100 + i: 100 for i in range(50)}}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_spanning_names_the_least():
    assert spanning(6, np.array([5, 4, 1]), np.array([4, 3, 2])).tolist() == [0, 1, 1, 3, 3, 3]
