from __future__ import annotations

import hashlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from levelmine.llm import kernel
from levelmine.llm.repeats import COVERS, difference_cover, remove_repeats, sparse_suffixes
from tests.llm.support import corpus, frame, space_words


def brute(rows, length):
    """{(doc_id, text): (words, removed, repeated, sha)}; a null id comes first, ids that repeat follow the text's hash."""
    signed = lambda t: (h := xxhash.xxh64_intdigest((t or "").encode(), seed=42)) - (h >> 63 << 64)
    keys = sorted({(-(1 << 63) if d is None else d, signed(t), d, t or "") for d, t in rows}, key=lambda x: x[:2])
    places = {}
    for n, (_, _, _, text) in enumerate(keys):
        words = space_words(text)
        for s in range(len(words) - length + 1):
            places.setdefault(tuple(words[s : s + length]), []).append((n, s))
    gone, again = {n: set() for n in range(len(keys))}, {n: set() for n in range(len(keys))}
    for at in places.values():
        for n, s in at[1:]:
            gone[n].update(range(s, s + length))
        for n, s in at if len(at) > 1 else []:
            again[n].update(range(s, s + length))
    out = {}
    for n, (_, _, d, text) in enumerate(keys):
        words = space_words(text)
        kept = " ".join(w for i, w in enumerate(words) if i not in gone[n])
        out[d, text] = (len(words), len(gone[n]), len(again[n]), hashlib.sha256(kept.encode()).hexdigest())
    return out


@pytest.mark.parametrize("how", [difference_cover(20), difference_cover(8), sparse_suffixes(50), sparse_suffixes(25, 10)], ids=["cover20", "cover8", "suffix50", "suffix25"])
def test_same_as_brute_force(spark, how):
    rows = corpus()
    want = brute(rows, how.length)
    got = remove_repeats(frame(spark, rows), how, with_text=True).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r[-5], r[-4], r[-3], r[-2]) == want[r["doc_id"], r["text"] or ""]
        if not r[-4]:
            assert r["r_text"] == (r["text"] or "")
    assert sum(w[1] for w in want.values()) > 0


def test_columns_pass_and_empty_table(spark):
    docs = frame(spark, corpus(n=5))
    out = remove_repeats(docs, difference_cover(20), with_text=True)
    assert out.columns == [*docs.columns, "r_words", "r_removed", "r_repeated", "r_sha", "r_text"]
    assert remove_repeats(docs.limit(0), sparse_suffixes(50)).count() == 0


@pytest.mark.parametrize("period", sorted(COVERS))
def test_covers_meet_at_every_shift(period):
    cover = set(COVERS[period])
    for i in range(period):
        assert any(k % period in cover and (k + i) % period in cover for k in range(period))


def test_vectorised_hash_is_xxh64():
    buf = np.frombuffer(np.random.default_rng(1).bytes(3000), np.uint8)
    rng = np.random.default_rng(2)
    start = rng.integers(0, 2500, 2000)
    end = start + rng.integers(0, 140, 2000)
    assert kernel.xxh64(buf, start, end).tolist() == [xxhash.xxh64_intdigest(buf[a:b].tobytes(), seed=42) for a, b in zip(start, end, strict=True)]


def test_one_text_repeated_inside(spark):
    rows = [(1, " ".join(["a", "b", "c"] * 40))]
    got = remove_repeats(frame(spark, rows), sparse_suffixes(50)).first()
    assert (got[-4], got[-3]) == brute(rows, 50)[1, rows[0][1]][:2]


def test_pipeline_of_passes_reuses_one_text_exchange(spark):
    plan = remove_repeats(frame(spark, corpus(n=5)), difference_cover(20))
    plan.collect()
    assert F and "ReusedExchange" in plan._jdf.queryExecution().toString()
