"""Every registered query of this subpackage on one folder of tables, long and odd texts among them, against plain versions."""

from __future__ import annotations

import hashlib
import math
import random
import zlib

import numpy as np
import pytest

import __spark_entry__
from levelmine.llm import bpe, quality
from tests.llm.support import corpus, frame, space_words
from tests.llm.test_decontaminate import brute as contaminated
from tests.llm.test_lm import brute as backoff
from tests.llm.test_repeats import brute as repeats
from tests.llm.test_simhash import Union, fingerprint

pytest.importorskip("public_tokenizers")


@pytest.fixture(scope="module")
def case(spark, tmp_path_factory):
    rng = random.Random(4)
    long = " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 9))) for _ in range(250_000))
    assert len(long) > 1 << 20
    rows = [*corpus(n=24), (5000, long), (5001, long[: 1 << 20] + " end"), (5002, "x" * (1 << 20))]
    path = f"file://{tmp_path_factory.mktemp('registered')}"
    frame(spark, rows).write.parquet(f"{path}/documents.parquet")
    passage = space_words(rows[0][1])
    items = [(1, " ".join(long.split()[100:130])), (2, "one two"), (3, None), (4, " ".join(passage[:15]) or "none")]
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    marks = [(d, int(len(t or "") % 3 > 0), 0) for d, t in rows if d is not None]
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    vectors = [(i, np.random.default_rng(i).normal(size=16).astype(np.float32).tolist(), 0) for i in range(120)] + [(200, None, 0)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").write.parquet(f"{path}/embeddings.parquet")
    pages = [(1, "u", "<a>"), (2, "v", "<a>"), (3, "w", None), (4, "x", "é" * (1 << 20))]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(f"{path}/pages.parquet")
    return path, rows, items, vectors, pages


@pytest.fixture(scope="module")
def answer(spark, case):
    queries = {name.split("_")[0]: q for name, q in __spark_entry__.queries().items() if name.startswith("op")}
    return lambda n: [tuple(r) for r in queries[f"op{n}"](spark, case[0]).collect()]


def sha(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


def test_op1(answer, case):
    x = {i: np.array(v, float) for i, v, _ in case[3] if v is not None}
    got = {}
    for q, rank, i, score in answer(1):
        assert score == pytest.approx(float((x[q] * x[i]).sum()), abs=1e-9)
        got.setdefault(q, []).append((rank, i))
    assert set(got) == {i for i in x if i % 20 == 0}
    hit = 0
    for q, found in got.items():
        truth = sorted((-(x[q] * x[i]).sum(), i) for i in x if i != q)[:20]
        hit += len({i for _, i in truth} & {i for _, i in found})
        assert [r for r, _ in sorted(found)] == list(range(1, 21))
    assert hit / (20 * len(got)) >= 0.9


def test_op2(answer, case):
    rows, union = case[1], Union()
    fps = {t or "": fingerprint(t) for _, t in rows}
    for a in set(fps.values()):
        for b in set(fps.values()):
            if (a ^ b).bit_count() <= 2:
                union.join(a, b)
    least = {}
    for d, t in rows:
        if d is not None:
            top = union.find(fps[t or ""])
            least[top] = min(least.get(top, d), d)
    want = [(d, f"{fps[t or '']:016x}", least.get(union.find(fps[t or ""]))) for d, t in rows]
    assert sorted(answer(2), key=str) == sorted(want, key=str)


def test_op3(answer, case):
    got = sorted((r[0], *r[1:]) for r in answer(3) if r[0] is not None)
    want = sorted(r for r in contaminated(case[1], [i for i in case[2] if i[1] is not None]) if r[0] is not None)
    assert got == want and any(r[-1] for r in got)


def test_op4_and_op5(answer, case):
    tok, total = bpe.tokenizer(bpe.default_path()), 0
    want = []
    for d, t in case[1]:
        ids = tok.encode(t)
        n = len(ids.split())
        total += n + (n > 0)
        want.append((d, n, sha(ids), sha(tok.decode_text(ids))))
    assert sorted(answer(4), key=str) == sorted(want, key=str)
    got = answer(5)
    assert sorted(r[0] for r in got) == list(range(len(got))) and sum(r[5] for r in got) == total


def test_op6(answer, case):
    got = sorted(answer(6), key=lambda r: (str(r[0]), r[1], r[2]))
    want = sorted(backoff(case[1], 3, True), key=lambda r: (str(r[0]), r[1], r[2]))
    for g, w in zip(got, want, strict=True):
        assert g[:2] == w[:2] and g[2] == pytest.approx(w[2], rel=1e-9, abs=1e-9)


def test_op7_and_op10(answer, case):
    rows, seven, ten = case[1], repeats(case[1], 50), repeats(case[1], 20)
    want = [(d, seven[d, t or ""][0], seven[d, t or ""][2], seven[d, t or ""][1], seven[d, t or ""][3]) for d, t in rows if seven[d, t or ""][2]]
    assert sorted(answer(7), key=str) == sorted(want, key=str) and want
    assert sorted(answer(10), key=str) == sorted([(d, ten[d, t or ""][0], ten[d, t or ""][1], ten[d, t or ""][3]) for d, t in rows], key=str)


M = 1 << 64


def _mixed(x: int, salt: int = 0) -> int:
    x ^= salt * 0x9E3779B97F4A7C15 % M
    x ^= x >> 33
    x = x * 0xFF51AFD7ED558CCD % M
    x ^= x >> 33
    x = x * 0xC4CEB9FE1A85EC53 % M
    return x ^ x >> 33


def plain_score(model, text: str | None) -> float:
    """Word by word and byte by byte: the mean of the features' weights under the softmax of two classes."""
    from levelmine.llm.kernel import _BYTE_VALUES

    values, data, found = [int(v) for v in _BYTE_VALUES], (text or "").encode(), []
    words = [w.encode() for w in space_words(text)]
    for i, w in enumerate(words):
        h = _mixed(sum(values[b] * pow(0x9E3779B97F4A7C15, j, M) for j, b in enumerate(w)) % M)
        found.append(h >> 64 - quality.BITS)
        ago = next((d for d in range(1, quality.RETURN_MOST + 1) if i >= d and words[i - d] == w), 0)
        found.append(ago + (len(quality.GRAMS) + 1 << quality.BITS))
    for n, size in enumerate(quality.GRAMS, 1):
        for i in range(len(data) - size + 1):
            value = int.from_bytes(data[i : i + size], "little")
            found.append(((value * 0x9E3779B97F4A7C15 + size) % M * 0xD1342543DE82EF95 % M >> 64 - quality.BITS) + (n << quality.BITS))
    logit = (sum(model.weight[f] for f in found) / len(found) if found else 0.0) + model.bias
    a, b = math.exp(0.0), math.exp(logit)
    return b / (a + b)


def test_op8(spark, answer, case):
    path, rows = case[:2]
    model = quality.fit(spark.read.parquet(f"{path}/documents.parquet"), spark.read.parquet(f"{path}/labels.parquet"))
    text = {}
    for d, t in rows:
        text.setdefault(d, []).append(t)
    for d, held, score, predicted in answer(8):
        assert held == (d is not None and zlib.crc32(str(d).encode()) % 5 == 0) and predicted == int(score >= 0.3)
        if d not in (5000, 5001, 5002):
            assert any(score == pytest.approx(plain_score(model, t), abs=1e-9) for t in text[d])


def test_op9(answer, case):
    got = {r[0]: r[1:] for r in answer(9)}
    assert {i: r[0] for i, r in got.items()} == {i: len((h or "").encode()) for i, _, h in case[4]}
    assert {i: r[2:4] for i, r in got.items()} == {1: ("response", None), 2: ("revisit", 1), 3: ("response", None), 4: ("response", None)}


def test_every_query_was_called():
    assert [n for n in range(1, 11) if not any(q.startswith(f"op{n}_") for q in __spark_entry__.queries())] == []
