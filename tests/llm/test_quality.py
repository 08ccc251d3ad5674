from __future__ import annotations

import random
import tracemalloc
import zlib

import numpy as np
import pyarrow as pa

from levelmine.llm import quality
from tests.llm.support import corpus, frame


def labelled(n=240):
    rng = random.Random(2)
    words = ["alpha", "beta", "gamma", "delta", "omega"]
    rows = []
    for i in range(n):
        good = rng.random() < 0.8
        mark = "" if good else rng.choice(["!!", "$$$", "###"])
        rows.append((i, " ".join(rng.choice(words) + mark for _ in range(rng.randint(5, 60))), int(good)))
    return rows


def test_held_out_accuracy(spark):
    rows = labelled()
    docs = frame(spark, [r[:2] for r in rows] + [(900, None), (901, ""), (None, "alpha")])
    labels = spark.createDataFrame([(i, q, 0) for i, _, q in rows] + [(None, 1, 0), (5, None, 0)], "doc_id long, quality int, toxic int")
    out = quality.score(docs, quality.fit(docs, labels)).withColumn("held_out", quality.held_out()).collect()
    truth = {i: q for i, _, q in rows}
    assert len(out) == len(rows) + 3
    for r in out:
        assert r["held_out"] == (r["doc_id"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
        assert 0 <= r["r_score"] <= 1 and r["r_predicted"] == int(r["r_score"] >= 0.3)
    held = [(r["r_predicted"], truth[r["doc_id"]]) for r in out if r["held_out"] and r["doc_id"] in truth]
    assert len(held) > 20 and np.mean([p == t for p, t in held]) > 0.95


def test_labels_of_the_held_out_fold_change_nothing(spark):
    rows = labelled(60)
    docs = frame(spark, [r[:2] for r in rows])
    held = lambda i: zlib.crc32(str(i).encode()) % 5 == 0
    a = spark.createDataFrame([(i, q) for i, _, q in rows], "doc_id long, quality int")
    b = spark.createDataFrame([(i, 1 - q if held(i) else q) for i, _, q in rows], "doc_id long, quality int")
    assert np.array_equal(quality.fit(docs, a).weight, quality.fit(docs, b).weight)


def test_no_labels_and_empty_tables(spark):
    docs = frame(spark, corpus(n=5))
    labels = spark.createDataFrame([], "doc_id long, quality int")
    model = quality.fit(docs, labels)
    out = quality.score(docs, model)
    assert out.columns == [*docs.columns, "r_score", "r_predicted"]
    assert {r["r_score"] for r in out.collect()} == {0.5}
    assert quality.score(docs.limit(0), model).count() == 0


def test_features_count_words_and_grams_of_each_row():
    texts = ["ab cd", "", "a", "abcdef", None, "é漢"]
    for _, _, kinds in quality.features(pa.array(texts)):
        sizes = [np.diff(p).tolist() for _, p in kinds]
    bytes_ = [len((t or "").encode()) for t in texts]
    assert sizes == [[2, 0, 1, 1, 0, 1]] * 2 + [[max(0, n - 2) for n in bytes_], [max(0, n - 4) for n in bytes_]]


def test_score_is_the_mean_of_its_features():
    model = quality.train(["good words here", "bad!! words!! here!!"] * 10, np.array([1, 0] * 10))
    text = "good words"
    for _, _, kinds in quality.features(pa.array([text])):
        used = np.concatenate([b for b, _ in kinds])
    want = 1 / (1 + np.exp(-(model.weight[used].mean() + model.bias)))
    assert np.isclose(model.scores(pa.array([text]))[0], want)


def test_returning_words_have_tokens():
    for _, _, kinds in quality.features(pa.array(["a a b a", "a", "b c d e b"])):
        bucket, ptr = kinds[1]
    base = quality._TABLE - quality.RETURN_MOST - 1
    assert (bucket - base).tolist() == [0, 1, 0, 2, 0, 0, 0, 0, 0, 4] and ptr.tolist() == [0, 4, 5, 10]


def test_sample_is_bounded_in_bytes(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(quality, "train", lambda texts, label: seen.append([len(t) for t in texts]))
    docs = frame(spark, [(i, "x" * (100 if i % 7 else 5000)) for i in range(60)])
    labels = spark.createDataFrame([(i, 1) for i in range(60)], "doc_id long, quality int")
    quality.fit(docs, labels, sample_bytes=1200)
    quality.fit(docs, labels)
    assert seen[0] and sum(seen[0]) <= 1200 and max(seen[0]) == 100 and len(seen[1]) > 40


def test_memory_of_training_does_not_grow_with_the_sample():
    def peak(texts):
        tracemalloc.start()
        quality.train(texts, np.arange(len(texts)) % 2, steps=1)
        try:
            return tracemalloc.get_traced_memory()[1]
        finally:
            tracemalloc.stop()

    rng = random.Random(5)
    texts = ["".join(rng.choices("abcdefghijklmnop ", k=40_000)) for _ in range(130)]
    few, many = peak(texts[:10]), peak(texts)
    assert many - few < 1_000_000 and many < 60_000_000  # features held in arrays: 10 MB more, and 121 MB


def test_texts_without_features_train_as_before():
    texts = [None, "good words here", "", "bad!! words!! here!!"] * 5
    model = quality.train(texts, np.array([1, 1, 0, 0] * 5))
    other = quality.train(quality._Texts(pa.chunked_array([texts[:3], texts[3:]])), np.array([1, 1, 0, 0] * 5))
    assert np.array_equal(model.weight, other.weight) and model.bias == other.bias
    good, bad, none = model.scores(pa.array(["good words here", "bad!! words!! here!!", None]))
    assert good > 0.9 and bad < 0.1 and 0 < none < 1
