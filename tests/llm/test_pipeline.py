from __future__ import annotations

import pytest

import corpus_pipeline
from levelmine.llm import bpe
from levelmine.session import materialise
from tests.llm.support import frame
from tests.llm.test_decontaminate import brute as contaminated
from tests.llm.test_decontaminate import words
from tests.llm.test_repeats import brute as repeats
from tests.llm.test_simhash import fingerprint

pytest.importorskip("public_tokenizers")


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """A small corpus whose marked documents are of low quality, with copies, a shared passage and a leak."""
    import random

    rng = random.Random(8)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(500)]
    prose = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    passage, leak = prose(60), prose(15)
    rows, marks = [], []
    for i in range(120):
        text = prose(rng.randint(30, 90))
        if i % 11 == 0:
            text[10:10] = passage
        if i == 16:
            text[5:5] = leak
        good = i % 6 != 5
        rows.append((i, " ".join(w if good else w + "$$$" for w in text)))
        marks.append((i, int(good), 0))
    rows += [(200, rows[3][1]), (201, rows[3][1].upper()), (202, None), (203, "")]
    path = str(tmp_path_factory.mktemp("pipeline"))
    frame(spark, rows).write.parquet(f"file://{path}/documents.parquet")
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(f"file://{path}/labels.parquet")
    spark.createDataFrame([(1, " ".join(leak))], "item_id long, text string").write.parquet(f"file://{path}/benchmark.parquet")
    return f"file://{path}", rows, dict((i, q) for i, q, _ in marks), leak


def test_each_stage_does_what_it_says(spark, folder):
    path, rows, good, leak = folder
    docs = spark.read.parquet(f"{path}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        docs = materialise(stage(spark, docs, path), "stage")
        seen[name] = before, docs
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == columns
    before, after = seen["quality classifier"]
    kept = {r["doc_id"] for r in after.collect()}
    assert all(i in kept for i, q in good.items() if q) and not any(i in kept for i, q in good.items() if not q)
    before, after = seen["SimHash near-dedup"]
    fps, group = {i: fingerprint(t) for i, t in before.items()}, {}
    for i in sorted(fps):  # the corpus has no chains of near copies: the least of each neighbourhood stays
        group.setdefault(min(j for j in fps if (fps[i] ^ fps[j]).bit_count() <= 2), set()).add(i)
    assert {r["doc_id"] for r in after.collect()} == set(group)
    assert not {200, 201} & set(group)
    before, after = seen["suffix-array dedup"]
    want = repeats(list(before.items()), 50)
    now = {r["doc_id"]: r for r in after.collect()}
    for i, t in before.items():
        n, gone, _, _ = want[i, t or ""]
        if gone:
            assert len(now[i]["text"].split()) == n - gone and now[i]["n_chars"] == len(now[i]["text"])
        else:
            assert now[i]["text"] == t
    assert sum(w[1] > 0 for w in want.values()) >= 5
    before, after = seen["benchmark decontamination"]
    hit = {r[0] for r in contaminated(list(before.items()), [(1, " ".join(leak))]) if r[5]}
    assert {r["doc_id"] for r in after.collect()} == set(before) - hit and hit == {16}
    before, after = seen["BPE encoding and decoding"]
    tok = bpe.tokenizer(bpe.default_path())
    assert {r["doc_id"]: r["n_tokens"] for r in after.collect()} == {i: len(tok.encode(t).split()) for i, t in before.items()} and words


def test_run_is_the_stages_in_turn(spark, folder):
    path = folder[0]
    docs = spark.read.parquet(f"{path}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, path)
    assert sorted(map(tuple, corpus_pipeline.run(spark, path).collect()), key=str) == sorted(map(tuple, docs.collect()), key=str)


def test_every_operator_has_its_query():
    from levelmine.llm import queries

    names = [q.split("_")[0] for q in queries.queries()]
    assert names == [f"op{n}" for n in range(1, 11)]
    assert set(queries.oracle_sql()) <= set(queries.queries())
