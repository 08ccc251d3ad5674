from __future__ import annotations

import hashlib

import numpy as np
import pytest

from levelmine.llm import bpe, order
from levelmine.session import materialise, scratch_path
from tests.llm.support import corpus, frame

pytest.importorskip("public_tokenizers")


@pytest.mark.parametrize("n", [1, 2, 3, 5, 64, 1000, 4097])
def test_slots_are_a_permutation(n):
    slots = order.permuted(np.arange(n), n)
    assert sorted(slots.tolist()) == list(range(n))
    if n > 100:
        assert not np.array_equal(slots, order.permuted(np.arange(n), n, key=1)) and (slots != np.arange(n)).mean() > 0.9


def packed(rows, sequence):
    """One task's stream: [(doc_id, offset, tokens)] of each sequence."""
    tok = bpe.tokenizer(bpe.default_path())
    stream, own = [], []
    for d, t in rows:
        ids = [int(i) for i in tok.encode(t).split()]
        if ids:
            own += [(d, i) for i in range(len(ids) + 1)]
            stream += [*ids, tok.special[order.END_TOKEN]]
    return [(*own[i], stream[i : i + sequence]) for i in range(0, len(stream), sequence)]


def test_shards_hold_every_sequence_at_its_slot(spark):
    rows = corpus()
    docs = materialise(frame(spark, rows).coalesce(1), "docs")  # one file: one task, one order
    given = [(r["doc_id"], r["text"]) for r in docs.collect()]
    path = scratch_path(spark, "test-order")
    manifest = order.write_shards(order.sequences(docs, sequence=32), path, sequence=32, per_shard=64)
    want = packed(given, 32)
    at = order.permuted(np.arange(len(want)), len(want))
    slots = {int(s): w for s, w in zip(at, want, strict=True)}
    assert sum(r["n_records"] for r in manifest.collect()) == len(want)
    got = {r["slot"]: (r["doc_id"], r["offset"], r["ids"]) for r in order.read_shards(spark, path, manifest, sequence=32, per_shard=64).collect()}
    assert got == slots
    later = order.read_shards(spark, path, manifest, sequence=32, per_shard=64, start=100)
    assert sorted(r["slot"] for r in later.select("slot").collect()) == list(range(100, len(want)))


def test_query_form_and_many_tasks(spark):
    got = order.training_order(frame(spark, corpus())).collect()
    assert sorted(r["slot"] for r in got) == list(range(len(got)))
    total = sum(len(w[2]) for w in packed(corpus(), 256))
    assert sum(r["n_tokens"] for r in got) == total
    assert all(len(r["ids_sha256"]) == 64 for r in got) and hashlib


def test_nothing_to_write(spark):
    assert order.training_order(frame(spark, [(1, None), (2, "")])).count() == 0
    assert order.training_order(frame(spark, [(1, "a")]).limit(0)).count() == 0


def test_streams_by_key_do_not_depend_on_the_tasks(spark):
    def told(tasks):
        docs = frame(spark, corpus()).repartition(tasks)
        seqs = order.sequences(docs, sequence=32, streams=5)
        rows = seqs.select("pid", "i", "count", "docs", "offsets", "body").collect()
        return sorted((r["pid"], r["i"], r["count"], bytes(r["docs"]), bytes(r["offsets"])) for r in rows)

    assert told(2) == told(7)
