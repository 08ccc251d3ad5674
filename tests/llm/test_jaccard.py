from __future__ import annotations

import random

import corpus_pipeline
import numpy as np
from levelmine.llm import jaccard
from levelmine.llm.jaccard import near_copies
from tests.llm.support import LOWER, corpus, frame, space_words
from tests.llm.test_simhash import Union, fingerprint


def grams(text):
    words = space_words((text or "").translate(LOWER))
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def similar(a, b):
    return a == b or 5 * len(a & b) >= 4 * len(a | b)


def brute(rows):
    """The groups of rows, by number, that pairs of similarity 0.8 and more connect."""
    union, of = Union(), [grams(t) for _, t in rows]
    for i in range(len(rows)):
        for j in range(i):
            if similar(of[i], of[j]):
                union.join(i, j)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(union.find(i), set()).add(i)
    return groups


def edited():
    """Prose whose copies have edits far apart, some near the similarity on both sides; two larger groups."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(3, 7)))
    rows = []
    for i in range(30):
        words = [word() for _ in range(rng.randint(60, 300))]
        rows.append((1000 * i, " ".join(words)))
        for k in range(1, 30 if i < 2 else 5):
            copy = list(words)
            for at in rng.sample(range(len(words)), max(1, round(len(words) * rng.uniform(0.002, 0.03)))):
                copy[at] = word()
            rows.append((1000 * i + k, " ".join(copy)))
    return rows


def test_groups_are_those_of_brute_force(spark):
    rows = edited() + [(900_000 + i, t) for i, (_, t) in enumerate(corpus())]
    got = {}
    for d, _, c in map(tuple, near_copies(frame(spark, rows)).collect()):
        got.setdefault(c, set()).add(d)
    assert {frozenset(g) for g in got.values()} == {frozenset(rows[i][0] for i in g) for g in brute(rows).values()}


def test_stage_drops_edited_copies_that_fingerprints_miss(spark):
    rows = edited()
    groups = brute(rows)
    far = [i for r, g in groups.items() for i in g if i != r and (fingerprint(rows[i][1]) ^ fingerprint(rows[r][1])).bit_count() > 2]
    assert len(far) > 50
    kept = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, frame(spark, rows), "").collect()}
    assert kept == {min(rows[i][0] for i in g) for g in groups.values()}


def test_stage_keeps_unlike_texts_under_repeated_and_null_ids(spark):
    texts = [t for d, t in edited() if d % 1000 == 0][:8]
    rows = [(1, texts[0]), (1, texts[1]), (2, texts[0]), (1, texts[0]), (None, texts[2]), (None, texts[3]), (None, texts[2]), (5, texts[3]), (None, texts[4]), (6, None), (None, "")]
    kept = [(r["doc_id"], r["text"]) for r in corpus_pipeline.drop_near_copies(spark, frame(spark, rows), "").collect()]
    assert sorted(kept, key=str) == sorted([(1, texts[0]), (1, texts[1]), (None, texts[2]), (5, texts[3]), (None, texts[4]), (6, None)], key=str)


def test_pairs_of_many_in_pieces(spark, monkeypatch):
    """Texts that share a beginning and differ in scattered words: all pairs are bounded in tasks, in pieces of three."""
    monkeypatch.setattr(jaccard, "MANY", 2)
    monkeypatch.setattr(jaccard, "PIECE", 3)
    rng = random.Random(8)
    base = [f"w{i}" for i in range(60)]
    rows = []
    for d in range(40):
        words = list(base)
        for at in rng.sample(range(20, 60), rng.choice((1, 2, 3, 4))):
            words[at] = f"x{rng.randrange(12)}"
        rows.append((d, " ".join(words)))
    sets = {d: {tuple(t.split()[i : i + 5]) for i in range(56)} for d, t in rows}
    top = {d: d for d in sets}
    for a in sets:
        for b in sets:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                top = {d: min(top[a], top[b]) if t in (top[a], top[b]) else t for d, t in top.items()}
    got: dict[int, set[int]] = {}
    for d, _, c in map(tuple, near_copies(frame(spark, rows)).collect()):
        got.setdefault(c, set()).add(d)
    want: dict[int, set[int]] = {}
    for d, t in top.items():
        want.setdefault(t, set()).add(d)
    assert 1 < len(want) < 40 and sorted(map(sorted, got.values())) == sorted(map(sorted, want.values()))


def test_components_do_not_depend_on_the_order_of_shingles(spark, monkeypatch):
    rng = random.Random(9)
    base = [f"w{i}" for i in range(80)]
    rows = []
    for d in range(30):
        words = list(base)
        for at in rng.sample(range(80), rng.choice((1, 2, 3))):
            words[at] = f"x{rng.randrange(9)}"
        rows.append((d, " ".join(words)))

    def classes():
        out: dict[int, list[int]] = {}
        for d, _, c in sorted(map(tuple, near_copies(frame(spark, rows)).collect())):
            out.setdefault(c, []).append(d)
        return sorted(out.values())

    sampled = classes()
    monkeypatch.setattr(jaccard, "_common", lambda rows, shingle: np.zeros(0, np.uint64))
    assert classes() == sampled


def test_few_pairs_are_verified_for_components_with_many_between_them(spark, monkeypatch):
    """Copies with scattered edits, which the stars leave in several components: one pair between two of them comes first."""
    verified = []
    real = jaccard.materialise

    def counted(df, name="table"):
        out = real(df, name)
        if name == "verified":
            verified.append(out.count())
        return out

    monkeypatch.setattr(jaccard, "materialise", counted)
    rng = random.Random(5)
    base = [f"w{i}" for i in range(100)]
    rows = []
    for d in range(160):
        words = list(base)
        for at in rng.sample(range(30, 100), rng.choice((1, 2, 3))):
            words[at] = f"x{rng.randrange(10**6)}"
        rows.append((d, " ".join(words)))
    got: dict[int, set[int]] = {}
    for d, _, c in map(tuple, near_copies(frame(spark, rows)).collect()):
        got.setdefault(c, set()).add(d)
    assert {frozenset(g) for g in got.values()} == {frozenset(g) for g in brute(rows).values()}
    assert 0 < sum(verified[2:]) < len(rows)
