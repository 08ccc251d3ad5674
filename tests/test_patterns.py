"""Isomorphism: the exact form, the spectral key, the search tree, and what each can tell apart."""

from __future__ import annotations

import random
from itertools import combinations, permutations, product

import pytest

from levelmine.measure.stats import partition_agreement
from levelmine.pattern import exact, search_tree, spectral
from levelmine.pattern.classify import ENGINES, classify, pattern_counts
from levelmine.pattern.encode import bit, bits_of, check_size, matrix
from levelmine.pattern.names import SHAPES, name_of


def connected(k, bits):
    m = matrix(k, bits)
    seen, todo = {0}, [0]
    while todo:
        i = todo.pop()
        for j in range(k):
            if m[i][j] and j not in seen:
                seen.add(j)
                todo.append(j)
    return len(seen) == k


def renamed(labels, bits, order):
    k = len(labels)
    m = matrix(k, bits)
    return tuple(labels[i] for i in order), bits_of(k, [(i, j) for j in range(k) for i in range(j) if m[order[i]][order[j]]])


def classes(k):
    """Connected simple graphs of k vertices, one of each class, grown from those of k - 1 by one vertex."""
    if k == 1:
        return {exact.canonical((1,), 0)[0]: 0}
    out = {}
    for bits in classes(k - 1).values():
        for mask in range(1, 1 << (k - 1)):
            new = bits | mask << bit(0, k - 1)
            out.setdefault(exact.canonical((1,) * k, new)[0], new)
    return out


@pytest.mark.parametrize("k, n", [(2, 1), (3, 2), (4, 6), (5, 21), (6, 112)])
def test_number_of_classes(k, n):
    found = classes(k)
    assert len(found) == n
    assert len({spectral.key((1,) * k, b, use_labels=False) for b in found.values()}) == n
    assert len({search_tree.canonical((1,) * k, b) for b in found.values()}) == n
    plain = {spectral.key((1,) * k, b, use_labels=False, use_degrees=False) for b in found.values()}
    assert len(plain) == (111 if k == 6 else n)


def test_classes_of_seven():
    found = classes(7)
    assert len(found) == 853
    assert len({spectral.key((1,) * 7, b, use_labels=False) for b in found.values()}) == 853


#: Two graphs of eight vertices and two labelled trees of seven that share their spectral keys: fixed values.
PAIR_8 = ["01 04 05 06 12 13 47 57", "03 05 06 07 12 14 23 27"]
PAIR_7 = ("13 04 25 02 01 16", (1, 2, 1, 1, 2, 1, 1), (2, 1, 1, 1, 1, 2, 1))


def _bits(k, text):
    return bits_of(k, [(int(e[0]), int(e[1])) for e in text.split()])


def test_where_the_spectral_key_fails():
    a, b = (_bits(8, t) for t in PAIR_8)
    one = (1,) * 8
    assert spectral.key(one, a) == spectral.key(one, b)
    assert exact.canonical(one, a)[0] != exact.canonical(one, b)[0]
    assert search_tree.canonical(one, a) != search_tree.canonical(one, b)
    tree, x, y = _bits(7, PAIR_7[0]), PAIR_7[1], PAIR_7[2]
    for width in (2, 3, 4, 8):
        assert spectral.key(x, tree, width) == spectral.key(y, tree, width)
    assert not exact.isomorphic((x, tree), (y, tree))


def test_labelled_graphs_of_four_vertices():
    forms = [(labels, bits) for labels in product((1, 2, 3), repeat=4) for bits in range(64) if connected(4, bits)]
    truth = {f: exact.canonical(*f)[0] for f in forms}
    assert len(set(truth.values())) == 201
    assert partition_agreement(truth, {f: spectral.key(*f) for f in forms}) == (0, 0)
    assert partition_agreement(truth, {f: search_tree.canonical(*f) for f in forms}) == (0, 0)


def test_exact_form_against_all_permutations():
    rng = random.Random(1)
    for _ in range(40):
        labels, bits = tuple(rng.randint(1, 2) for _ in range(4)), rng.randrange(1, 64)
        same = {renamed(labels, bits, p) for p in permutations(range(4))}
        for other in (tuple(rng.randint(1, 2) for _ in range(4)), tuple(sorted(labels))):
            for b in (bits, rng.randrange(1, 64)):
                assert exact.isomorphic((labels, bits), (other, b)) == ((other, b) in same)


@pytest.mark.parametrize("k", [3, 5, 7])
def test_renaming_changes_no_key(k):
    rng = random.Random(k)
    for _ in range(20):
        labels, bits = tuple(rng.randint(1, 3) for _ in range(k)), rng.randrange(1 << k * (k - 1) // 2)
        order = list(range(k))
        rng.shuffle(order)
        other = renamed(labels, bits, order)
        assert exact.canonical(labels, bits)[0] == exact.canonical(*other)[0]
        assert spectral.key(labels, bits) == spectral.key(*other)
        assert search_tree.canonical(labels, bits) == search_tree.canonical(*other)


def test_places_and_orbits():
    code, place, orbit = exact.canonical((1, 1, 1), bits_of(3, [(0, 1), (1, 2)]))
    assert sorted(place) == [0, 1, 2] and orbit[0] == orbit[2] != orbit[1]
    assert len(set(exact.canonical((1,) * 5, bits_of(5, combinations(range(5), 2)))[2])) == 1
    assert len(set(exact.canonical((1, 2, 3), 7)[2])) == 3


def test_edge_labels_tell_patterns_apart():
    chain = bits_of(3, [(0, 1), (1, 2)])
    a = exact.canonical((1, 1, 1), chain, ((bit(0, 1), 2), (bit(1, 2), 1)))
    b = exact.canonical((1, 1, 1), chain, ((bit(0, 1), 1), (bit(1, 2), 2)))
    assert a[0] == b[0] != exact.canonical((1, 1, 1), chain)[0]
    assert len(set(a[2])) == 3
    assert exact.canonical((1, 1, 1), chain, ((0, 1), (2, 1)))[0] == exact.canonical((1, 1, 1), chain)[0]


def test_polynomials():
    assert spectral.charpoly(matrix(3, 7)) == (0, -3, -2)
    big = spectral.charpoly(spectral.weighted((63,) * 8, matrix(8, (1 << 28) - 1), 6))
    assert max(map(abs, big)) > 1 << 64  # exact beyond machine words
    rng = random.Random(2)
    for _ in range(10):
        bits = rng.randrange(1 << 15)
        roots = spectral.eigenvalues((1,) * 6, bits, use_labels=False)
        poly = (1, *spectral.charpoly(matrix(6, bits)))
        for x in roots:
            assert abs(sum(c * x ** (6 - i) for i, c in enumerate(poly))) < 1e-6


def test_guards():
    with pytest.raises(ValueError):
        check_size(9)
    with pytest.raises(ValueError):
        spectral.key((0, 0), 1)
    with pytest.raises(ValueError):
        spectral.key((300, 1), 1)


def test_names():
    for name, (k, edges) in SHAPES.items():
        assert name_of(exact.canonical((1,) * k, bits_of(k, edges))[0]) == name
    assert name_of(exact.canonical((1, 2), 1)[0]) is None


def test_engines_agree_on_data(spark):
    rows = [(list(labels), bits) for labels in product((1, 2), repeat=4) for bits in range(64) if connected(4, bits)]
    raw = spark.createDataFrame(rows, "labels array<int>, bits long")
    truth = None
    for engine in ENGINES:
        keys = {(tuple(r["labels"]), r["bits"]): r["code"] for r in classify(raw, engine).collect()}
        assert len(keys) == len(rows)
        truth = truth or keys
        assert partition_agreement(truth, keys) == (0, 0)
    counts = pattern_counts(raw, labelled=False)
    assert sum(r["frequency"] for r in counts.collect()) == len(rows) and counts.count() == 6
    with pytest.raises(ValueError):
        classify(raw, "guess")
