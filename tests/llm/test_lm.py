from __future__ import annotations

import math
from collections import Counter

import pytest

from levelmine.llm.lm import backoff_by_rows, stupid_backoff
from tests.llm.support import corpus, frame, space_words


def brute(rows, order, leave_out):
    docs = rows
    grams = lambda w: Counter(tuple(w[i : i + n]) for n in range(1, order + 1) for i in range(len(w) - n + 1))
    count, total = Counter(), 0
    for _, t in docs:
        count.update(grams(space_words(t)))
        total += len(space_words(t))
    out = []
    for d, t in rows:
        w = space_words(t)
        own = grams(w) if leave_out else Counter()
        c = lambda g: count[g] - own[g]  # noqa: B023, E731
        score = 0.0
        for i in range(len(w)):
            penalty = 0.0
            for n in range(min(order, i + 1), 0, -1):
                g = tuple(w[i - n + 1 : i + 1])
                if n == 1:
                    score += penalty + math.log(max(c(g), 0.5) / max(1, total - (len(w) if leave_out else 0)))
                elif c(g) > 0:
                    score += penalty + math.log(c(g) / c(g[:-1]))
                    break
                penalty += math.log(0.4)
        out.append((d, len(w), score))
    return out


@pytest.mark.parametrize("leave_out", [True, False])
@pytest.mark.parametrize("layout", [stupid_backoff, backoff_by_rows])
@pytest.mark.parametrize("order", [1, 2, 3])
def test_same_as_brute_force(spark, order, layout, leave_out):
    rows = corpus(n=30)
    got = sorted(map(tuple, layout(frame(spark, rows), order, leave_out=leave_out).collect()), key=lambda r: (str(r[0]), r[1], r[2]))
    want = sorted(brute(rows, order, leave_out), key=lambda r: (str(r[0]), r[1], r[2]))
    assert len(got) == len(want)
    for g, w in zip(got, want, strict=True):
        assert g[:2] == w[:2] and g[2] == pytest.approx(w[2], rel=1e-9, abs=1e-9)
        assert g[3] is None if not w[1] else g[3] == pytest.approx(w[2] / w[1], rel=1e-9, abs=1e-9)


def test_empty_table(spark):
    assert stupid_backoff(frame(spark, []).limit(0)).count() == 0
