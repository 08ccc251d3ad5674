from __future__ import annotations

import hashlib
import random
import re

import duckdb
import pytest

from levelmine.llm import decontaminate as dc
from tests.llm.support import LOWER, corpus, frame


def words(text):
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", (text or "").translate(LOWER))


def brute(rows, items):
    windows = {}
    for item, text in items:
        w = words(text)
        if item is None or not w:
            continue
        for s in range(max(1, len(w) - 9)):
            windows.setdefault(tuple(w[s : s + 10]), set()).add(item)
    out = []
    for d, text in rows:
        w, hit, found = words(text), set(), set()
        for g, ids in windows.items():
            for s in range(len(w) - len(g) + 1):
                if tuple(w[s : s + len(g)]) == g:
                    hit.update(range(s, s + len(g)))
                    found |= ids
        names = ",".join(sorted(map(str, found)))
        out.append((d, len(w), len(hit), len(found), hashlib.sha256(names.encode()).hexdigest(), bool(hit)))
    return sorted(out, key=str)


@pytest.fixture(scope="module")
def case():
    rows = corpus(seed=4)
    texts = [t for _, t in rows if t and len(words(t)) > 40]
    rng = random.Random(1)
    items = [(i, " ".join(words(t)[5 : 5 + rng.choice([4, 10, 11, 25])]).upper()) for i, t in enumerate(texts[:12])]
    items += [(50, "one"), (51, None), (52, ""), (53, "..."), (None, words(texts[0])[0]), (0, items[0][1]), (10, items[0][1]), (9, "nothing like this is said anywhere in any of these documents at all")]
    rows += [(2000, "ONE-" + items[3][1].lower() + "!" + items[3][1]), (2001, "x1y ÄÖ " + items[2][1])]
    return rows, items


@pytest.mark.parametrize("most", [500_000, 0], ids=["broadcast", "shuffled"])
def test_same_as_brute_force(spark, case, most):
    rows, items = case
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = dc.contamination(frame(spark, rows), bench, broadcast_windows=most).drop("text_key")
    want = brute(rows, items)
    assert sorted(map(tuple, got.collect()), key=str) == want
    assert 0 < sum(r[5] for r in want) < len(want)


def test_oracle_says_the_same(case):
    rows, items = case
    rows = [r for r in rows if r[0] is not None and r[0] not in (12, 1005)]
    db = duckdb.connect()
    db.execute("CREATE TABLE documents(doc_id BIGINT, text VARCHAR)")
    db.executemany("INSERT INTO documents VALUES (?, ?)", rows)
    db.execute("CREATE TABLE benchmark(item_id BIGINT, text VARCHAR)")
    db.executemany("INSERT INTO benchmark VALUES (?, ?)", items)
    assert sorted(db.execute(dc.ORACLE).fetchall(), key=str) == brute(rows, items)


def test_empty_tables(spark, case):
    rows, items = case
    docs, bench = frame(spark, rows), spark.createDataFrame(items, "item_id long, text string")
    none = dc.contamination(docs, bench.limit(0))
    assert none.count() == len(rows) and none.filter("contaminated").count() == 0
    assert dc.contamination(docs.limit(0), bench).count() == 0


def test_no_python_in_the_plan(spark, case):
    rows, items = case
    df = dc.contamination(frame(spark, rows), spark.createDataFrame(items, "item_id long, text string"))
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("Python", "Pandas", "Arrow"))
