from __future__ import annotations

import random

from levelmine.operators.inputs import graph_doc_overlap
from levelmine.sources.graphs import document_overlap


def test_shingles_of_many_documents_link_them(spark, tmp_path):
    rng = random.Random(4)
    prose = lambda n: [str(rng.randrange(10**6)) for _ in range(n)]
    base, passage = prose(20), prose(12)
    rows = [(i, " ".join(base)) for i in range(60)]
    rows += [(100 + i, " ".join(prose(10) + passage + prose(5))) for i in range(55)]
    rows += [(200, " ".join(base[:10])), (201, " ".join(base[:9])), (202, " ".join(prose(30))), (203, None)]
    spark.createDataFrame([(d, t, "en") for d, t in rows], "doc_id long, text string, lang string").write.parquet(f"file://{tmp_path}/documents.parquet")
    words = {d: (t or "").split() for d, t in rows}
    sets = {d: {tuple(w[i : i + 8]) for i in range(len(w) - 7)} for d, w in words.items()}
    want = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 3}
    graph = document_overlap(spark, f"file://{tmp_path}")
    assert len(want) == 60 * 59 // 2 + 55 * 54 // 2 + 60
    assert {(e["src"], e["dst"]) for e in graph.edges.collect()} == want
    assert graph.vertices.count() == len(rows)


def test_a_row_for_each_document_has_its_class_and_links(spark, tmp_path):
    """Copies, a passage of many, links that only add up over shingles of several holders, odd words and ids."""
    rng = random.Random(6)
    prose = lambda n: [rng.choice("éß漢bc") + str(rng.randrange(10**6)) for _ in range(n)]
    base, passage, parts = prose(20), prose(12), [prose(8) for _ in range(6)]
    rows = [(7 * i - 200, "\t\n ".join(base)) for i in range(60)]
    rows += [((1 << 40) + i, " ".join(prose(10) + passage + prose(5))) for i in range(40)]
    rows += [(1000 + i, " ".join(sum((p for p in rng.sample(parts, 4)), []))) for i in range(30)]
    rows += [(2000, " ".join(base[:10]).upper()), (2001, " ".join(base[:9])), (2002, " ".join(prose(30))), (2003, None), (2004, ""), (2004, " ".join(passage)), (None, " ".join(base))]
    spark.createDataFrame([(d, t, "en") for d, t in rows], "doc_id long, text string, lang string").repartition(3).write.parquet(f"file://{tmp_path}/documents.parquet")
    sets: dict = {}
    for d, t in rows:
        w = (t or "").lower().split()
        sets.setdefault(d, set()).update(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    sets[None] = set()
    near = {a: [b for b in sets if a != b and len(sets[a] & sets[b]) >= 3] for a in sets}
    low = dict(zip(sets, sets, strict=True))
    for _ in sets:
        low = {a: min([low[a], *[low[b] for b in near[a]]]) if near[a] else a for a in sets}
    got = graph_doc_overlap(spark, f"file://{tmp_path}").collect()
    assert len(got) == len(sets) and len(near[1000]) > 3
    assert {(r["doc_id"], r["class_id"], r["links"]) for r in got} == {(a, low[a], len(near[a])) for a in sets}


def test_no_documents(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string").write.parquet(f"file://{tmp_path}/documents.parquet")
    assert graph_doc_overlap(spark, f"file://{tmp_path}").count() == 0
