"""Baseline B: embeddings as sets of edges, grown by joins with the edge table on any shared end, made unique by a
distinct in every round. A vertex-induced subgraph is reached when its last edge is added, so motifs of k vertices take
as many rounds as a k-clique has edges.

`motifs` goes the same rounds without a row for what only has to be counted. A set of all k vertices in which some vertex
hangs by one edge is made from the set without its greatest such edge alone, so it needs no distinct; one without such a
vertex is made by its last edge between vertices, from sets of which that edge takes up all that hang. So sets in which three
and more vertices hang, as the stars of a hub, are no one's parent, and trees go straight into the hash aggregate."""

from __future__ import annotations

import functools
import time
from collections import Counter
from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.graph.model import PropertyGraph
from levelmine.pattern.classify import classify
from levelmine.pattern.encode import bit
from levelmine.session import materialise, shuffle_width


#: Numbers of partitions of which the best is taken: fixed values.
PARTITIONS = (10, 20, 50, 100)
#: Pairs of a set and an edge that one vertex's part of a growth has at most, about; a hub's sets are dealt to several.
PAIRS = 1 << 17


def start(graph: PropertyGraph) -> DataFrame:
    """(eids, verts): single edges."""
    return graph.edges.select(F.array("eid").alias("eids"), F.array("src", "dst").alias("verts"))


def grow(graph: PropertyGraph, rows: DataFrame, most: int) -> DataFrame:
    """One more edge on any shared end, up to `most` vertices; equal edge sets become one."""
    near = graph.sym.select("u", "v", "eid")
    out = rows.select("eids", "verts", F.explode("verts").alias("u")).join(near, "u").filter(~F.array_contains("eids", F.col("eid")))
    out = out.select(F.sort_array(F.concat("eids", F.array("eid"))).alias("eids"), F.sort_array(F.array_union("verts", F.array("v"))).alias("verts"))
    return out.filter(F.size("verts") <= most).distinct()


def closed(graph: PropertyGraph, rows: DataFrame) -> DataFrame:
    """One more edge between two vertices that a set has already: as `grow`, without going through their other neighbours."""
    later = lambda x: F.transform(F.filter("verts", lambda y: y > x), lambda y: F.struct(x.alias("src"), y.alias("dst")))
    pairs = rows.select("eids", "verts", F.explode(F.flatten(F.transform("verts", later))).alias("p")).select("eids", "verts", "p.src", "p.dst")
    out = pairs.join(graph.edges.select("src", "dst", "eid"), ["src", "dst"]).filter(~F.array_contains("eids", F.col("eid")))
    return out.select(F.sort_array(F.concat("eids", F.array("eid"))).alias("eids"), "verts").distinct()


def vertex_sets(graph: PropertyGraph, k: int) -> tuple[DataFrame, list[int]]:
    """(verts, eids): the vertex-induced subgraphs of k vertices, as the largest edge set of each vertex set; and the
    rows that each round has made."""
    rows, best, made = materialise(start(graph), "relation"), None, []
    for size in range(1, k * (k - 1) // 2 + 1):
        if size > 1:
            rows = materialise(grow(graph, rows, k), "relation")
        made.append(rows.count())
        full = rows.filter(F.size("verts") == k)
        best = full if best is None else best.unionByName(full)
        if not made[-1]:
            break
    top = best.groupBy("verts").agg(F.max_by("eids", F.size("eids")).alias("eids"))
    return top, made


def _shaped(graph: PropertyGraph, rows: DataFrame) -> DataFrame:
    """Adds bits, the form of a set over its sorted vertices, and hangs: for each of them its edge if it has but one, else -1."""
    at = rows.select("eids", "verts", F.explode("eids").alias("eid")).join(graph.edges.select("eid", "src", "dst"), "eid")
    i, j = F.array_position("verts", F.col("src")) - 1, F.array_position("verts", F.col("dst")) - 1
    at = at.withColumns({"i": i.cast("int"), "j": j.cast("int")})
    bits = F.bit_or(F.expr("shiftleft(1L, cast(j * (j - 1) / 2 as int) + i)")).alias("bits")
    out = at.groupBy("eids", "verts").agg(bits, F.collect_list(F.struct("eid", "i", "j")).alias("links"))
    mine = lambda p: F.filter("links", lambda x: (x["i"] == p) | (x["j"] == p))
    alone = lambda _, p: F.when(F.size(mine(p)) == 1, mine(p)[0]["eid"]).otherwise(F.lit(-1).cast("long"))
    return out.select("eids", "verts", "bits", F.transform("verts", alone).alias("hangs"))


def _hung(graph: PropertyGraph, rows: DataFrame, most: int | None = None) -> DataFrame:
    """(eids, verts, bits, p, others, v, eid): shaped rows with one more vertex v, which hangs from the vertex at p by the edge
    eid; others: the other vertices that hang. A set comes from the one row that lacks its greatest hanging edge. most: only
    sets in which at most so many vertices hang."""
    at = rows.select("*", F.posexplode("verts").alias("p", "u"))
    at = at.withColumn("others", F.filter("verts", lambda _, q: (F.col("hangs")[q] >= 0) & (q != F.col("p"))))
    if most is not None:
        at = at.filter(F.size("others") < most)
    above = F.array_max(F.transform("hangs", lambda x, q: F.when(q == F.col("p"), F.lit(-1).cast("long")).otherwise(x)))
    at = at.withColumn("above", above).drop("hangs")
    near = graph.sym.select("u", "v", "eid")
    work = at.groupBy("u").agg(F.count("*").alias("n")).join(graph.degrees().withColumnRenamed("id", "u"), "u")
    wide = materialise(work.select("u", F.ceil(F.col("n") * F.col("deg") / PAIRS).cast("int").alias("pieces")).filter("pieces > 1"), "wide")
    at = at.join(wide, "u", "left").withColumn("piece", F.pmod(F.xxhash64("eids"), F.coalesce("pieces", F.lit(1))).cast("int"))
    near = near.join(wide, "u", "left").select("u", "v", "eid", F.explode(F.sequence(F.lit(0), F.coalesce("pieces", F.lit(1)) - 1)).alias("piece"))
    both = at.repartition(shuffle_width(at.sparkSession), "u", "piece").join(near.hint("shuffle_hash"), ["u", "piece"])
    both = both.filter((F.col("eid") > F.col("above")) & ~F.array_contains("verts", F.col("v")))
    return both.select("eids", "verts", "bits", "p", "others", "v", "eid")


def _as_sets(hung: DataFrame) -> DataFrame:
    """(eids, verts) of hung rows."""
    grown = lambda c, x: F.sort_array(F.concat(c, F.array(x)))
    return hung.select(grown("eids", "eid").alias("eids"), grown("verts", "v").alias("verts"))


def _ringed(graph: PropertyGraph, hung: DataFrame) -> DataFrame:
    """Of hung rows in which at most two vertices hang, the sets with one more edge in which none does: from v to the other
    one, or to any vertex. No row is a set before it is known that there is such an edge."""
    away = F.filter("verts", lambda _, q: q != F.col("p"))
    at = hung.withColumn("y", F.explode(F.when(F.size("others") == 1, F.col("others")).otherwise(away)))
    at = at.withColumns({"src": F.least("y", "v"), "dst": F.greatest("y", "v")})
    both = at.join(graph.edges.select("src", "dst", F.col("eid").alias("last")), ["src", "dst"])
    eids, verts = F.concat("eids", F.array("eid", "last")), F.concat("verts", F.array("v"))
    return both.select(F.sort_array(eids).alias("eids"), F.sort_array(verts).alias("verts")).distinct()


def _trees(k: int, bits: int) -> list[int]:
    """The forms of all trees on k vertices among the edges of a form."""
    edges, found = [(i, j) for j in range(k) for i in range(j) if bits >> bit(i, j) & 1], []
    for some in combinations(edges, k - 1):
        group = list(range(k))
        for i, j in some:
            group = [group[i] if g == group[j] else g for g in group]
        if len(set(group)) == 1:
            found.append(sum(1 << bit(i, j) for i, j in some))
    return found


def raw_sets(graph: PropertyGraph, k: int) -> dict[int, int]:
    """Numbers by raw form that add up, over the forms of a class, to its vertex-induced subgraphs of k >= 3 vertices.

    Of a vertex set with a cycle the largest edge set is kept. A tree is vertex-induced unless it lies in one of those, so
    their trees are taken off again."""
    open_, cyclic, counts, made, ringed = materialise(start(graph), "relation"), [], Counter(), [], []
    widest = (k - 1) * (k - 2) // 2  # edges of an open set, one of fewer than k vertices, at most
    for size in range(2, k * (k - 1) // 2 + 1):
        made = ringed + [closed(graph, x) for x in made]
        made = [materialise(functools.reduce(DataFrame.unionByName, made).distinct(), "closed")] if made else []
        cyclic, ringed = cyclic + made, []
        last = open_.filter(F.size("verts") == k - 1) if size - 1 <= widest else None
        if last is not None and not last.isEmpty():
            shaped = materialise(_shaped(graph, last), "shaped")
            if size == k - 1:
                for r in _hung(graph, shaped).groupBy("bits", "p").agg(F.count("*").alias("n")).collect():
                    counts[r["bits"] | 1 << bit(r["p"], k - 1)] += r["n"]
            else:
                cyclic.append(materialise(_as_sets(_hung(graph, shaped)), "hung"))
            ringed = [_ringed(graph, _hung(graph, shaped, most=2))]
        if size <= widest:
            more = grow(graph, open_.filter(F.size("verts") < k - 1), k - 1)
            open_ = materialise(more.unionByName(closed(graph, last)).distinct(), "relation")
    if not cyclic:
        return {}
    top = functools.reduce(DataFrame.unionByName, cyclic).groupBy("verts").agg(F.max_by("eids", F.size("eids")).alias("eids"))
    for r in _shaped(graph, top).groupBy("bits").agg(F.count("*").alias("n")).collect():
        counts[r["bits"]] += r["n"]
        counts.subtract({tree: r["n"] for tree in _trees(k, r["bits"])})
    return {form: n for form, n in counts.items() if n}


def motifs(graph: PropertyGraph, k: int, engine: str = "search_tree") -> DataFrame:
    """(code, frequency): quick patterns are counted by a hash aggregate, then classified."""
    forms = [([1] * k, form, n) for form, n in raw_sets(graph, k).items()]
    raw = graph.edges.sparkSession.createDataFrame(forms, "labels array<int>, bits long, n long")
    counts = classify(raw, engine).groupBy("code").agg(F.sum("n").cast("long").alias("frequency"))
    return counts.filter("frequency > 0")


def cliques(graph: PropertyGraph, k: int) -> DataFrame:
    """(path): cliques by rounds of edge growth: a clique of k vertices is reached when its last edge is added, so it takes
    as many rounds as it has edges. Each round keeps the edge sets that can still become one."""
    rows, edges = materialise(start(graph), "relation"), k * (k - 1) // 2
    for size in range(2, edges + 1):
        # vertices of a set in the order in which a clique's edges can come: all pairs of the first ones, then the next
        n = next(n for n in range(2, k + 1) if size <= n * (n - 1) // 2)
        opens = size == (n - 1) * (n - 2) // 2 + 1
        rows = materialise(grow(graph, rows, n).filter(F.size("verts") == n) if opens else closed(graph, rows), "relation")
    return rows.select(F.col("verts").alias("path"))


def best_partitions(graph: PropertyGraph, run: Callable[[PropertyGraph], object], partitions: tuple[int, ...] = PARTITIONS) -> list[tuple[int, float]]:
    """(partitions, seconds) of the same work under each number of shuffle partitions, fastest first; the setting is put back."""
    conf, key, taken = graph.edges.sparkSession.conf, "spark.sql.shuffle.partitions", []
    before = conf.get(key)
    try:
        for n in partitions:
            conf.set(key, str(n))
            began = time.perf_counter()
            run(graph)
            taken.append((n, time.perf_counter() - began))
    finally:
        conf.set(key, before)
    return sorted(taken, key=lambda x: x[1])


def triangles(graph: PropertyGraph) -> DataFrame:
    """(n): each vertex gathers its neighbours and sends them along its edges; common ones are counted three times."""
    sets = graph.sym.groupBy("u").agg(F.collect_set("v").alias("around"))
    e = graph.edges.select("src", "dst").join(sets.toDF("src", "a"), "src").join(sets.toDF("dst", "b"), "dst")
    return e.agg((F.coalesce(F.sum(F.size(F.array_intersect("a", "b")).cast("long")), F.lit(0).cast("long")) / 3).cast("long").alias("n"))
