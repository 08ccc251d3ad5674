"""Near copies by the exact Jaccard similarity of word-shingle sets, after SimHash links.

Texts of equal shingle sets are one vertex. Pairs to look at come from three places: SimHash links within `radius` bits
(3-word fingerprints and BK-trees, as op2) and two stars a text; then stars around one text of each prefix shingle whose
texts are not in one component yet; at last the pairs of such a shingle that are in different components and of sizes
that the similarity allows; where many texts hold it, tasks bound the pairs by the parities before they send them on.
Of the latter a forest over the components is verified first, by its nearest pairs; pairs that it has joined are not
asked for any more, all others are. Every pair is verified on whole sets before it links, and large groups close by stars.

Prefixes: in one order of all shingles, two sets of the similarity share one among the first n - ceil(s n) + 1 of each,
so no pair is missed, whatever the order is. Shingles that many texts of a sample hold come last in it, which only
keeps the groups of a prefix shingle small. Sizes, places in the order and parities of hashed bits bound what two sets
can share; only sets of pairs within these bounds are built for the verification.

Defined results. Wordless and null texts are near copies of each other. Texts of fewer words than a shingle are one
shingle. Sets are of 64-bit hashes.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelmine.llm.components import components
from levelmine.llm.kernel import give_back
from levelmine.llm.simhash import fingerprints, links, shingles
from levelmine.session import materialise, release

SHINGLE = 5
SIMILARITY = (4, 5)
#: Texts of the sample that orders shingles, and how many of them make a shingle come last. No result depends on them.
ORDER_SAMPLE, ORDER_HELD = 4000, 4
#: 64-bit words of a set's parities, and of the further ones that sets of more than WIDE_FROM shingles have.
PARITY_WORDS, WIDE_WORDS, WIDE_FROM = 16, 256, 1600
#: Texts of a prefix shingle from which their pairs are bounded in a task and not by a join, and of one side of a piece of it.
MANY, PIECE = 8, 4096
_U = np.uint64


def sets(column: pa.Array, shingle: int = SHINGLE) -> Iterator[np.ndarray]:
    """The sorted shingle set of each text."""
    for _, edge, hashes in shingles(column, shingle):
        for i in range(len(edge) - 1):
            yield np.unique(hashes[edge[i] : edge[i + 1]])


def _signature(grams: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(grams.tobytes(), digest_size=8).digest(), "little", signed=True)


def _parities(grams: np.ndarray, words: int) -> np.ndarray:
    odd = np.bincount((grams % _U(64 * words)).astype(np.int64), minlength=64 * words) & 1
    return np.packbits(odd.astype(np.bool_)).view(_U)


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int32)
    values = np.concatenate(parts) if parts else np.zeros(0, _U)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(values.view(np.int64)))


def _keys(last: np.ndarray, shingle: int, similarity: tuple[int, int]):
    """Signature, fingerprint, set size, prefix and parities of each row; shingles of `last` end the order."""
    p, q = similarity

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sig, size, prefix, parity, wide = [], [], [], [], []
            for grams in sets(batch.column(2), shingle):
                n = len(grams)
                sig.append(_signature(grams))
                size.append(n)
                late = last[np.minimum(np.searchsorted(last, grams), len(last) - 1)] == grams if len(last) else np.zeros(n, np.bool_)
                prefix.append(np.concatenate([grams[~late], grams[late]])[: n + (-p * n) // q + 1 if n else 0])
                parity.append(_parities(grams, PARITY_WORDS))
                wide.append(_parities(grams, WIDE_WORDS) if n > WIDE_FROM else np.zeros(0, _U))
            fp = fingerprints(batch.column(2)).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sig, pa.int64()), pa.array(fp), pa.array(size, pa.int32()), _lists(prefix), _lists(parity), _lists(wide)], ["doc_id", "key", "sig", "fp", "n", "prefix", "parity", "wide"])
        give_back()

    return run


def _whole(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = list(sets(batch.column(2), shingle))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([_signature(g) for g in found], pa.int64()), _lists(found)], ["doc_id", "key", "sig", "grams"])
        give_back()

    return run


def _common(rows: DataFrame, shingle: int) -> np.ndarray:
    """Shingles that many texts of a sample hold."""
    cuts = max(1, rows.count() // ORDER_SAMPLE)
    texts = rows.filter(F.pmod("key", F.lit(cuts)) == 0).select("doc_id", "key", "text").dropDuplicates(["key"])
    held = texts.mapInArrow(_whole(shingle), "doc_id long, key long, sig long, grams array<long>").dropDuplicates(["sig"])
    many = held.select(F.explode("grams").alias("gram")).groupBy("gram").count().filter(F.col("count") >= ORDER_HELD)
    return np.sort(many.select("gram").toArrow()["gram"].to_numpy().astype(np.int64).view(_U))


def _reaches(shared: Column, a: Column, b: Column, similarity: tuple[int, int]) -> Column:
    """Whether so many shared shingles of sets of sizes a and b make the similarity."""
    p, q = similarity
    return (p + q) * shared.cast("long") >= p * (a.cast("long") + b.cast("long"))


def _may(a: str, b: str, similarity: tuple[int, int]) -> Column:
    """Whether rows a and b of a prefix shingle can have the similarity if it is the first that they share."""
    n, m = F.col(f"{a}.n"), F.col(f"{b}.n")
    return _reaches(F.least(n, m), n, m, similarity) & _reaches(F.least(n - F.col(f"{a}.pos"), m - F.col(f"{b}.pos")), n, m, similarity)


def _pairs_of_many(similarity: tuple[int, int]):
    """Pairs of one piece of a prefix shingle's texts that are in different components and within the bounds of sizes,
    places and parities, each where it shares its first shingle. Pieces are cells (i, j) of a grid of parts.

    A row is a pair of components, its pairs by how far their parities differ; the rows of `tree` span the components."""
    p, q = similarity

    def reaches(shared: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
        return (p + q) * shared >= p * (n + m)

    def run(table: pa.Table) -> pa.Table:
        sig, top, part = (table[c].to_numpy() for c in ("sig", "top", "part"))
        n, pos = (table[c].to_numpy().astype(np.int64) for c in ("n", "pos"))
        odd = table["parity"].combine_chunks().flatten().to_numpy().view(_U).reshape(len(sig), -1)
        before, same = table["before"], table["i"][0].as_py() == table["j"][0].as_py()
        sets: dict[int, frozenset] = {}
        earlier = lambda r: sets[r] if r in sets else sets.setdefault(r, frozenset(before[r].as_py()))
        one = np.arange(len(sig)) if same else np.flatnonzero(part == table["i"][0].as_py())
        other = one if same else np.flatnonzero(part == table["j"][0].as_py())
        a, b, far = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for r in one.tolist():
            at = other[other > r] if same else other
            at = at[top[at] != top[r]]
            at = at[reaches(np.minimum(n[at], n[r]), n[at], n[r]) & reaches(np.minimum(n[at] - pos[at], n[r] - pos[r]), n[at], n[r])]
            differ = np.bitwise_count(odd[at] ^ odd[r]).sum(axis=1, dtype=np.int64)
            near = reaches((n[at] + n[r] - differ) // 2, n[at], n[r])
            near[near] = [earlier(r).isdisjoint(earlier(x)) for x in at[near].tolist()]
            a.append(np.full(near.sum(), r))
            b.append(at[near])
            far.append(differ[near])
        return _by_components(sig, top, *map(np.concatenate, (a, b, far)))

    return run


def _by_components(sig: np.ndarray, top: np.ndarray, a: np.ndarray, b: np.ndarray, far: np.ndarray) -> pa.Table:
    """Pairs (a, b) of places in sig as a row for each pair of components, the least `far` first."""
    low, high = np.minimum(top[a], top[b]), np.maximum(top[a], top[b])
    order = np.lexsort((sig[b], sig[a], far, high, low))
    a, b, far, low, high = (x[order] for x in (a, b, far, low, high))
    new = np.ones(len(a), np.bool_)
    new[1:] = (low[1:] != low[:-1]) | (high[1:] != high[:-1])
    first = np.flatnonzero(new)
    ends = pa.array(np.append(first, len(a)).astype(np.int32))
    names, at = np.unique(np.concatenate([low[first], high[first]]), return_inverse=True)
    root, tree = list(range(len(names))), np.zeros(len(first), np.bool_)

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = x = root[root[x]]
        return x

    for k in np.argsort(far[first], kind="stable").tolist():
        x, y = find(int(at[k])), find(int(at[len(first) + k]))
        tree[k], root[x] = x != y, y
    lists = [pa.ListArray.from_arrays(ends, pa.array(sig[x])) for x in (a, b)]
    return pa.table([pa.array(low[first]), pa.array(high[first]), pa.array(tree), *lists], ["low", "high", "tree", "a", "b"])


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def near_copies(docs: DataFrame, radius: int = 2, shingle: int = SHINGLE, similarity: tuple[int, int] = SIMILARITY) -> DataFrame:
    """doc_id, key (of the text, as decontaminate.text_key), component: one row for each of docs.

    Components are those of all pairs of texts whose sets have the similarity."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("key"), text.alias("text"))
    keys = materialise(rows.mapInArrow(_keys(_common(rows, shingle), shingle, similarity), "doc_id long, key long, sig long, fp long, n int, prefix array<long>, parity array<long>, wide array<long>"), "keys")
    one = materialise(keys.dropDuplicates(["sig"]), "vertices")
    token = Window.partitionBy("token")
    posting = one.select("sig", "n", F.posexplode("prefix").alias("pos", "token"))
    posting = materialise(posting.withColumn("held", F.count("*").over(token)).filter("held > 1"), "postings")

    heads = materialise(one.groupBy("fp").agg(F.min("sig").alias("head")), "fingerprints")
    head = lambda end: heads.select(F.col("fp").alias(end), F.col("head").alias(f"{end}_head"))
    close = links(heads.select("fp"), radius).join(head("a"), "a").join(head("b"), "b").select(F.col("a_head").alias("a"), F.col("b_head").alias("b"))
    close = materialise(_ordered(close.unionByName(one.join(heads, "fp").select(F.col("sig").alias("a"), F.col("head").alias("b")))), "close")

    def verified(pairs: DataFrame) -> DataFrame:
        """The pairs within the bounds, and whether they are near."""
        side = lambda end: one.select(F.col("sig").alias(end), *[F.col(c).alias(f"{end}_{c}") for c in ("n", "parity", "wide")])
        count = lambda c: F.aggregate(F.zip_with(f"a_{c}", f"b_{c}", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
        differ = F.when((F.size("a_wide") > 0) & (F.size("b_wide") > 0), count("wide")).otherwise(count("parity"))
        bound = _reaches(F.floor((F.col("a_n") + F.col("b_n") - differ) / 2), F.col("a_n"), F.col("b_n"), similarity)
        pairs = materialise(_ordered(pairs).join(side("a"), "a").join(side("b"), "b").filter(bound).select("a", "b"), "pairs")
        asked = one.join(pairs.select(F.col("a").alias("sig")).union(pairs.select("b")).distinct(), "sig", "left_semi")
        asked = materialise(asked.select(F.col("doc_id").alias("of_doc"), F.col("key").alias("of_key")), "asked")
        mine = rows.join(asked, (F.col("key") == F.col("of_key")) & F.col("doc_id").eqNullSafe(F.col("of_doc")), "left_semi")
        whole = materialise(mine.mapInArrow(_whole(shingle), "doc_id long, key long, sig long, grams array<long>").select("sig", "grams").dropDuplicates(["sig"]), "grams")
        a, b = whole.select(F.col("sig").alias("a"), F.col("grams").alias("x")), whole.select(F.col("sig").alias("b"), F.col("grams").alias("y"))
        near = _reaches(F.size(F.array_intersect("x", "y")), F.size("x"), F.size("y"), similarity)
        out = materialise(pairs.join(a, "a").join(b, "b").select("a", "b", near.alias("near")), "verified")
        release(pairs, asked, whole)
        return out

    def named(tested: DataFrame) -> DataFrame:
        return components(tested.filter("near").select("a", "b")).select(F.col("vertex").alias("sig"), F.col("least").alias("top"))

    # each text with the least text of its most frequent prefix shingle, and with the least text of all of them
    hub = posting.select("held", F.struct("sig", "n", "pos").alias("x"), F.min(F.struct("sig", "n", "pos")).over(token).alias("y"))
    hub = hub.filter(F.col("x.sig") != F.col("y.sig")).filter(_may("x", "y", similarity)).groupBy(F.col("x.sig").alias("a"))
    stars = hub.agg(F.array(F.max_by("y.sig", F.struct("held", "y.sig")), F.min("y.sig")).alias("hubs")).select("a", F.explode("hubs").alias("b"))
    tested = verified(stars.union(close))
    tops = named(tested)
    untested = lambda pairs: verified(_ordered(pairs).join(tested, ["a", "b"], "left_anti"))
    for last in (False, True):
        now = posting.join(tops, "sig", "left").withColumn("top", F.coalesce("top", "sig"))
        now = now.withColumns({"low": F.min("top").over(token), "high": F.max("top").over(token)}).filter("low <> high").select("token", F.struct("sig", "n", "pos", "top").alias("x"))
        if last:  # what is left: pairs of different components, of sizes that the similarity allows
            step = math.log(similarity[1] / similarity[0])
            band = F.floor(F.log(F.greatest(F.col("x.n"), F.lit(1)).cast("double")) / step).cast("int")
            now = materialise(now.withColumns({"band": band, "held": F.count("*").over(token)}), "open")
            # shingles of many texts: a grid of pieces, each task sends on what is within all bounds
            many = now.filter(F.col("held") >= MANY).select("token", "x.*", F.ceil(F.col("held") / PIECE).cast("int").alias("parts"))
            many = many.join(one.select("sig", "parity", "prefix"), "sig").withColumn("part", F.pmod(F.xxhash64("sig", F.lit(2)), F.col("parts")).cast("int"))
            cells = many.select("token", "sig", "n", "pos", "top", "parity", F.slice("prefix", 1, F.col("pos")).alias("before"), "part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("with"))
            cells = cells.withColumns({"i": F.least("part", "with"), "j": F.greatest("part", "with")}).drop("with")
            many = cells.groupBy("token", "i", "j").applyInArrow(_pairs_of_many(similarity), "low long, high long, tree boolean, a array<long>, b array<long>")
            many = materialise(many, "bounded")
            tested = tested.unionByName(untested(many.filter("tree").select(F.col("a")[0].alias("a"), F.col("b")[0].alias("b"))))
            tops = named(tested)
            known = lambda old, new: tops.select(F.col("sig").alias(old), F.col("top").alias(new))
            many = many.join(known("low", "p"), "low", "left").join(known("high", "q"), "high", "left")
            many = many.filter(F.coalesce("p", "low") != F.coalesce("q", "high")).select(F.explode(F.arrays_zip("a", "b")).alias("x")).select("x.*")
            few = now.filter(F.col("held") < MANY).join(known("at", "new"), F.col("x.sig") == F.col("at"), "left")
            few = few.select("token", "band", F.struct("x.sig", "x.n", "x.pos", F.coalesce("new", "x.top").alias("top")).alias("x"))
            near = few.select("token", F.explode(F.array("band", F.col("band") + 1)).alias("band"), F.col("x").alias("y"))
            # sets of one band, or of neighbouring ones; the smaller set of a pair of two bands is y
            both = few.join(near, ["token", "band"]).filter("x.top <> y.top and x.sig <> y.sig")
        else:  # stars around other centres, so that large groups close before all pairs are asked for; texts that share
            # many shingles have one centre for all of them
            both = now.withColumn("y", F.min_by("x", F.xxhash64("x.sig", F.lit(1))).over(token))
        pairs = both.filter((F.col("x.top") != F.col("y.top")) & _may("x", "y", similarity)).select(F.col("x.sig").alias("a"), F.col("y.sig").alias("b"))
        pairs = pairs.unionByName(many) if last else pairs
        tested = tested.unionByName(untested(pairs))
        tops = named(tested)
    release(one, posting, heads, close)
    return keys.select("doc_id", "key", "sig").join(tops, "sig", "left").select("doc_id", "key", F.coalesce("top", "sig").alias("component"))
