"""Stupid-backoff language-model scores.

The counts of all 1- to `order`-grams of the corpus are tables partitioned by hash, joined to the documents' exploded
n-grams; the logarithms are summed per document. Two layouts give the same scores:

* `backoff_by_rows`: DataFrame functions only. A row for each n-gram of each table, a row for each word's n-grams, two
  equi-joins. N-grams are compared as text.
* `stupid_backoff`: the same tables with rows packed. Documents are dealt to chunks by key; a chunk's n-grams, one of each
  with its number, go to the tables' partitions (buckets), which add up the numbers of all chunks and answer with the
  totals; the chunk joins them to its exploded n-grams and sums per document. A frequent n-gram is one entry a chunk,
  never a row per occurrence. Two passes use one exchange of the texts. N-grams are told apart by 44 bits of hash within
  a bucket, besides the bucket itself. Hashes travel as sorted steps, byte plane by byte plane under an entropy coder.

A word scores count(n-gram) / count(its context); where the n-gram is unseen, the next shorter one times ALPHA; a single
word its share of all words; an unseen word counts UNSEEN. With leave_out, a document's own occurrences are taken off
all counts, so that it is scored by the others. Words are as in the text, cut at white space.

Defined results. Null or wordless text: 0 words, score 0, mean null. Every row is a document of its own, also one that
repeats. No rows give no rows. A long text is cut into words whole, in one task.
"""

from __future__ import annotations

import math
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.llm.kernel import gram_hashes, within_rows, word_blocks
from levelmine.llm.repeats import _cuts, _tidy
from levelmine.llm.sizes import group_count
from levelmine.session import materialise

ORDER, ALPHA, UNSEEN = 3, 0.4, 0.5
_BITS = 44
_U = np.uint64


def _packed(x: np.ndarray, kind: str) -> tuple[bytes, bytes]:
    """Numbers in few bytes each, the planes of their bytes compressed; those that do not fit stand in a second array."""
    import zstandard

    top = np.iinfo(kind).max
    small = np.minimum(x, _U(top)).astype(kind)
    planes = small.view(np.uint8).reshape(len(small), -1).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes()), x[x >= _U(top)].astype("<u8").tobytes()


def _unpacked(small: bytes, large: bytes, kind: str) -> np.ndarray:
    import zstandard

    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(small), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    x = np.ascontiguousarray(planes.T).reshape(-1).view(kind).astype(_U)
    x[x == _U(np.iinfo(kind).max)] = np.frombuffer(large, "<u8")
    return x


class _Texts:
    """The words of a chunk's documents: their hashes, and where each document's begin."""

    def __init__(self, table: pa.Table):
        hashes, sizes = [np.zeros(0, _U)], [np.zeros(0, np.int64)]
        for _, _, words in word_blocks(table["text"].cast(pa.large_string())):
            hashes.append(words.hashes())
            sizes.append(words.counts())
        self.hashes = np.concatenate(hashes)
        self.ptr = np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype(np.int64)


class _Grams:
    """The n-grams of a chunk: positions that have one, distinct keys (bucket, then hash), each position's key, numbers."""

    def __init__(self, chunk: _Texts, n: int, buckets: int):
        self.at = np.flatnonzero(within_rows(chunk.ptr, n))
        grams = gram_hashes(chunk.hashes, n)[self.at] if len(self.at) else np.zeros(0, _U)
        keys = (grams % _U(buckets)) << _U(_BITS) | grams >> _U(64 - _BITS)
        self.keys, self.which, self.count = np.unique(keys, return_inverse=True, return_counts=True)

    def cuts(self) -> list[tuple[int, int, int]]:
        return _cuts(self.keys >> _U(_BITS))


_PART = "array<struct<keys:binary,keys_more:binary,counts:binary,counts_more:binary>>"
_ASK = f"bucket int, chunk int, n {_PART}"
_REPLY = "chunk int, bucket int, n array<struct<counts:binary,counts_more:binary>>"
_ASK_ARROW = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("n", pa.list_(pa.struct([(c, pa.binary()) for c in ("keys", "keys_more", "counts", "counts_more")])))])
_REPLY_ARROW = pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("n", pa.list_(pa.struct([("counts", pa.binary()), ("counts_more", pa.binary())])))])
_NONE = {"keys": b"", "keys_more": b"", "counts": b"", "counts_more": b""}


def _ask(table: pa.Table, order: int, buckets: int) -> pa.Table:
    """One row a bucket; entry n - 1 has the n-grams."""
    chunk, number, rows = _Texts(table), table["chunk"][0].as_py(), {}
    for n in range(1, order + 1):
        grams = _Grams(chunk, n, buckets)
        for k, a, b in grams.cuts():
            step = np.diff(grams.keys[a:b] & _U((1 << _BITS) - 1), prepend=_U(0))
            body = dict(zip(_NONE, (*_packed(step, "<u4"), *_packed(grams.count[a:b].astype(_U), "u1")), strict=True))
            rows.setdefault(k, [_NONE] * order)[n - 1] = body
    return pa.table([list(rows), [number] * len(rows), list(rows.values())], schema=_ASK_ARROW)


def _totals(table: pa.Table) -> pa.Table:
    """A partition of the count tables: adds up, and answers each chunk in its own order."""
    table = table.to_pydict()
    told = [[{"counts": b"", "counts_more": b""} for _ in row] for row in table["n"]]
    for n in range(len(table["n"][0])):
        rows = [i for i, row in enumerate(table["n"]) if row[n]["keys"]]
        if not rows:
            continue
        part = [table["n"][i][n] for i in rows]
        keys = [np.cumsum(_unpacked(p["keys"], p["keys_more"], "<u4")) | _U(table["bucket"][i]) << _U(_BITS) for i, p in zip(rows, part, strict=True)]
        edge = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
        keys = np.concatenate(keys)
        count = np.concatenate([_unpacked(p["counts"], p["counts_more"], "u1") for p in part]).astype(np.int64)
        order = np.argsort(keys)
        keys, count = keys[order], count[order]
        first = np.ones(len(keys), np.bool_)
        first[1:] = keys[1:] != keys[:-1]
        total = np.empty(len(keys), _U)
        total[order] = np.add.reduceat(count, np.flatnonzero(first))[np.cumsum(first) - 1].astype(_U)
        for at, i in enumerate(rows):
            told[i][n] = dict(zip(("counts", "counts_more"), _packed(total[edge[at] : edge[at + 1]], "u1"), strict=True))
    return pa.table([pa.array(table["chunk"], pa.int32()), pa.array(table["bucket"], pa.int32()), pa.array(told, _REPLY_ARROW.field("n").type)], schema=_REPLY_ARROW)


def _counts(chunk: _Texts, replies: pa.Table, order: int, buckets: int, leave_out: bool) -> list[np.ndarray]:
    """For n = 1..order: each word position's count of the n-gram that starts there (0 where none does)."""
    said = replies.to_pydict()
    got = dict(zip(said["bucket"], said["n"], strict=True))
    doc = np.repeat(np.arange(len(chunk.ptr) - 1), np.diff(chunk.ptr))
    out = []
    for n in range(1, order + 1):
        grams = _Grams(chunk, n, buckets)
        total = np.zeros(len(grams.keys), np.int64)
        for k, a, b in grams.cuts():
            total[a:b] = _unpacked(got[k][n - 1]["counts"], got[k][n - 1]["counts_more"], "u1").astype(np.int64)
        here = np.zeros(len(chunk.hashes), np.int64)
        here[grams.at] = total[grams.which]
        if leave_out:
            _, which, own = np.unique(grams.which * len(chunk.ptr) + doc[grams.at], return_inverse=True, return_counts=True)
            here[grams.at] -= own[which]
        out.append(here)
    return out


def _summed(table: pa.Table, replies: pa.Table, order: int, buckets: int, alpha: float, leave_out: bool) -> pa.Table:
    """Per row: words, the score without the number of all words, and how often that number divides."""
    chunk = _Texts(table)
    m, ptr = len(chunk.hashes), chunk.ptr
    counts = _counts(chunk, replies, order, buckets, leave_out)
    place = np.arange(m) - np.repeat(ptr[:-1], np.diff(ptr))
    value, open_, penalty = np.zeros(m), np.ones(m, np.bool_), np.zeros(m)
    for n in range(order, 1, -1):
        can = np.flatnonzero(open_ & (place >= n - 1))
        seen = counts[n - 1][can - n + 1]
        hit = seen > 0
        at = can[hit]
        value[at] = np.log(seen[hit] / counts[n - 2][at - n + 1]) + penalty[at]
        open_[at] = False
        penalty[can[~hit]] += math.log(alpha)
    rest = np.flatnonzero(open_)
    value[rest] = np.log(np.maximum(counts[0][rest], UNSEEN)) + penalty[rest]
    single = np.concatenate([[0], np.cumsum(open_)])
    # sums by document, not differences of one long running sum, so that a document's score is its own alone
    per_doc = np.zeros(len(ptr) - 1)
    full = np.flatnonzero(np.diff(ptr))
    if len(full):
        per_doc[full] = np.add.reduceat(value, ptr[:-1][full])
    return pa.table({"doc_id": table["doc_id"].cast(pa.int64()), "n_words": np.diff(ptr), "part": per_doc, "singles": np.diff(single[ptr])})


def _scored(parts: DataFrame, leave_out: bool) -> DataFrame:
    """parts: the sums without the number of all words, and how often that number divides."""
    words = parts.agg(F.sum("n_words")).first()[0] or 0
    others = F.greatest(F.lit(words) - (F.col("n_words") if leave_out else F.lit(0)), F.lit(1))
    score = F.col("part") - F.col("singles") * F.log(others.cast("double"))
    return parts.select("doc_id", "n_words", score.alias("log_score"), F.when(F.col("n_words") > 0, score / F.col("n_words")).alias("log_score_per_word"))


def stupid_backoff(docs: DataFrame, order: int = ORDER, alpha: float = ALPHA, leave_out: bool = False, buckets: int | None = None, chunks: int | None = None) -> DataFrame:
    """doc_id, n_words, log_score (natural logarithm, summed over words), log_score_per_word."""
    buckets, chunks = buckets or group_count(docs), chunks or group_count(docs, 2)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    keyed = keyed.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text", F.spark_partition_id()), F.lit(chunks)).cast("int"))
    by_chunk = keyed.groupBy("chunk")
    ask, total = _tidy(lambda t: _ask(t, order, buckets)), _tidy(_totals)
    asked = by_chunk.applyInArrow(lambda t: ask(t), _ASK)
    told = asked.groupBy("bucket").applyInArrow(lambda t: total(t), _REPLY)
    out = "doc_id long, n_words long, part double, singles long"
    empty = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("part", pa.float64()), ("singles", pa.int64())])

    score = _tidy(lambda t, r: _summed(t, r, order, buckets, alpha, leave_out).cast(empty) if len(t) else empty.empty_table())

    def last(t: pa.Table, r: pa.Table) -> pa.Table:
        return score(t, r)

    return _scored(materialise(by_chunk.cogroup(told.groupBy("chunk")).applyInArrow(last, out), "scores"), leave_out)


def ngram_counts(grams: DataFrame) -> DataFrame:
    """grams(gram, ...), a row for each occurrence -> (gram, c)."""
    return grams.groupBy("gram").agg(F.count("*").alias("c"))


def backoff_by_rows(docs: DataFrame, order: int = ORDER, alpha: float = ALPHA, leave_out: bool = False) -> DataFrame:
    """The columns of stupid_backoff by DataFrame functions: count tables joined to exploded n-grams."""
    words = F.array_remove(F.split(F.coalesce(F.col("text").cast("string"), F.lit("")), "[\\x20\\x09-\\x0D]+"), "")
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), words.alias("w"))
    rows = materialise(rows, "words")
    at = rows.filter(F.size("w") > 0).select("row", "w", F.explode(F.sequence(F.lit(1), F.size("w"))).alias("i"))
    at = at.select("row", "w", "i", F.explode(F.sequence(F.lit(1), F.least("i", F.lit(order)))).alias("n"))
    gram = F.array_join(F.slice("w", F.col("i") - F.col("n") + 1, F.col("n")), " ")
    said = at.select("row", "i", "n", gram.alias("gram"))
    counts, tables = said.join(ngram_counts(said), "gram"), ["row", "i", "n"]
    if leave_out:
        own = said.groupBy("row", "gram").agg(F.count("*").alias("own"))
        counts = counts.join(own, ["row", "gram"]).withColumn("c", F.col("c") - F.col("own"))
    counts = counts.select(*tables, "c")
    context = counts.select("row", (F.col("i") + 1).alias("i"), (F.col("n") + 1).alias("n"), F.col("c").alias("d"))
    both = counts.join(context, tables, "left").filter("c > 0 or n = 1")
    best = both.groupBy("row", "i").agg(F.max(F.struct("n", "c", "d")).alias("s")).select("row", "i", "s.n", "s.c", "s.d")
    steps = F.least("i", F.lit(order)) - F.col("n")
    value = F.when(F.col("n") > 1, F.log(F.col("c") / F.col("d"))).otherwise(F.log(F.greatest(F.col("c").cast("double"), F.lit(UNSEEN))))
    parts = best.groupBy("row").agg(F.sum(value + steps * math.log(alpha)).alias("part"), F.sum((F.col("n") == 1).cast("long")).alias("singles"))
    kept = rows.select("row", "doc_id", F.size("w").cast("long").alias("n_words")).join(parts, "row", "left")
    zero = [F.coalesce("part", F.lit(0.0)).alias("part"), F.coalesce("singles", F.lit(0).cast("long")).alias("singles")]
    return _scored(materialise(kept.select("doc_id", "n_words", *zero), "scores"), leave_out)
