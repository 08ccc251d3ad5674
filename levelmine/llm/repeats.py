"""Exact removal of repeated passages: words covered by a window of `length` words that also starts earlier.

Two ways to find the places worth comparing share the rest of the work:

* `difference_cover(20)`: anchors are hashed only where the word's position modulo a period lies in a difference
  cover; two equal passages always share an aligned anchor. An anchor's key is the hash of its words.
* `sparse_suffixes(50)`: suffixes are retained only at minimiser positions, chosen by content; equal passages retain
  the same suffixes. A suffix's key is its first words in order, a few bits of each, so that keys sort as suffixes do
  and neighbours that agree in all these words are a match.

A match is extended to the left and right by windows: all windows that hold its place are compared by their contents,
which finds every extent of `length` words exactly, however many others share the place. Where windows overlap, their
words are one passage. (Sorting whole suffixes by place would gather all copies of a frequent passage in one task, with
as many contexts; windows of equal content are one entry a chunk.)

Plan. Documents are dealt to chunks by key; one exchange of the texts serves three passes (Spark reuses it).
  1. chunk -> anchors, one of each per chunk -> buckets by hash; a bucket sorts them, compares neighbours and answers
     with a bit for each anchor that some other chunk has too.
  2. chunk + bits -> windows around repeated anchors, the earliest of each per chunk -> buckets by hash; a bucket sorts
     and answers with two bits: it starts in an earlier document; it is in another document.
  3. chunk + bits -> covered words -> result.
A message is a chunk's entries for one bucket, packed; tasks read and write all messages of a group as flat arrays. The
numbers of chunks and buckets follow the input's bytes, so that each group is of bounded size at any shuffle width.
A passage that a third of all documents share is one entry per chunk, so no bucket holds a row per occurrence. Rows that
repeat doc_id and text are dealt to chunks by their partition too, so many of them do not meet in one.

Defined results. A null text has no words. A null doc_id counts as smaller than all others. Rows that repeat both
doc_id and text are judged once and returned as often as given; rows that repeat a doc_id with other texts are ordered
by a hash of the text. An empty table gives an empty result. Columns of any name pass through. A long text is cut into
words whole; a task's memory is a small multiple of its chunk or of the longest text. Windows count as equal if 96 bits
of hash are equal.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from levelmine.llm.kernel import cell_bytes, cells, give_back, gram_hashes, mix, run_edges, within_rows, word_blocks
from levelmine.llm.sizes import group_count

_U = np.uint64
_NULL_ID = -(1 << 63)


@dataclass(frozen=True)
class Anchors:
    """Where a window of `length` words is looked at: `width` words from each chosen position on."""

    length: int
    width: int
    pick: Callable[[np.ndarray, np.ndarray], np.ndarray]  # (hashes of width words, row ranges) -> mask
    ordered: bool = False  # keys are the words in order, else one hash of them

    @property
    def key_bytes(self) -> int:
        return 8 if self.ordered else 5

    def keys(self, words: np.ndarray, at: np.ndarray, grams: np.ndarray) -> np.ndarray:
        """The sort keys of the anchors at these positions, in the low 8 * key_bytes bits."""
        if not self.ordered:
            return grams >> _U(24)
        said, bits = min(self.width, 20), 60 // min(self.width, 20)
        out = np.zeros(len(at), _U)
        for j in range(said):
            out = out << _U(bits) | words[at + j] >> _U(64 - bits)
        return out


#: Perfect difference covers (period: positions); fixed values.
COVERS = {7: (1, 2, 4), 13: (0, 1, 3, 9), 21: (3, 6, 7, 12, 14), 31: (1, 5, 11, 24, 25, 27)}


def difference_cover(length: int) -> Anchors:
    """The widest period that leaves an anchor of 8 words or more, or else the narrowest."""
    period = max((p for p in COVERS if length - p + 1 >= 8), default=min(COVERS))
    width = length - period + 1
    if width < 1:
        raise ValueError(f"a window needs {min(COVERS)} words at least")
    cover = np.zeros(period, np.bool_)
    cover[list(COVERS[period])] = True

    def pick(grams: np.ndarray, ptr: np.ndarray) -> np.ndarray:
        at = np.arange(len(grams)) - np.repeat(ptr[:-1], np.diff(ptr))[: len(grams)]
        return cover[at % period]

    return Anchors(length, width, pick)


def _slide(x: np.ndarray, n: int, best: np.ufunc) -> np.ndarray:
    """best over n entries from each position on, in log2(n) steps."""
    have, out = 1, x
    while have < n:
        step = min(have, n - have)
        out = best(out[:-step], out[step:])
        have += step
    return out


def sparse_suffixes(length: int, width: int = 20) -> Anchors:
    """Minimisers: of the suffixes that start in a window, those with the least hash of their first `width` words."""
    width = min(width, length)
    span = length - width + 1

    def pick(grams: np.ndarray, ptr: np.ndarray) -> np.ndarray:
        value = mix(grams, 3)
        chosen = np.zeros(len(grams), np.bool_)
        if len(grams) < span:
            return chosen
        least = _slide(value, span, np.minimum)
        least[~within_rows(ptr, length)] = 0
        edge = np.zeros(span - 1, _U)
        return _slide(np.concatenate([edge, least, edge]), span, np.maximum) == value

    return Anchors(length, width, pick, ordered=True)


class _Chunk:
    """The distinct documents of one chunk in the order of their keys, and the hashes of their words."""

    def __init__(self, table: pa.Table, how: Anchors | None, with_words: bool = False):
        self.how = how
        keys = [table[c].to_numpy() for c in ("kd", "kh")]
        order = np.lexsort((keys[1], keys[0]))
        kd, kh = keys[0][order], keys[1][order]
        fresh = np.ones(len(order), np.bool_)
        fresh[1:] = (kd[1:] != kd[:-1]) | (kh[1:] != kh[:-1])
        self.order, self.doc_of_row = order, np.cumsum(fresh) - 1
        self.kd, self.kh = kd[fresh], kh[fresh]
        text = table["text"].cast(pa.large_string()).take(pa.array(order[fresh]))
        hashes, sizes, self.parts = [np.zeros(0, _U)], [np.zeros(0, np.int64)], []
        for block in word_blocks(text):
            hashes.append(block[2].hashes())
            sizes.append(block[2].counts())
            if with_words:
                self.parts.append(block[2])
        self.hashes = np.concatenate(hashes)
        self.ptr = np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype(np.int64)

    def anchor_keys(self, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Positions; bucket and key of each distinct anchor, sorted; each position's anchor; each anchor's number."""
        grams = gram_hashes(self.hashes, self.how.width)
        at = np.flatnonzero(within_rows(self.ptr, self.how.width) & self.how.pick(grams, self.ptr)) if len(grams) else np.zeros(0, np.int64)
        grams = grams[at]
        bucket, key = grams % _U(buckets), self.how.keys(self.hashes, at, grams)
        order = np.argsort(bucket << _U(40) | key) if not self.how.ordered and buckets < 1 << 24 else np.lexsort((key, bucket))
        bucket, key = bucket[order], key[order]
        fresh = np.ones(len(order), np.bool_)
        fresh[1:] = (bucket[1:] != bucket[:-1]) | (key[1:] != key[:-1])
        group = np.cumsum(fresh) - 1
        which = np.empty(len(order), np.int64)
        which[order] = group
        return at, bucket[fresh].astype(np.int64), key[fresh], which, np.bincount(group) if len(group) else np.zeros(0, np.int64)

    def windows(self, repeated: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts of the windows that hold one of the given anchors, and 64 and 32 bits of hash of each."""
        n, how = len(self.hashes), self.how
        ok = within_rows(self.ptr, how.length)
        seen = np.zeros(n + 1, np.int64)
        seen[repeated + 1] = 1
        np.cumsum(seen, out=seen)
        first = np.arange(len(ok))
        start = first[ok & (seen[first + how.length - how.width + 1] > seen[first])]
        grams = gram_hashes(self.hashes, how.length)[start] if len(start) else np.zeros(0, _U)
        other = gram_hashes(mix(self.hashes, 5), how.length)[start] if len(start) else np.zeros(0, _U)
        return start, grams, (other >> _U(32)).astype(np.uint32)


def _low_bytes(keys: np.ndarray, n: int) -> np.ndarray:
    return np.ascontiguousarray(keys.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :n])


def _from_bytes(data: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((len(data) // n, 8), np.uint8)
    out[:, :n] = data[: len(out) * n].reshape(-1, n)
    return out.reshape(-1).view("<u8")


def _cuts(bucket: np.ndarray) -> list[tuple[int, int, int]]:
    """(bucket, from, to) of each run of a sorted array."""
    edge = run_edges(bucket)
    return [(int(bucket[a]), int(a), int(b)) for a, b in zip(edge[:-1], edge[1:], strict=True)]


_ASK_ARROW = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("body", pa.binary()), ("docs", pa.binary())])
_REPLY_ARROW = pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("bits", pa.binary())])
_ASK, _REPLY = "bucket int, chunk int, body binary, docs binary", "chunk int, bucket int, bits binary"
_WINDOW = np.dtype([("high", "<u8"), ("low", "<u4")])
_DOC = np.dtype([("kd", "<i8"), ("kh", "<i8"), ("n", "<u4")])


def _places(edge: np.ndarray, start: np.ndarray, per: int) -> np.ndarray:
    """Where the bits of all entries are, if those of message i (entries edge[i]..edge[i + 1]) begin at bit start[i]."""
    return np.repeat(start - edge[:-1] * per, np.diff(edge) * per) + np.arange(int(edge[-1]) * per)


def _reply(table: pa.Table, size: np.ndarray, bits: np.ndarray, per: int) -> pa.Table:
    """One message back for each message of the bucket: its entries' bits in its own order."""
    edge = np.concatenate([[0], np.cumsum(size)])
    at = np.concatenate([[0], np.cumsum((size * per + 7) // 8)])
    full = np.zeros(int(at[-1]) * 8, np.bool_)
    full[_places(edge, at[:-1] * 8, per)] = bits.reshape(-1)
    return pa.table([table["chunk"].combine_chunks(), table["bucket"].combine_chunks(), cells(np.packbits(full), at)], schema=_REPLY_ARROW)


def _shared_anchors(table: pa.Table, key_bytes: int) -> pa.Table:
    """A bucket's anchors sorted; a bit for each whose neighbour, from another chunk, is equal."""
    data, at = cell_bytes(table["body"])
    keys = _from_bytes(data, key_bytes)
    order = np.argsort(keys)
    same = np.flatnonzero(keys[order[1:]] == keys[order[:-1]])
    bits = np.zeros(len(keys), np.bool_)
    bits[order[same]] = True
    bits[order[same + 1]] = True
    return _reply(table, np.diff(at) // key_bytes, bits, 1)


def _first_windows(table: pa.Table) -> pa.Table:
    """A bucket's windows sorted by hash, then document; two bits for each: an earlier document has it; another one has it."""
    data, at = cell_bytes(table["body"])
    said, docs = data.view(_WINDOW), cell_bytes(table["docs"])[0].view(_DOC)
    kd, kh = (np.repeat(docs[c], docs["n"]) for c in ("kd", "kh"))
    order = np.lexsort((kh, kd, said["low"], said["high"]))
    high, low, kd, kh = said["high"][order], said["low"][order], kd[order], kh[order]
    fresh = np.ones(len(order), np.bool_)
    fresh[1:] = (high[1:] != high[:-1]) | (low[1:] != low[:-1])
    first = np.flatnonzero(fresh)
    last, group = np.concatenate([first[1:], [len(order)]]) - 1, np.cumsum(fresh) - 1
    bits = np.zeros((len(order), 2), np.bool_)
    if len(order):
        bits[order, 0] = (kd != kd[first][group]) | (kh != kh[first][group])
        bits[order, 1] = ((kd[first] != kd[last]) | (kh[first] != kh[last]))[group]
    return _reply(table, np.diff(at) // _WINDOW.itemsize, bits, 2)


def _asks(chunk: int, bucket: np.ndarray, body: pa.Array, docs: pa.Array | None) -> pa.Table:
    n = len(bucket)
    none = cells(np.zeros(0, np.uint8), np.zeros(n + 1, np.int64))
    return pa.table([pa.array(bucket, pa.int32()), pa.array(np.full(n, chunk), pa.int32()), body, none if docs is None else docs], schema=_ASK_ARROW)


def _number(table: pa.Table) -> int:
    return table["chunk"][0].as_py()


def _ask_anchors(table: pa.Table, how: Anchors, buckets: int) -> pa.Table:
    _, bucket, keys, _, _ = _Chunk(table, how).anchor_keys(buckets)
    edge = run_edges(bucket)
    return _asks(_number(table), bucket[edge[:-1]], cells(_low_bytes(keys, how.key_bytes), edge * how.key_bytes), None)


def _bits(replies: pa.Table, edge: np.ndarray, per: int) -> np.ndarray:
    """The buckets' bits in the order in which this chunk asked: by bucket, as its runs of entries have it."""
    if not len(replies):
        return np.zeros((0, per), np.bool_)
    order = np.argsort(replies["bucket"].to_numpy())
    data, at = cell_bytes(replies["bits"])
    return np.unpackbits(data)[_places(edge, at[:-1][order] * 8, per)].reshape(-1, per).astype(np.bool_)


def _repeated(chunk: _Chunk, replies: pa.Table, buckets: int) -> np.ndarray:
    at, bucket, _, which, count = chunk.anchor_keys(buckets)
    shared = _bits(replies, run_edges(bucket), 1)[:, 0]
    return at[((count > 1) | shared)[which]]


class _Windows:
    """The candidate windows of a chunk; `first` are the earliest of each content, ordered by bucket, then position."""

    def __init__(self, chunk: _Chunk, repeated: np.ndarray, buckets: int):
        self.start, self.high, self.low = chunk.windows(repeated)
        order = np.lexsort((self.low, self.high))  # stable: earlier windows come first
        high, low = self.high[order], self.low[order]
        fresh = np.ones(len(order), np.bool_)
        fresh[1:] = (high[1:] != high[:-1]) | (low[1:] != low[:-1])
        group = np.cumsum(fresh) - 1
        self.group = np.empty(len(order), np.int64)
        self.group[order] = group
        self.is_first = np.zeros(len(order), np.bool_)
        self.is_first[order[fresh]] = True
        self.size = np.bincount(group) if len(group) else np.zeros(0, np.int64)
        first = np.flatnonzero(self.is_first)
        bucket = (self.high[first] % _U(buckets)).astype(np.int64)
        by = np.argsort(bucket, kind="stable")
        self.first, self.bucket = first[by], bucket[by]
        self.edge = run_edges(self.bucket)


def _ask_windows(table: pa.Table, replies: pa.Table, how: Anchors, buckets: int) -> pa.Table:
    if not len(table):
        return _ASK_ARROW.empty_table()
    chunk = _Chunk(table, how)
    win = _Windows(chunk, _repeated(chunk, replies, buckets), buckets)
    said = np.empty(len(win.first), _WINDOW)
    said["high"], said["low"] = win.high[win.first], win.low[win.first]
    doc = np.searchsorted(chunk.ptr, win.start[win.first], "right") - 1
    runs = run_edges(win.bucket * (len(chunk.kd) + 1) + doc)
    docs = np.empty(len(runs) - 1, _DOC)
    docs["kd"], docs["kh"], docs["n"] = chunk.kd[doc[runs[:-1]]], chunk.kh[doc[runs[:-1]]], np.diff(runs)
    ends = np.searchsorted(runs, win.edge)
    return _asks(_number(table), win.bucket[win.edge[:-1]], cells(said, win.edge * _WINDOW.itemsize), cells(docs, ends * _DOC.itemsize))


def _cover(n: int, start: np.ndarray, length: int) -> np.ndarray:
    step = np.zeros(n + 1, np.int64)
    step[start] += 1  # starts are distinct
    step[start + length] -= 1
    return np.cumsum(step[:n]) > 0


def _result(table: pa.Table, anchor_bits: pa.Table, window_bits: pa.Table, how: Anchors, buckets: int, with_text: bool, schema: pa.Schema) -> pa.Table:
    if not len(table):
        return schema.empty_table()
    chunk = _Chunk(table, how, with_words=True)
    win = _Windows(chunk, _repeated(chunk, anchor_bits, buckets), buckets)
    bits = np.zeros((len(win.start), 2), np.bool_)
    bits[win.first] = _bits(window_bits, win.edge, 2)
    elsewhere = np.zeros(len(win.size), np.bool_)
    elsewhere[win.group[win.first]] = bits[win.first, 1]
    later = ~win.is_first | bits[:, 0]
    again = (win.size > 1)[win.group] | elsewhere[win.group]
    n = len(chunk.hashes)
    gone, repeated = _cover(n, win.start[later], how.length), _cover(n, win.start[again], how.length)
    counted = [np.diff(np.concatenate([[0], np.cumsum(x)])[chunk.ptr]) for x in (gone, repeated)]
    texts, digests, lo, row = [], [], 0, 0
    for w in chunk.parts:
        m = int(w.ptr[-1])
        body, at = w.joined(~gone[lo : lo + m])
        body, lo = body.tobytes(), lo + m
        first = row
        given, of = w.buf.tobytes() if with_text else b"", w.row_bytes.tolist()
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            piece = body[a:b]
            digests.append(hashlib.sha256(piece).hexdigest())
            if with_text:  # a text that loses nothing stays as it is
                texts.append(piece if counted[0][row] else given[of[row - first] : of[row - first + 1]])
            row += 1
    doc = pa.array(chunk.doc_of_row)
    out = {"r_words": pa.array(np.diff(chunk.ptr)), "r_removed": pa.array(counted[0]), "r_repeated": pa.array(counted[1]), "r_sha": pa.array(digests, pa.string())}
    if with_text:
        out["r_text"] = pa.array(texts, pa.binary()).cast(pa.string())
    rows = table.take(pa.array(chunk.order))
    return pa.table([rows[f.name].cast(f.type) if f.name[0] == "c" else out[f.name].take(doc).cast(f.type) for f in schema], schema=schema)


def _tidy(fn: Callable[..., pa.Table]) -> Callable[..., pa.Table]:
    """fn, and what it has freed goes back to the system: the next groups may be other operators'."""

    def run(*tables: pa.Table) -> pa.Table:
        out = fn(*tables)
        give_back()
        return out

    return run


def remove_repeats(docs: DataFrame, how: Anchors, with_text: bool = False, buckets: int | None = None, chunks: int | None = None) -> DataFrame:
    """The columns of docs, then r_words, r_removed, r_repeated (words of windows that occur more than once, the first
    occurrence included), r_sha (SHA-256 of the kept words joined by a space) and, if asked for, r_text (those words; the text itself where none
    is removed).

    buckets, chunks: groups that the two hash exchanges and the documents are cut into; by the input's bytes and the
    session's shuffle width unless given.
    """
    buckets, chunks = buckets or group_count(docs), chunks or group_count(docs, 4)
    names = [f"c{i}" for i in range(len(docs.columns))]
    doc_id, text = docs.columns.index("doc_id"), docs.columns.index("text")
    kinds = [f.dataType for f in docs.schema.fields]
    plain = docs.toDF(*names)
    keyed = plain.select(
        *names,
        F.coalesce(F.col(f"c{doc_id}").cast("long"), F.lit(_NULL_ID)).alias("kd"),
        F.xxhash64(F.coalesce(F.col(f"c{text}").cast("string"), F.lit(""))).alias("kh"),
    )
    keyed = keyed.withColumn("chunk", F.pmod(F.xxhash64("kd", "kh", F.spark_partition_id()), F.lit(chunks)).cast("int"))
    text_name = f"c{text}"

    def renamed(t: pa.Table) -> pa.Table:
        return t.append_column("text", t[text_name].cast(pa.large_string()))

    by_chunk = keyed.groupBy("chunk")
    one, two = (lambda f: lambda t: f(t)), (lambda f: lambda t, r: f(t, r))  # Spark asks how many arguments there are
    asked = by_chunk.applyInArrow(one(_tidy(lambda t: _ask_anchors(renamed(t), how, buckets))), _ASK)
    anchor_bits = asked.groupBy("bucket").applyInArrow(one(_tidy(lambda t: _shared_anchors(t, how.key_bytes))), _REPLY)
    asked = by_chunk.cogroup(anchor_bits.groupBy("chunk")).applyInArrow(two(_tidy(lambda t, r: _ask_windows(renamed(t), r, how, buckets))), _ASK)
    window_bits = asked.groupBy("bucket").applyInArrow(one(_tidy(_first_windows)), _REPLY)
    tagged = anchor_bits.withColumn("kind", F.lit(0)).unionByName(window_bits.withColumn("kind", F.lit(1)))
    kept = [i for i in range(len(names)) if with_text or i != text]
    fields = [T.StructField(names[i], kinds[i]) for i in kept]
    fields += [T.StructField(c, T.LongType()) for c in ("r_words", "r_removed", "r_repeated")] + [T.StructField("r_sha", T.StringType())]
    fields += [T.StructField("r_text", T.StringType())] * with_text
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(T.StructType(fields))

    def last(t: pa.Table, r: pa.Table) -> pa.Table:
        kind = r["kind"]
        anchors, windows = (r.filter(pa.compute.equal(kind, k)) for k in (0, 1))
        return _result(renamed(t), anchors, windows, how, buckets, with_text, schema)

    out = by_chunk.cogroup(tagged.groupBy("chunk")).applyInArrow(two(_tidy(last)), T.StructType(fields))
    return out.toDF(*[docs.columns[i] for i in kept], *[f.name for f in fields[len(kept) :]])
