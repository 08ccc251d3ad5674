"""Training-order materialisation: token sequences in a keyed pseudo-random order, as shards of fixed stride.

Texts become token ids; a task's documents, each closed by an end token, are one stream that is cut into sequences of
SEQUENCE tokens, the last one shorter. A sequence's index among all is where the written blocks have it, tasks in the
order of their numbers. A Feistel network over the least even number of bits that holds all indexes, walked until it
falls among them, makes a permutation of exactly 0..n-1 under a key. The slot so found names the shard and the record:
shard = slot // per_shard, byte = (slot % per_shard) * stride. Tasks own ranges of slots and write whole shards front to
back; a reader resumes anywhere by arithmetic. Blocks of sequences travel compressed.

A record: doc_id of the first token (int64), that token's place in its document (int32), number of tokens (int32), then
SEQUENCE uint16 ids, zero after the last. Defined results: null and token-less texts add nothing; a null doc_id is
stored as the least int64 and read back as null; repeated rows are documents each by itself; no rows, no shards. A long
text is encoded whole, in one task.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.llm.bpe import default_path, shared_table, tokenizer
from levelmine.llm.kernel import mix
from levelmine.llm.warc import _open
from levelmine.session import materialise, scratch_path, shuffle_width

SEQUENCE = 256
PER_SHARD = 16_384
BLOCK = 512
KEY = 0x5EED
#: Words kept with their ids, in each Python worker.
WORDS = 200_000
END_TOKEN = "<|endoftext|>"
_NULL_ID = -(1 << 63)
_U = np.uint64
_TWO_BYTES = [i.to_bytes(2, "little") for i in range(1 << 16)]


def record_type(sequence: int = SEQUENCE) -> np.dtype:
    return np.dtype([("doc_id", "<i8"), ("offset", "<i4"), ("n", "<i4"), ("ids", "<u2", (sequence,))])


def permuted(index: np.ndarray, n: int, key: int = KEY, rounds: int = 6) -> np.ndarray:
    """The slots of indexes below n: a bijection of 0..n-1."""
    half = max(1, (max(1, n - 1).bit_length() + 1) // 2)
    mask = _U((1 << half) - 1)
    out = index.astype(_U)
    walking = np.arange(len(out))
    while len(walking):
        x = out[walking]
        left, right = x >> _U(half), x & mask
        for r in range(rounds):
            left, right = right, left ^ (mix(right + _U((key << 8) + r), 17 + r) & mask)
        x = left << _U(half) | right
        out[walking] = x
        walking = walking[x >= n]
    return out.astype(np.int64)


class _Ids(dict):
    """word -> its token ids as uint16 bytes, by the tokenizer's own model; word splitting is the automaton's."""

    def __init__(self, path: str, table: Broadcast):
        from tokenizers import Tokenizer

        super().__init__()
        self.words, self.model = tokenizer(path, table), Tokenizer.from_file(path).model

    def __missing__(self, word: str) -> bytes:
        if len(self) >= WORDS:
            self.clear()
        whole = word
        if not (word.isascii() and word.isprintable()):
            whole = word.encode("utf-8", "replace").decode("latin-1").translate(self.words.symbols)
        out = self[word] = b"".join([_TWO_BYTES[t.id] for t in self.model.tokenize(whole)])
        return out

    def of(self, text: str | None) -> bytes:
        if not text:
            return b""
        if "<|" in text:
            return np.array(self.words.encode(text).split(), "<u2").tobytes()
        return b"".join(map(self.__getitem__, self.words.split(text)))


_BLOCK_DDL = "pid int, i long, count int, docs binary, offsets binary, body binary"
_BLOCK_NAMES = ["pid", "i", "count", "docs", "offsets", "body"]


def _blocks(path: str, table: Broadcast, sequence: int):
    """A task's stream as blocks of sequences; i is the index in the task of a block's first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        pid, made = TaskContext.get().partitionId(), 0
        pack, ids = zstandard.ZstdCompressor(level=3), _Ids(path, table)
        end = np.array([ids.words.special[END_TOKEN]], "<u2").tobytes()
        held, docs, starts, size = [], [], [], 0  # the stream's bytes, its documents, where they start in it (in tokens)

        def cut(last: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held, docs, starts, size, made
            stream = np.frombuffer(b"".join(held), "<u2")
            n = len(stream) // sequence if not last else -(-len(stream) // sequence)
            at, of = np.arange(n) * sequence, np.array(starts, np.int64)
            doc = np.searchsorted(of, at, "right") - 1
            ids_, offset = np.array(docs, np.int64)[doc], (at - of[doc]).astype("<i4")
            for lo in range(0, n, BLOCK):
                hi = min(n, lo + BLOCK)
                body = pack.compress(stream[lo * sequence : hi * sequence].tobytes())
                yield pa.RecordBatch.from_arrays([pa.array([pid], pa.int32()), pa.array([made + lo]), pa.array([hi - lo], pa.int32()), pa.array([ids_[lo:hi].tobytes()]), pa.array([offset[lo:hi].tobytes()]), pa.array([body], pa.binary())], _BLOCK_NAMES)
            made += n
            rest = stream[n * sequence :]
            if len(rest):
                doc = int(np.searchsorted(of, n * sequence, "right")) - 1
                docs, starts = docs[doc:], [s - n * sequence for s in starts[doc:]]
            else:
                docs, starts = [], []
            held, size = [rest.tobytes()], len(rest)

        for batch in batches:
            for doc_id, cell in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                got = ids.of(cell.as_py())
                if not got:
                    continue
                docs.append(_NULL_ID if doc_id is None else doc_id)
                starts.append(size)
                held += [got, end]
                size += len(got) // 2 + 1
                if size >= BLOCK * sequence:
                    yield from cut(False)
        if size:
            yield from cut(True)

    return run


def sequences(docs: DataFrame, path: str | None = None, sequence: int = SEQUENCE, streams: int | None = None) -> DataFrame:
    """The sequences of all documents in blocks, written once; (pid, i) orders them from then on.

    streams: documents are dealt by key to so many streams, each in the order of (doc_id, hash of the text), so that the
    order of all sequences depends on the documents, the key and this number alone; it costs one exchange of the texts.
    Without it a stream is a task's share of the table as it is stored: another split of the files gives another order.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    if streams is not None:
        text_hash = F.xxhash64(F.coalesce("text", F.lit("")))
        dealt = rows.repartitionById(streams, F.pmod(F.xxhash64("doc_id", text_hash), F.lit(streams)).cast("int"))
        rows = dealt.withColumn("h", text_hash).sortWithinPartitions("doc_id", "h").drop("h")
    path = path or default_path()
    return materialise(rows.mapInArrow(_blocks(path, shared_table(docs.sparkSession, path), sequence), _BLOCK_DDL), "sequences")


def _dealt(base: np.ndarray, pids: np.ndarray, total: int, key: int, sequence: int, per_shard: int):
    """Blocks -> for each shard one row of a task's records in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        pack, unpack = zstandard.ZstdCompressor(level=2), zstandard.ZstdDecompressor()
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def dealt() -> Iterator[pa.RecordBatch]:
            slot, records = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])
            order = np.argsort(slot)
            slot, records = slot[order], records[order]
            shard = slot // per_shard
            edge = np.concatenate([[0], np.flatnonzero(shard[1:] != shard[:-1]) + 1, [len(shard)]])
            for lo, hi in zip(edge[:-1], edge[1:], strict=True):
                head = np.concatenate([slot[lo:hi].view(np.uint8), records["doc_id"][lo:hi].copy().view(np.uint8), records["offset"][lo:hi].copy().view(np.uint8), records["n"][lo:hi].copy().view(np.uint8)])
                yield pa.RecordBatch.from_arrays([pa.array([int(shard[lo])]), pa.array([hi - lo], pa.int32()), pa.array([head.tobytes()]), pa.array([pack.compress(records["ids"][lo:hi].tobytes())], pa.binary())], ["shard", "count", "head", "body"])

        for b in batches:
            for pid, i, count, docs, offsets, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                stream = np.frombuffer(unpack.decompress(body), "<u2")
                records = np.zeros(count, record_type(sequence))
                records["doc_id"], records["offset"] = np.frombuffer(docs, "<i8"), np.frombuffer(offsets, "<i4")
                records["n"] = np.minimum(sequence, len(stream) - np.arange(count) * sequence)
                full = np.zeros(count * sequence, "<u2")
                full[: len(stream)] = stream
                records["ids"] = full.reshape(count, sequence)
                at = base[np.searchsorted(pids, pid)] + i + np.arange(count)
                held.append((permuted(at, total, key), records))
                if len(held) * BLOCK * sequence > 32 << 20:
                    yield from dealt()
                    held.clear()
        if held:
            yield from dealt()

    return run


def _written(path: str, sequence: int, per_shard: int):
    """Writes the shards of a task's range; a shard is visible under its name only when it is whole."""
    kind = record_type(sequence)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        system, base = _open(path)
        attempt, unpack, done = TaskContext.get().taskAttemptId(), zstandard.ZstdDecompressor(), []
        system.create_dir(base, recursive=True)
        shard, records, filled = None, None, 0

        def close():
            name = f"{base}/.{shard:08d}.{attempt}"
            with system.open_output_stream(name, compression=None) as out:
                out.write(records[:filled].tobytes())
            system.move(name, f"{base}/{shard:08d}.bin")
            done.append((shard, filled))

        for b in batches:
            for of, count, head, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if of != shard:
                    if shard is not None:
                        close()
                    shard, records, filled = of, np.zeros(per_shard, kind), 0
                at = np.frombuffer(head, "<i8", count) % per_shard
                records["doc_id"][at] = np.frombuffer(head, "<i8", count, 8 * count)
                records["offset"][at] = np.frombuffer(head, "<i4", count, 16 * count)
                records["n"][at] = np.frombuffer(head, "<i4", count, 20 * count)
                records["ids"][at] = np.frombuffer(unpack.decompress(body), "<u2").reshape(count, sequence)
                filled += count
        if shard is not None:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.int64()), pa.array([d[1] for d in done], pa.int64())], ["shard", "n_records"])

    return run


def write_shards(seqs: DataFrame, path: str, key: int = KEY, sequence: int = SEQUENCE, per_shard: int = PER_SHARD) -> DataFrame:
    """Writes all shards to path; (shard, n_records) of each. One number a task that wrote goes through the driver."""
    sizes = {r["pid"]: r["n"] for r in seqs.groupBy("pid").agg(F.sum("count").alias("n")).collect()}
    pids = np.array(sorted(sizes), np.int64)
    base = np.concatenate([[0], np.cumsum([sizes[p] for p in pids.tolist()])]).astype(np.int64)
    total = int(base[-1])
    shards = max(1, -(-total // per_shard))
    tasks = max(1, min(shards, shuffle_width(seqs.sparkSession)))
    dealt = seqs.mapInArrow(_dealt(base, pids, total, key, sequence, per_shard), "shard long, count int, head binary, body binary")
    ranged = dealt.repartitionById(tasks, F.floor(F.col("shard") * tasks / shards).cast("int")).sortWithinPartitions("shard")
    return materialise(ranged.mapInArrow(_written(path, sequence, per_shard), "shard long, n_records long"), "shards")


def read_shards(spark: SparkSession, path: str, manifest: DataFrame, sequence: int = SEQUENCE, per_shard: int = PER_SHARD, start: int = 0) -> DataFrame:
    """slot, doc_id, offset, n_tokens, ids of the records from slot `start` on, each shard read front to back."""
    kind = record_type(sequence)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, base = _open(path)
        for b in batches:
            for shard in b.column(0).to_pylist():
                first = max(0, start - shard * per_shard)
                with system.open_input_file(f"{base}/{shard:08d}.bin") as f:
                    f.seek(first * kind.itemsize)
                    at = shard * per_shard + first
                    while raw := f.read(1024 * kind.itemsize):
                        r = np.frombuffer(raw, kind)
                        doc = pa.array(r["doc_id"], mask=r["doc_id"] == _NULL_ID)
                        width = r["n"].astype(np.int64)
                        flat = r["ids"][np.arange(sequence) < width[:, None]]
                        ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(width)]), pa.int32()), pa.array(flat.astype(np.int32)))
                        yield pa.RecordBatch.from_arrays([pa.array(np.arange(at, at + len(r))), doc, pa.array(r["offset"].astype(np.int32)), pa.array(r["n"].astype(np.int32)), ids], ["slot", "doc_id", "offset", "n_tokens", "ids"])
                        at += len(r)

    live = manifest.filter((F.col("shard") + 1) * per_shard > start).select("shard")
    return live.repartition(shuffle_width(spark), "shard").mapInArrow(run, "slot long, doc_id long, offset int, n_tokens int, ids array<int>")


def training_order(docs: DataFrame, path: str | None = None, key: int = KEY) -> DataFrame:
    """Writes the shards, reads them back: slot, shard, record, doc_id and offset of the first token, n_tokens,
    ids_sha256 (of the uint16 ids) of every sequence."""
    spark = docs.sparkSession
    out = scratch_path(spark, "order")
    manifest = write_shards(sequences(docs, path), out, key)

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(4)
            flat, at = ids.flatten().to_numpy().astype("<u2"), ids.offsets.to_numpy()
            at = at - at[0]
            sha = [hashlib.sha256(flat[a:z].tobytes()).hexdigest() for a, z in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(sha, pa.string())], ["slot", "doc_id", "offset", "n_tokens", "ids_sha256"])

    back = read_shards(spark, out, manifest).mapInArrow(digest, "slot long, doc_id long, offset int, n_tokens int, ids_sha256 string")
    return back.select("slot", F.floor(F.col("slot") / PER_SHARD).alias("shard"), (F.col("slot") % PER_SHARD).alias("record"), "doc_id", "offset", "n_tokens", "ids_sha256")
