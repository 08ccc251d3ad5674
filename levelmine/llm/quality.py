"""Quality classifier: hashed word and character n-gram vectors, averaged per document, under a softmax. Words that
return at once or after a few words add a token for that, as a vector of each repeated word alone would not generalise.

Training runs in numpy on the driver on a sample of labelled documents whose size is bounded by SAMPLE_ROWS and
SAMPLE_BYTES; the sample's features lie in a temporary file of the driver. Everything else reads all rows. As the layers
are linear, a trained model folds into one number per hash bucket, so scoring looks up and averages numbers; that table of
fixed size goes to the tasks.

Defined results. Null text scores as empty: the bias alone. Without any labels every score is 0.5.
Rows that repeat are scored each by itself. An empty table has no scores. A long text's features are made whole, in one
task, whose memory is a small multiple of the text.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.llm.kernel import NON_SPACE, give_back, word_blocks
from levelmine.session import materialise

#: Documents of the training sample at most, and bytes of their texts; the sample is those with the least hash of their id.
SAMPLE_ROWS, SAMPLE_BYTES = 4000, 64 << 20
BITS, DIM, RATE, SEED = 18, 8, 8.0, 11
#: Steps of training in all; the number of epochs follows from it.
STEPS = 24_000
#: Texts of the sample whose features are made at once.
_TEXTS_AT_ONCE = 32
GRAMS = (3, 5)
#: Words that return within so many words have a token of their own.
RETURN_MOST = 4
_TABLE = (len(GRAMS) + 1 << BITS) + RETURN_MOST + 1
HELD_OUT_FOLDS = 5
THRESHOLD = 0.3
_U = np.uint64


def held_out(doc_id="doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % HELD_OUT_FOLDS == 0, F.lit(False))


def _returns(hashes: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """A token for each word: how many words ago it was said before, up to RETURN_MOST; none."""
    place = np.arange(len(hashes)) - np.repeat(ptr[:-1], np.diff(ptr))
    ago = np.zeros(len(hashes), np.int64)
    for d in range(RETURN_MOST, 0, -1):
        same = np.flatnonzero((hashes[d:] == hashes[:-d]) & (place[d:] >= d)) + d
        ago[same] = d
    return ago + (len(GRAMS) + 1 << BITS)


def features(column: pa.Array) -> Iterator[tuple[int, int, list[tuple[np.ndarray, np.ndarray]]]]:
    """For each block of rows: from, to, and (buckets, row offsets) of words, of their returns and of each n-gram length."""
    for lo, hi, words in word_blocks(column, NON_SPACE):
        hashes = words.hashes()
        out = [((hashes >> _U(64 - BITS)).astype(np.int64), words.ptr), (_returns(hashes, words.ptr), words.ptr)]
        n = len(words.buf)
        pad = np.concatenate([words.buf, np.zeros(8, np.uint8)])
        wide = np.ndarray(n, "<u8", pad, strides=(1,)) if n else np.zeros(0, _U)
        for i, size in enumerate(GRAMS, 1):
            value = wide & _U((1 << 8 * size) - 1)
            bucket = ((value * _U(0x9E3779B97F4A7C15) + _U(size)) * _U(0xD1342543DE82EF95) >> _U(64 - BITS)).astype(np.int64) + (i << BITS)
            sizes = np.maximum(np.diff(words.row_bytes) - size + 1, 0)
            inside = np.ones(n, np.bool_)
            for back in range(1, size):
                at = words.row_bytes[1:] - back
                inside[at[at >= 0]] = False
            short = np.flatnonzero((sizes == 0) & (np.diff(words.row_bytes) > 0))
            for r in short.tolist():
                inside[words.row_bytes[r] : words.row_bytes[r + 1]] = False
            out.append((bucket[inside], np.concatenate([[0], np.cumsum(np.bincount(np.repeat(np.arange(hi - lo), np.diff(words.row_bytes))[inside], minlength=hi - lo))])))
        yield lo, hi, out


class Model:
    """weight: a bucket's share of the logit; bias."""

    def __init__(self, weight: np.ndarray, bias: float):
        self.weight, self.bias = weight, bias

    def scores(self, column: pa.Array) -> np.ndarray:
        out = np.zeros(len(column))
        for lo, hi, kinds in features(column):
            total, count = np.zeros(hi - lo), np.zeros(hi - lo)
            for bucket, ptr in kinds:
                if not len(bucket):
                    continue
                full = np.flatnonzero(np.diff(ptr))
                total[full] += np.add.reduceat(self.weight[bucket], ptr[:-1][full])
                count += np.diff(ptr)
            out[lo:hi] = total / np.maximum(count, 1)
        return 1 / (1 + np.exp(-(out + self.bias)))


class _Texts(Sequence):
    """A column's texts, made as they are asked for."""

    def __init__(self, column: pa.ChunkedArray):
        self.column = column

    def __len__(self) -> int:
        return len(self.column)

    def __getitem__(self, at):
        got = self.column[at]
        return got.to_pylist() if isinstance(at, slice) else got.as_py()


class _SampleFeatures:
    """Distinct buckets of each text and their shares, in a file of the driver that has no name: training asks for one
    text's at a time, so that the driver's memory does not grow with the sample."""

    def __init__(self, texts: Sequence[str | None]):
        self.file, self.edge = tempfile.TemporaryFile(buffering=0), [0]
        with open(self.file.fileno(), "wb", closefd=False) as out:
            for lo in range(0, len(texts), _TEXTS_AT_ONCE):
                for _, _, kinds in features(pa.array(texts[lo : lo + _TEXTS_AT_ONCE], pa.large_string())):
                    for r in range(len(kinds[0][1]) - 1):
                        bucket, count = np.unique(np.concatenate([b[p[r] : p[r + 1]] for b, p in kinds]), return_counts=True)
                        out.write(bucket.astype(np.int32).tobytes())
                        out.write((count / max(1, count.sum())).astype(np.float32).tobytes())
                        self.edge.append(self.edge[-1] + len(bucket))

    def __len__(self) -> int:
        return len(self.edge) - 1

    def __getitem__(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        n = self.edge[k + 1] - self.edge[k]
        self.file.seek(8 * self.edge[k])
        both = np.empty(2 * n, np.int32)
        room = both.view(np.uint8)
        while len(room):
            if not (got := self.file.readinto(room)):
                raise EOFError("the sample's features end too early")
            room = room[got:]
        return both[:n], both[n:].view(np.float32)

    def close(self) -> None:
        self.file.close()


def train(texts: Sequence[str | None], label: np.ndarray, steps: int = STEPS, seed: int = SEED) -> Model:
    """Per-document steps over shuffled epochs; bucket vectors step by their own gathered gradients."""
    size = _TABLE
    if not len(texts):
        return Model(np.zeros(size), 0.0)
    rng = np.random.default_rng(seed)
    sample = _SampleFeatures(texts)
    vectors = np.empty((size, DIM), np.float32)
    for lo in range(0, size, 1 << 16):  # in pieces, as the generator makes doubles
        vectors[lo : lo + (1 << 16)] = rng.normal(0, 0.1, (min(1 << 16, size - lo), DIM))
    gathered = np.full(size, 1e-8, np.float32)
    top = np.zeros((DIM, 2), np.float32)
    top[:, 0], top[:, 1] = -0.5, 0.5
    top += rng.normal(0, 0.1, top.shape)
    bias = np.log(np.maximum(np.bincount(label, minlength=2), 1) / len(label)).astype(np.float32)
    n = len(sample)
    epochs = min(60, max(4, -(-steps // n)))
    for epoch in range(epochs):
        rate = RATE * (1 - epoch / epochs)
        for k in rng.permutation(n):
            bucket, part = sample[k]
            if not len(bucket):
                continue
            mean = part @ vectors[bucket]
            logit = mean @ top + bias
            odds = np.exp(logit - logit.max())
            error = odds / odds.sum()
            error[label[k]] -= 1
            back = top @ error
            top -= 0.05 * rate * np.outer(mean, error)
            gathered[bucket] += part * part * (back @ back) / DIM
            vectors[bucket] -= (0.2 * rate * part / np.sqrt(gathered[bucket]))[:, None] * back
    sample.close()
    edge = top[:, 1] - top[:, 0]
    return Model((vectors @ edge).astype(np.float64), float(bias[1] - bias[0]))


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, sample_bytes: int = SAMPLE_BYTES) -> Model:
    """Trains on labelled documents outside the held-out fold: at most sample_rows of them, and of these, in the order of
    the hash, as many as have sample_bytes of text together; a text that does not fit is passed over."""
    known = labels.filter("doc_id is not null and quality in (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    order = F.xxhash64("doc_id", F.lit(SEED))
    chosen = known.filter(~held_out()).orderBy(order, "doc_id").limit(sample_rows)
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")
    rows = materialise(rows.dropDuplicates(["doc_id"]).select("doc_id", "text", "quality", order.alias("place")), "sample")
    sizes = rows.select("doc_id", "place", F.coalesce(F.octet_length("text"), F.lit(0)).alias("n")).toPandas().sort_values(["place", "doc_id"])
    room, fits = sample_bytes, []
    for doc, n in zip(sizes["doc_id"].tolist(), sizes["n"].tolist(), strict=True):
        if n <= room:
            room -= n
            fits.append((doc,))
    if len(fits) < len(sizes):
        rows = rows.join(F.broadcast(rows.sparkSession.createDataFrame(fits, rows.select("doc_id").schema)), "doc_id", "left_semi")
    got = rows.select("doc_id", "text", "quality").toArrow().sort_by("doc_id")
    model = train(_Texts(got["text"]), got["quality"].to_numpy().astype(np.int64))
    del got
    give_back()
    return model


def score(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """All columns of docs, then r_score and r_predicted."""
    names = [f"c{i}" for i in range(len(docs.columns))]
    text = docs.columns.index("text")
    kinds = ", ".join(f"{n} {f.dataType.simpleString()}" for n, f in zip(names, docs.schema.fields, strict=True))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            value = model.scores(batch.column(text))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(value), pa.array((value >= threshold).astype(np.int32))], [*names, "r_score", "r_predicted"])
        give_back()

    out = docs.toDF(*names).withColumn(names[text], F.col(names[text]).cast("string")).mapInArrow(run, f"{kinds}, r_score double, r_predicted int")
    return out.toDF(*docs.columns, "r_score", "r_predicted")
