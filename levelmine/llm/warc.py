"""WARC archives as a Python data source: reading and writing, with revisit records for equal payloads.

Writing: one archive a task, each record a gzip member of its own whose header tells the member's length in an extra
field, so that a reader can go from record to record without inflating payloads.
Reading: the files are the partitions. Filters on columns that come from headers are pushed down; a record's headers
are inflated and parsed first, and its payload only if the record passes and the payload is asked for.
Archives of other writers (plain or gzip, with no such field) are read too, record by record.

Options: path; payload ("true": return payloads), verify ("true": inflate payloads and compare their digests).
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import datasource as ds
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from levelmine.session import scratch_path

SCHEMA = "record_type string, page_id long, target_uri string, payload_bytes long, payload_digest string, refers_to long, content_length long, payload binary"
PUSHED = ("record_type", "page_id", "target_uri", "payload_bytes", "payload_digest", "refers_to", "content_length")
_URN = "urn:page:"
_EXTRA = b"RL"  # sub-field of the gzip header: the member's length
_DATE = "2020-01-01T00:00:00Z"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _member(data: bytes) -> bytes:
    body = zlib.compressobj(6, zlib.DEFLATED, -15)
    packed = body.compress(data) + body.flush()
    size = 10 + 2 + 12 + len(packed) + 8
    head = b"\x1f\x8b\x08\x04" + bytes(4) + b"\x00\xff" + struct.pack("<H2sHQ", 12, _EXTRA, 8, size)
    return head + packed + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


def record_bytes(record_type: str, page_id: int | None, uri: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One record; a revisit holds the HTTP headers alone."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + (payload if record_type == "response" else b"")
    lines = ["WARC/1.1", f"WARC-Type: {record_type}"]
    lines.append(f"WARC-Record-ID: <{_URN}{page_id}>" if page_id is not None else f"WARC-Record-ID: <urn:uuid:{uuid.uuid4()}>")
    lines += [f"WARC-Date: {_DATE}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if uri is not None:
        lines.append(f"WARC-Target-URI: {' '.join(uri.split())}")
    if record_type == "revisit":
        lines += [f"WARC-Refers-To: <{_URN}{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode("utf-8", "replace") + b"\r\n\r\n" + block + b"\r\n\r\n"


def _open(path: str):
    """(file system, path) of any URI that Arrow knows; a bare path is local."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


@dataclass
class _Done(ds.WriterCommitMessage):
    files: list


class WarcWriter(ds.DataSourceWriter):
    def __init__(self, path: str, overwrite: bool):
        self.path, self.overwrite = path, overwrite

    def write(self, rows: Iterator) -> ds.WriterCommitMessage:
        system, base = _open(self.path)
        name = f"{base}/_part-{uuid.uuid4().hex}"  # no reader takes it before the commit
        system.create_dir(base, recursive=True)
        some = False
        with system.open_output_stream(name, compression=None) as out:
            for r in rows:
                some = True
                payload = bytes(r.payload or b"")
                out.write(_member(record_bytes(r.record_type, r.page_id, r.target_uri, payload, base32_sha1(payload), r.refers_to)))
        if not some:
            system.delete_file(name)
        return _Done([name] if some else [])

    def commit(self, messages) -> None:
        """Gives the files of the attempts that count their names; what other attempts have left is never read."""
        from pyarrow import fs

        system, base = _open(self.path)
        system.create_dir(base, recursive=True)
        if self.overwrite:
            for f in system.get_file_info(fs.FileSelector(base)):
                if f.is_file and f.path.endswith((".warc", ".warc.gz")):
                    system.delete_file(f.path)
        for m in messages:
            for f in m.files if m else []:
                folder, _, file = f.rpartition("/")
                system.move(f, f"{folder}/{file.removeprefix('_')}.warc.gz")

    def abort(self, messages) -> None:
        system, _ = _open(self.path)
        for m in messages:
            for f in m.files if m else []:
                system.delete_file(f)


class _Part(ds.InputPartition):
    def __init__(self, file: str):
        self.file = file


def _headers(data: bytes) -> tuple[dict[str, str], int]:
    """Fields of a WARC header, and where its block begins."""
    end = data.index(b"\r\n\r\n")
    fields = {}
    for line in data[:end].decode("utf-8", "replace").split("\r\n")[1:]:
        name, _, value = line.partition(":")
        fields[name.strip().lower()] = value.strip()
    return fields, end + 4


class _GzipRecords:
    """Members of a gzip archive one after the other; only what is asked for is inflated."""

    def __init__(self, stream):
        self.stream, self.at = stream, 0

    def _start(self) -> tuple[int | None, bytes]:
        self.stream.seek(self.at)
        head = self.stream.read(24)
        length = None
        if len(head) == 24 and head[3] & 4 and head[12:14] == _EXTRA:
            length = struct.unpack("<Q", head[16:24])[0]
        return length, head

    def __iter__(self):
        while True:
            length, head = self._start()
            if len(head) < 18:
                return
            box = zlib.decompressobj(31)
            data, pos = b"", self.at
            while b"\r\n\r\n" not in data:
                self.stream.seek(pos)
                raw = self.stream.read(2048)
                if not raw:
                    return
                data += box.decompress(raw)
                pos += len(raw)
            fields, begin = _headers(data)

            def block(box=box, data=data, begin=begin, fields=fields, pos=pos):
                """The record's block, and where the next member starts if no length says so."""
                out, at = bytearray(data), pos
                while not box.eof:
                    self.stream.seek(at)
                    raw = self.stream.read(1 << 16)
                    if not raw:
                        break
                    out += box.decompress(raw)
                    at += len(raw)
                self.after = at - len(box.unused_data)
                return bytes(out[begin : begin + int(fields["content-length"])])

            yield fields, block
            if length is not None:
                self.at += length
            else:
                if not box.eof:
                    block()
                else:
                    self.after = getattr(self, "after", pos - len(box.unused_data))
                self.at = self.after


class _PlainRecords:
    def __init__(self, stream):
        self.stream = stream

    def __iter__(self):
        at = 0
        while True:
            self.stream.seek(at)
            data = b""
            while b"\r\n\r\n" not in data:
                raw = self.stream.read(4096)
                if not raw:
                    return
                data += raw
            fields, begin = _headers(data)
            size = int(fields["content-length"])

            def block(start=at + begin, size=size):
                self.stream.seek(start)
                return self.stream.read(size)

            yield fields, block
            at += begin + size + 4


def _page(urn: str | None) -> int | None:
    tail = (urn or "").strip("<>").removeprefix(_URN)
    return int(tail) if tail.lstrip("-").isdigit() else None


def _payload(block: bytes, kind: str) -> bytes:
    return block.partition(b"\r\n\r\n")[2] if kind.startswith("application/http") else block


class WarcReader(ds.DataSourceReader):
    def __init__(self, options: dict, schema: StructType):
        self.path = options["path"]
        self.with_payload = options.get("payload", "true") == "true"
        self.verify = options.get("verify", "false") == "true"
        self.names = schema.fieldNames()
        self.tests: list[tuple[str, str, object]] = []

    def pushFilters(self, filters):
        for f in filters:
            column = getattr(f, "attribute", (None,))
            kind = type(f).__name__
            if len(column) == 1 and column[0] in PUSHED and kind in ("EqualTo", "In", "IsNotNull", "IsNull", "GreaterThan", "GreaterThanOrEqual", "LessThan", "LessThanOrEqual", "StringStartsWith"):
                self.tests.append((kind, column[0], getattr(f, "value", None)))
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        system, base = _open(self.path)
        info = system.get_file_info(base)
        found = [info] if info.is_file else system.get_file_info(fs.FileSelector(base, recursive=True, allow_not_found=True))
        files = sorted((f.path, f.size) for f in found if f.is_file and f.path.endswith((".warc", ".warc.gz")))
        return [_Part(path) for path, _ in sorted(files, key=lambda x: -x[1])] or [_Part("")]

    def _passes(self, row: dict) -> bool:
        for kind, column, value in self.tests:
            have = row[column]
            if kind == "IsNull":
                ok = have is None
            elif have is None:
                ok = False
            else:
                ok = {"EqualTo": lambda: have == value, "In": lambda: have in value, "IsNotNull": lambda: True, "GreaterThan": lambda: have > value, "GreaterThanOrEqual": lambda: have >= value,
                      "LessThan": lambda: have < value, "LessThanOrEqual": lambda: have <= value, "StringStartsWith": lambda: have.startswith(value)}[kind]()
            if not ok:
                return False
        return True

    def _read_payload(self, row: dict, fields: dict, block, partition: _Part) -> bytes:
        """The payload; its length and digest are entered in the row."""
        payload = _payload(block(), fields.get("content-type", ""))
        digest = base32_sha1(payload)
        if self.verify and row["payload_digest"] not in (None, digest):
            raise ValueError(f"{partition.file}: record {fields.get('warc-record-id')} has another digest")
        row["payload_bytes"], row["payload_digest"] = len(payload), digest
        return payload

    def read(self, partition: _Part) -> Iterator[pa.RecordBatch]:
        if not partition.file:
            return
        system, _ = _open(self.path)
        types = {"record_type": pa.string(), "page_id": pa.int64(), "target_uri": pa.string(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "refers_to": pa.int64(), "content_length": pa.int64(), "payload": pa.binary()}
        rows, held = [], 0
        asked = {"payload_bytes", "payload_digest"} & {column for _, column, _ in self.tests}
        with system.open_input_file(partition.file) as stream:
            for fields, block in (_GzipRecords if partition.file.endswith(".gz") else _PlainRecords)(stream):
                said = fields.get("x-payload-length")
                row = {
                    "record_type": fields.get("warc-type"), "page_id": _page(fields.get("warc-record-id")), "target_uri": fields.get("warc-target-uri"),
                    "payload_bytes": int(said) if said else None, "payload_digest": (fields.get("warc-payload-digest") or "").removeprefix("sha1:") or None,
                    "refers_to": _page(fields.get("warc-refers-to")), "content_length": int(fields["content-length"]), "payload": None,
                }
                payload = None
                if row["record_type"] != "revisit" and any(row[c] is None for c in asked):  # other writers' headers may lack it
                    payload = self._read_payload(row, fields, block, partition)
                if not self._passes(row):
                    continue
                if row["record_type"] != "revisit" and (self.with_payload or self.verify):
                    payload = self._read_payload(row, fields, block, partition) if payload is None else payload
                    if self.with_payload:
                        row["payload"] = payload
                        held += len(payload)
                rows.append(row)
                if len(rows) >= 5000 or held > 8 << 20:
                    yield pa.RecordBatch.from_pylist([{n: r[n] for n in self.names} for r in rows], pa.schema([(n, types[n]) for n in self.names]))
                    rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_pylist([{n: r[n] for n in self.names} for r in rows], pa.schema([(n, types[n]) for n in self.names]))


class WarcSource(ds.DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> WarcReader:
        return WarcReader(dict(self.options), schema)

    def writer(self, schema: StructType, overwrite: bool) -> WarcWriter:
        return WarcWriter(self.options["path"], overwrite)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


def records(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """Pages as records. Of equal payloads of min_revisit_bytes or more, the one with the least page_id is the response.

    Defined results. Null html: an empty payload. A null page_id counts as larger than all; such a row revisits a page
    with an id if there is one, and is a response else. Rows that repeat a response's page_id and payload are responses.
    """
    payload = F.encode(F.coalesce(F.col("html").cast("string"), F.lit("")), "UTF-8")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("target_uri"), payload.alias("payload"))
    rows = rows.withColumn("sha", F.sha1("payload"))
    first = rows.groupBy("sha").agg(F.min("page_id").alias("first")).withColumnRenamed("sha", "of")
    both = rows.join(first, F.col("sha") == F.col("of"))
    again = (F.octet_length("payload") >= min_revisit_bytes) & F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return both.select(
        F.when(again, "revisit").otherwise("response").alias("record_type"), "page_id", "target_uri",
        F.octet_length("payload").cast("long").alias("payload_bytes"), F.col("sha").alias("payload_digest"),
        F.when(again, F.col("first")).alias("refers_to"), F.lit(None).cast("long").alias("content_length"), "payload",
    )


def write_pages(pages: DataFrame, path: str, min_revisit_bytes: int = 0) -> None:
    register(pages.sparkSession)
    records(pages, min_revisit_bytes).write.format("warc").mode("append").save(path)


def round_trip(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """Writes archives to the shared folder and reads them back with verified digests."""
    spark = pages.sparkSession
    path = scratch_path(spark, "warc")
    write_pages(pages, path, min_revisit_bytes)
    back = spark.read.format("warc").option("payload", "false").option("verify", "true").load(path)
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
