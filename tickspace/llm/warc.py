"""WARC archives as a PySpark Python data source, for reading and writing.

Each record is a gzip member of its own whose extra field holds the member's
compressed and uncompressed length (subfield ``sl``, as the WARC format's annex
on compression has it).  A reader therefore inflates a record's first kilobytes
only, parses the headers, applies the pushed predicates, and jumps over the rest
when the record or its payload is not wanted; members without the field, and
files without compression, are read through.

Reading: ``spark.read.format("warc").load(folder)``.  Files are planned into
partitions of about ``partition_bytes``; a larger file is cut where its writer's
manifest says that records begin (a foreign one is a partition of its own).  Rows
come as Arrow batches of bounded size.  Equality, IN, NULL and comparison
predicates on header columns are pushed down (where the session allows filters to
be pushed to Python sources); ``option("payload", "false")`` leaves the payload
column null and undecoded.  Writing: rows with the columns ``record_type,
record_id, target_uri, refers_to, http, payload_length, payload_digest, payload``;
attempts write files of unique names, and only those of the job's commit message
get into the manifest, so retried and speculative tasks leave no double records.

Folders are opened through pyarrow's file systems, hence by any URI that these
know (local, HDFS, S3, GCS).

Defined cases (``archive_rows``): null pages are empty payloads; a null id is
``urn:page:null`` and is the response of its payload only where no other row has
one; rows repeated under the smallest id are responses all; columns beyond id,
url and payload are ignored, whatever their names; an empty table writes no file,
and a folder without files reads as an empty table.
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualNullSafe, EqualTo, GreaterThan, GreaterThanOrEqual, In, InputPartition, IsNotNull, IsNull, LessThan, LessThanOrEqual, StringStartsWith, WriterCommitMessage

from .shared import BATCH_BYTES, bounded, materialise

SCHEMA = "file string, position bigint, record_type string, record_id string, target_uri string, refers_to string, http string, payload_length bigint, payload_digest string, payload binary"
_FIELDS = {"record_type": "WARC-Type", "record_id": "WARC-Record-ID", "target_uri": "WARC-Target-URI", "refers_to": "WARC-Refers-To", "payload_digest": "WARC-Payload-Digest"}
_MANIFEST = "_manifest.json"
_REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def encode_record(row) -> bytes:
    """One record before compression.  A revisit carries the HTTP headers of
    the response it stands for, with their Content-Length, and no payload."""
    payload = b"" if row["record_type"] == "revisit" else bytes(row["payload"] or b"")
    block = (row["http"] or f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {row['payload_length']}\r\n\r\n").encode() + payload
    clean = lambda x: " ".join(str(x).split())  # noqa: E731  header values hold no line breaks
    head = ["WARC/1.1", f"WARC-Type: {row['record_type']}", f"WARC-Record-ID: <{clean(row['record_id'])}>", "WARC-Date: 2024-01-01T00:00:00Z"]
    if row["target_uri"] is not None:
        head.append(f"WARC-Target-URI: {clean(row['target_uri'])}")
    if row["refers_to"] is not None:
        head += [f"WARC-Refers-To: <{clean(row['refers_to'])}>", f"WARC-Profile: {_REVISIT_PROFILE}"]
    head += [f"WARC-Payload-Digest: sha1:{row['payload_digest']}", "Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def gzip_member(data: bytes, level: int = 1) -> bytes:
    squeeze = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = squeeze.compress(data) + squeeze.flush()
    total = 12 + 12 + len(body) + 8
    return b"\x1f\x8b\x08\x04\0\0\0\0\0\xff" + struct.pack("<H2sHII", 12, b"sl", 8, total, len(data) & 0xFFFFFFFF) + body + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


def _header(raw: bytes) -> dict[str, str]:
    out, last = {}, None
    for line in raw.decode("utf-8", "replace").split("\r\n")[1:]:
        if line[:1] in (" ", "\t") and last:
            out[last] += " " + line.strip()
        elif ":" in line:
            name, _, value = line.partition(":")
            last = name.strip().lower()
            out[last] = value.strip()
    return out


def _row(head: dict[str, str]) -> dict:
    row = {k: head.get(v.lower()) for k, v in _FIELDS.items()}
    for k in ("record_id", "refers_to"):
        if row[k]:
            row[k] = row[k].strip("<>")
    if row["payload_digest"]:
        row["payload_digest"] = row["payload_digest"].removeprefix("sha1:")
    return row


class _Member:
    """A stream of one record's bytes, inflated no further than asked for."""

    def __init__(self, source, at: int, size: int):
        self.source, self.at, self.end, self.data, self.read = source, at, None, bytearray(), 0
        source.seek(at)
        start = source.read(min(24, size - at))
        self.plain = start[:2] != b"\x1f\x8b"
        if self.plain:
            source.seek(at)
            return
        if start[3] & 4 and start[12:14] == b"sl":
            self.end = at + struct.unpack("<I", start[16:20])[0]
        source.seek(at)
        self.inflate = zlib.decompressobj(31)

    def until(self, n: int | None, mark: bytes | None = None) -> bool:
        """Read until ``n`` bytes or ``mark`` are there; False at the end."""
        step, looked = 4096, 0
        while n is None or len(self.data) < n:
            if mark is not None:
                if self.data.find(mark, max(0, looked - len(mark))) >= 0:
                    return True
                looked = len(self.data)
            if self.plain:
                part = self.source.read(step)
            else:
                raw = self.inflate.unconsumed_tail or self.source.read(step)
                part = self.inflate.decompress(raw, 1 << 20)
                if not part and not raw and self.inflate.eof is False:
                    return False
                if self.inflate.eof:
                    self.data += part
                    return mark in self.data if mark else n is not None and len(self.data) >= n
            if not part and (self.plain or not raw):
                return False
            self.data += part
            step = min(step * 4, 1 << 20)
        return True

    def close(self, length: int) -> int:
        """Where the next record starts; ``length``: of this one, inflated."""
        if self.plain:
            return self.at + length
        if self.end is None:
            while not self.inflate.eof:
                raw = self.inflate.unconsumed_tail or self.source.read(1 << 16)
                if not raw:
                    break
                self.inflate.decompress(raw, 1 << 20)
            self.end = self.source.tell() - len(self.inflate.unused_data)
        return self.end


def read_records(source, size: int, keep=lambda row: True, payload: bool = True, start_at: int = 0, stop_at: int | None = None, inflated: list | None = None) -> Iterator[dict]:
    """Rows of one open archive, of the records that begin in [start_at,
    stop_at); ``keep`` sees the header columns only, and what it refuses is not
    inflated further.  ``inflated`` gets the bytes held of each record."""
    at, stop = start_at, size if stop_at is None else min(size, stop_at)
    while at < stop:
        member = _Member(source, at, size)
        if not member.until(None, b"\r\n\r\n"):
            if member.data.strip():
                raise ValueError(f"broken WARC record at {at}")
            return
        cut = member.data.index(b"\r\n\r\n")
        if not member.data.startswith(b"WARC/"):
            raise ValueError(f"no WARC record at {at}")
        head = _header(bytes(member.data[:cut]))
        start, length = cut + 4, int(head.get("content-length", 0))
        row = _row(head) | {"position": at, "http": None, "payload_length": None, "payload": None}
        if keep(row):
            if head.get("content-type", "").startswith("application/http"):
                ask = length if payload else min(length, 4096)
                member.until(start + ask)
                while (cut := member.data.find(b"\r\n\r\n", start, start + length)) < 0 and ask < length:
                    ask = min(length, 4 * ask)
                    member.until(start + ask)
                body = cut + 4 if cut >= 0 else start
                row["http"] = member.data[start:body].decode("utf-8", "replace")
                told = _header(row["http"].encode()).get("content-length")
                row["payload_length"] = int(told) if told else start + length - body
            else:
                body = start
                row["payload_length"] = length
            if payload:
                if not member.until(start + length):
                    raise ValueError(f"cut-off WARC record at {at}")
                row["payload"] = bytes(member.data[body : start + length])
            yield row
        if inflated is not None:
            inflated.append(len(member.data))
        at = member.close(start + length + 4)


def _accepts(filters) -> callable:
    tests = []
    for f in filters:
        col = f.attribute[0]
        if isinstance(f, (EqualTo, EqualNullSafe)):
            tests.append(lambda r, c=col, v=f.value: r[c] == v)
        elif isinstance(f, In):
            tests.append(lambda r, c=col, v=frozenset(f.value): r[c] in v)
        elif isinstance(f, IsNull):
            tests.append(lambda r, c=col: r[c] is None)
        elif isinstance(f, IsNotNull):
            tests.append(lambda r, c=col: r[c] is not None)
        elif isinstance(f, StringStartsWith):
            tests.append(lambda r, c=col, v=f.value: r[c] is not None and r[c].startswith(v))
        else:
            op = {GreaterThan: "__gt__", GreaterThanOrEqual: "__ge__", LessThan: "__lt__", LessThanOrEqual: "__le__"}[type(f)]
            tests.append(lambda r, c=col, v=f.value, o=op: r[c] is not None and getattr(r[c], o)(v))
    return lambda row: all(t(row) for t in tests)


class _Files(InputPartition):
    """(path, size, first byte, last byte + 1) of each file or piece."""

    def __init__(self, files: list[tuple[str, int, int, int]]):
        super().__init__(files)
        self.files = files


_KINDS = {"string": pa.string(), "bigint": pa.int64(), "binary": pa.large_binary()}
_ARROW = pa.schema([(c.split()[0], _KINDS[c.split()[1]]) for c in SCHEMA.split(", ")])


class WarcReader(DataSourceReader):
    def __init__(self, options):
        self.folder, self.filters = options["path"], []
        self.payload = str(options.get("payload", "true")).lower() != "false"
        self.bytes = int(options.get("partition_bytes", 64 << 20))

    def pushFilters(self, filters):
        for f in filters:
            if f.__class__ in (EqualTo, EqualNullSafe, In, IsNull, IsNotNull, StringStartsWith, GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual) and len(f.attribute) == 1 and f.attribute[0] in _FIELDS:
                self.filters.append(f)
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        store, root = filesystem(self.folder)
        found = {i.path: i.size for i in store.get_file_info(fs.FileSelector(root, recursive=True)) if i.is_file}
        listed = [p for p in found if p.endswith(_MANIFEST)]
        files = [p for p in found if p.endswith((".warc", ".warc.gz"))]
        marks: dict[str, list[int]] = {}
        if listed:
            for p in listed:
                with store.open_input_stream(p) as f:
                    marks |= {f"{p.rpartition('/')[0]}/{n}": at for n, at in json.loads(f.read())["files"].items()}
            files = [p for p in files if p in marks]
        parts, part, held = [], [], 0
        for p in sorted(files):
            edges = [0]
            for at in marks.get(p, ()):
                if at - edges[-1] >= self.bytes:
                    edges.append(at)
            for first, last in zip(edges, [*edges[1:], found[p]]):
                part.append((p, found[p], first, last))
                held += last - first
                if held >= self.bytes:
                    parts.append(_Files(part))
                    part, held = [], 0
        return parts + ([_Files(part)] if part else [])

    def read(self, partition):
        store, _ = filesystem(self.folder)
        keep, rows, held = _accepts(self.filters), [], 0

        def batch():
            return pa.RecordBatch.from_pylist(rows, schema=_ARROW)

        for path, size, first, last in partition.files if partition else ():
            with store.open_input_file(path) as f:
                for row in read_records(f, size, keep, self.payload, first, last):
                    rows.append(row | {"file": path})
                    held += 200 + len(row["payload"] or b"") + len(row["http"] or "")
                    if held >= BATCH_BYTES or len(rows) >= 5000:
                        yield batch()
                        rows, held = [], 0
        if rows:
            yield batch()


class _Wrote(WriterCommitMessage):
    def __init__(self, files):
        self.files = files


class WarcWriter(DataSourceWriter):
    def __init__(self, options):
        self.folder = options["path"]
        self.roll = int(options.get("file_bytes", 512 << 20))
        self.mark = int(options.get("mark_bytes", 4 << 20))
        self.level = int(options.get("level", 1))

    def write(self, rows):
        store, root = filesystem(self.folder)
        store.create_dir(root, recursive=True)
        files: dict[str, list[int]] = {}  # name -> places where a record begins, some apart
        out, held, marks = None, 0, []
        for row in rows:
            if out is None or held >= self.roll:
                if out is not None:
                    out.close()
                name = f"part-{uuid.uuid4().hex}.warc.gz"
                files[name] = marks = []
                out, held = store.open_output_stream(f"{root}/{name}", compression=None), 0
            if held - (marks[-1] if marks else 0) >= self.mark:
                marks.append(held)
            member = gzip_member(encode_record(row), self.level)
            out.write(member)
            held += len(member)
        if out is not None:
            out.close()
        return _Wrote(files)

    def commit(self, messages):
        store, root = filesystem(self.folder)
        store.create_dir(root, recursive=True)
        with store.open_output_stream(f"{root}/{uuid.uuid4().hex}{_MANIFEST}") as f:
            f.write(json.dumps({"files": {n: at for m in messages if m for n, at in m.files.items()}}).encode())

    def abort(self, messages):
        store, root = filesystem(self.folder)
        for m in messages:
            for n in m.files if m else ():
                store.delete_file(f"{root}/{n}")


class WarcSource(DataSource):
    @classmethod
    def name(cls):
        return "warc"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return WarcReader(self.options)

    def writer(self, schema, overwrite):
        return WarcWriter(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WarcSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")


def _digests(batches):
    for batch in batches:
        payload = batch.column(1).to_pylist()
        out = [(len(x), digest(x)) for x in (p or b"" for p in payload)]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([n for n, _ in out], pa.int64()), pa.array([d for _, d in out], pa.string())], ["id", "payload", "uri", "payload_length", "payload_digest"])


def archive_rows(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", min_bytes: int = 0) -> DataFrame:
    """Rows for the writer: of equal payloads of at least ``min_bytes`` the one
    with the smallest id is the response, the others are revisits of it.

    Null payloads are empty; rows repeated under the smallest id are responses
    all.  One pre-aggregated minimum by digest over payloads that come again,
    written, so that its true size decides on the join back: broadcast where it
    is small (no payload moves then), else a join that splits a hot payload."""
    src = bounded(pages).select(F.col(id_col).cast("bigint").alias("id"), F.encode(F.col(payload_col), "UTF-8").alias("payload"), F.col(url_col).alias("uri"))
    rows = src.mapInArrow(_digests, "id bigint, payload binary, uri string, payload_length bigint, payload_digest string")
    # the digest of the count is made in the JVM, so that this scan needs no Python
    key = src.select("id", F.sha1(F.coalesce("payload", F.lit(b""))).alias("hex"), F.coalesce(F.length("payload"), F.lit(0)).alias("n"))
    first = key.where(F.col("n") >= min_bytes).groupBy("hex").agg(F.min("id").alias("first"), F.count("*").alias("m")).where("m > 1")
    first = materialise(first.select(F.unhex("hex").alias("sha"), "first"), "first")
    joined = rows.withColumn("sha", F.unhex(F.sha1(F.coalesce("payload", F.lit(b""))))).join(first, "sha", "left")
    again = F.col("first").isNotNull() & ~F.col("id").eqNullSafe(F.col("first"))
    return joined.select(
        F.when(again, "revisit").otherwise("response").alias("record_type"),
        F.concat(F.lit("urn:page:"), F.coalesce(F.col("id").cast("string"), F.lit("null"))).alias("record_id"),
        F.col("uri").alias("target_uri"),
        F.when(again, F.concat(F.lit("urn:page:"), F.col("first").cast("string"))).alias("refers_to"),
        F.lit(None).cast("string").alias("http"),
        "payload_length",
        "payload_digest",
        F.when(~again, F.col("payload")).alias("payload"),
    )


def write_archives(rows: DataFrame, folder: str, **options) -> None:
    register(rows.sparkSession)
    rows.write.format("warc").mode("append").options(**options).save(folder)


def read_archives(spark: SparkSession, folder: str, **options) -> DataFrame:
    register(spark)
    return spark.read.format("warc").options(**options).load(folder)
