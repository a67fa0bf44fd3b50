"""WARC archives as a Spark data source with planned files, pushed predicates and late decoding.

*Written* records are of WARC 1.1: dated, with the page as an HTTP response; a revisit holds the HTTP
headers of the payload that it refers to.  Every record is one gzip member whose header carries its
own length in an extra field (the skip length), so a reader decompresses a record's headers only,
and jumps over payloads that it does not need.  Files belong to an archive when the manifest names
them; the manifest is written once all tasks have committed, so failed or repeated tasks leave
nothing visible.  It also names places inside large files where a reader may begin.

*Read* are archives of any writer: gzip members of one or many records, with or without skip
lengths, plain files, records of all types, blocks with and without HTTP headers.  A folder without
a manifest is read by its ``.warc`` and ``.warc.gz`` files, each by one task; ``path`` may be a file.

Options of the reader: ``path``; ``record_types`` (comma-separated) and ``min_payload`` as header
predicates, also taken from filters on record_type and payload_bytes; ``payload`` (default true)
decodes payloads; ``verify`` checks payloads against length and digest even when they are not
returned; ``split_bytes`` of a task.

Defined cases: a null html is an empty payload; a null url leaves the target out; equal payloads,
empty ones too, are revisits of the smallest page_id; repeated page rows are repeated records; an
empty table gives an archive without records; lengths have no limit (members of 4 GiB and more
carry no skip length).
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from dataclasses import dataclass
from datetime import UTC, datetime

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import (
    DataSource,
    DataSourceArrowWriter,
    DataSourceReader,
    EqualTo,
    GreaterThan,
    GreaterThanOrEqual,
    In,
    InputPartition,
    WriterCommitMessage,
)

from gistloom.llm.shared import fresh_path

SCHEMA = "record_id string, record_type string, target string, refers_to string, payload_digest string, payload_bytes long, payload binary"
BROADCAST_DIGESTS = 1_000_000
MANIFEST = "_manifest.json"
BEGIN_EVERY = 8 << 20  # bytes between the places that the manifest names


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    if "://" in path or path.startswith("file:"):
        if path.startswith("file:") and not path.startswith("file://"):
            path = "file://" + path[5:]
        return pafs.FileSystem.from_uri(path)
    return pafs.LocalFileSystem(), path


def _clean(value: str) -> str:
    return value.replace("\r", "%0D").replace("\n", "%0A")


def encode_record(page_id, url, html, refers_to, date: str) -> bytes:
    """One gzip member; revisits carry the digest and the HTTP headers of the payload that they refer to."""
    body = (html or "").encode("utf-8", "surrogatepass")
    digest = base64.b32encode(hashlib.sha1(body).digest()).decode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + body
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {date}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {_clean(url)}")
    if refers_to is not None:
        lines += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += [f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return gzip_member("\r\n".join(lines).encode("utf-8", "surrogatepass") + block + b"\r\n\r\n")


def gzip_member(raw: bytes) -> bytes:
    deflate = zlib.compressobj(6, zlib.DEFLATED, -15)
    packed = deflate.compress(raw) + deflate.flush()
    tail = struct.pack("<II", zlib.crc32(raw), len(raw) & 0xFFFFFFFF)
    total = 10 + 2 + 12 + len(packed) + 8
    if max(total, len(raw)) >= 1 << 32:
        return b"\x1f\x8b\x08\0" + b"\0\0\0\0\0\xff" + packed + tail
    head = b"\x1f\x8b\x08\x04" + b"\0\0\0\0\0\xff" + struct.pack("<H", 12) + b"sl" + struct.pack("<HII", 8, total, len(raw))
    return head + packed + tail


@dataclass
class _Written(WriterCommitMessage):
    file: str
    size: int
    records: int
    begins: list


class WarcWriter(DataSourceArrowWriter):
    def __init__(self, path: str, overwrite: bool):
        self.path, self.overwrite = path, overwrite

    def write(self, iterator) -> _Written:
        system, base = _open(self.path)
        system.create_dir(base, recursive=True)
        date = datetime.now(UTC).strftime("%Y-%m-%dT%H:%M:%SZ")
        name, size, records, begins = f"part-{uuid.uuid4().hex}.warc.gz", 0, 0, [0]
        with system.open_output_stream(f"{base}/{name}", compression=None) as out:
            for batch in iterator:
                columns = [batch.column(batch.schema.get_field_index(c)) for c in ("page_id", "url", "html", "refers_to")]
                for i in range(len(batch)):
                    if size - begins[-1] >= BEGIN_EVERY:
                        begins.append(size)
                    member = encode_record(*(c[i].as_py() for c in columns), date)
                    out.write(member)
                    size += len(member)
                    records += 1
        return _Written(name, size, records, begins)

    def commit(self, messages) -> None:
        system, base = _open(self.path)
        system.create_dir(base, recursive=True)
        kept = [] if self.overwrite else _manifest(system, base) or []
        kept = sorted([*kept, *([m.file, m.size, m.begins] for m in messages if m is not None and m.records)])
        with system.open_output_stream(f"{base}/{MANIFEST}") as out:
            out.write(json.dumps(kept).encode())

    def abort(self, messages) -> None:
        system, base = _open(self.path)
        for m in messages:
            if m is not None:
                system.delete_file(f"{base}/{m.file}")


def _manifest(system: pafs.FileSystem, base: str) -> list | None:
    if system.get_file_info(f"{base}/{MANIFEST}").type == pafs.FileType.NotFound:
        return None
    with system.open_input_stream(f"{base}/{MANIFEST}") as f:
        return json.loads(f.read())


class _Bytes:
    """The bytes of a file from a place on, out of its gzip members where it has any."""

    def __init__(self, f, at: int):
        self.f, self.next, self.held, self.unpack, self.skip = f, at, b"", None, None
        f.seek(at)
        self.plain = f.read(2) != b"\x1f\x8b"

    def place(self) -> int | None:
        """Offset in the file where the next record begins, if a member does."""
        return None if self.held or self.unpack else self.next

    def _member(self, first: bytes) -> None:
        """The end of the member that begins here, if its header carries a skip length."""
        self.skip = None
        if len(first) >= 12 and first[3] & 4:
            extra, at = first[12 : 12 + struct.unpack("<H", first[10:12])[0]], 0
            while at + 4 <= len(extra):
                kind, size = extra[at : at + 2], struct.unpack("<H", extra[at + 2 : at + 4])[0]
                if kind == b"sl" and size >= 4:
                    self.skip = self.next + struct.unpack("<I", extra[at + 4 : at + 8])[0]
                at += 4 + size

    def _more(self, most: int) -> bool:
        if self.plain:
            self.f.seek(self.next)
            block = self.f.read(most)
            self.next += len(block)
            self.held += block
            return bool(block)
        if self.unpack is None:
            self.f.seek(self.next)
            block = self.f.read(4096)
            if not block:
                return False
            self._member(block)
            self.unpack = zlib.decompressobj(31)
        else:
            block = self.unpack.unconsumed_tail
            if not block:
                self.f.seek(self.next)
                block = self.f.read(max(4096, min(most, 1 << 20)))
                if not block:
                    raise ValueError("a gzip member has no end")
        fresh = 0 if block is self.unpack.unconsumed_tail else len(block)
        self.held += self.unpack.decompress(block, max(most, 1024))
        self.next += fresh
        if self.unpack.eof:
            self.next -= len(self.unpack.unused_data)
            self.unpack = None
        return True

    def until(self, mark: bytes) -> bytes | None:
        """Bytes up to and with the mark; None at the end of the file."""
        while mark not in self.held:
            if not self._more(4096):
                return None
        at = self.held.index(mark) + len(mark)
        out, self.held = self.held[:at], self.held[at:]
        return out

    def take(self, size: int) -> bytes:
        parts = [self.held[:size]]
        self.held = self.held[size:]
        missing = size - len(parts[0])
        while missing and self._more(missing):
            parts.append(self.held[:missing])
            self.held = self.held[missing:]
            missing -= len(parts[-1])
        return b"".join(parts)

    def drop(self, size: int, alone: bool) -> None:
        """Passes over bytes; jumps to the next member where the record is ``alone`` in one that says where it ends."""
        if alone and self.skip is not None and not self.plain:
            self.next, self.held, self.unpack = self.skip, b"", None
            return
        if self.plain:
            ahead = max(0, size - len(self.held))
            self.held = self.held[size:]
            self.next += ahead
            return
        while size:
            size -= len(self.take(min(size, 1 << 20))) or size


def _fields(head: bytes) -> dict[str, str]:
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")[1:]
    return {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in lines if line)}


@dataclass
class _Files(InputPartition):
    spans: list  # (file, first byte, end)


class WarcReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]
        self.types = {t.strip() for t in options.get("record_types", "").split(",") if t.strip()} or None
        self.least = int(options.get("min_payload", 0))
        self.payload = options.get("payload", "true").lower() == "true"
        self.verify = options.get("verify", "false").lower() == "true"
        self.target = int(options.get("split_bytes", 64 << 20))

    def pushFilters(self, filters):
        """Takes equality and IN on record_type, and lower bounds of payload_bytes, out of the query."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("record_type",):
                self.types = {f.value} if self.types is None else {f.value} & self.types
            elif isinstance(f, In) and f.attribute == ("record_type",):
                self.types = set(f.value) if self.types is None else set(f.value) & self.types
            elif isinstance(f, GreaterThanOrEqual) and f.attribute == ("payload_bytes",):
                self.least = max(self.least, f.value)
            elif isinstance(f, GreaterThan) and f.attribute == ("payload_bytes",):
                self.least = max(self.least, f.value + 1)
            else:
                yield f

    def _listed(self, system, base) -> list:
        info = system.get_file_info(base)
        if info.type == pafs.FileType.File:
            return [["", info.size, [0]]]
        listed = _manifest(system, base)
        if listed is None:
            found = system.get_file_info(pafs.FileSelector(base))
            listed = [[i.base_name, i.size, [0]] for i in found if i.type == pafs.FileType.File and i.base_name.endswith((".warc", ".warc.gz"))]
        return sorted(listed)

    def partitions(self) -> list:
        """Spans of files that begin where the manifest says a record does, packed up to split_bytes each."""
        system, base = _open(self.path)
        packs: list = []
        room = 0
        for name, size, begins in self._listed(system, base):
            cuts = [0]
            for at in begins:
                if at - cuts[-1] >= self.target:
                    cuts.append(at)
            for first, end in zip(cuts, [*cuts[1:], size], strict=True):
                if not packs or room < end - first:
                    packs.append(_Files([]))
                    room = self.target
                packs[-1].spans.append((name, first, end))
                room -= end - first
        return packs or [_Files([])]

    def read(self, partition):
        system, base = _open(self.path)
        for name, first, end in partition.spans:
            with system.open_input_file(f"{base}/{name}" if name else base) as f:
                yield from self._batches(f, first, end)

    def _batches(self, f, first, end):
        rows, held = [], 0
        for row in self._records(f, first, end):
            rows.append(row)
            held += len(row[6] or b"") + 200
            if held > 4_000_000:
                yield _as_batch(rows)
                rows, held = [], 0
        if rows:
            yield _as_batch(rows)

    def _records(self, f, first, end):
        source = _Bytes(f, first)
        while True:
            at = source.place()
            if (at is not None and at >= end) or (source.plain and source.next - len(source.held) >= end):
                return
            head = source.until(b"\r\n\r\n")
            if head is None:
                return
            head = head.lstrip(b"\r\n")
            if not head.startswith(b"WARC/"):
                raise ValueError(f"no WARC record where one should begin: {head[:40]!r}")
            fields = _fields(head)
            kind, size = fields.get("warc-type", ""), int(fields["content-length"])
            alone = at is not None
            if self.types is not None and kind not in self.types:
                source.drop(size + 4, alone)
                continue
            rest, n = size, size
            if size and fields.get("content-type", "").lower().startswith("application/http"):
                http = source.until(b"\r\n\r\n") or b""
                if len(http) > size:  # headers without an end: all of the block is payload
                    source.held = http + source.held
                else:
                    rest = size - len(http)
                    told = _fields(http).get("content-length", "")
                    n = int(told) if kind == "revisit" and told.isdigit() else rest
            digest = fields.get("warc-payload-digest")
            if n < self.least:
                source.drop(rest + 4, alone)
                continue
            body = None
            if self.payload or (self.verify and kind != "revisit"):
                body = source.take(rest)
                source.drop(4, alone)
                if len(body) != rest:
                    raise ValueError(f"payload of {fields.get('warc-record-id')} is cut off")
                if self.verify and kind != "revisit" and digest and digest.lower().startswith("sha1:"):
                    if base64.b32encode(hashlib.sha1(body).digest()).decode() != digest[5:].upper():
                        raise ValueError(f"payload of {fields.get('warc-record-id')} does not fit its digest")
            else:
                source.drop(rest + 4, alone)
            bare = digest.partition(":")[2] if digest and ":" in digest else digest
            yield (_inner(fields.get("warc-record-id")), kind, fields.get("warc-target-uri"), _inner(fields.get("warc-refers-to")), bare, n, body if self.payload else None)


def _inner(urn: str | None) -> str | None:
    return None if urn is None else urn.strip("<>").removeprefix("urn:page:")


def _as_batch(rows) -> pa.RecordBatch:
    kinds = [pa.string()] * 5 + [pa.int64(), pa.binary()]
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[i]) for i in range(7)], names)


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return WarcReader(dict(self.options))

    def writer(self, schema, overwrite):
        return WarcWriter(self.options["path"], overwrite)


def write_archive(pages: DataFrame, path: str) -> None:
    """One record a row; rows whose payload occurs at a smaller page_id become revisits of it.

    Only payload digests that occur more than once are joined back, broadcast under a counted
    bound, so payloads are not shuffled.
    """
    spark = pages.sparkSession
    spark.dataSource.register(WarcSource)
    html = F.coalesce("html", F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", html.alias("html"), F.sha1(html).alias("_gl_sha"))
    firsts = rows.groupBy("_gl_sha").agg(F.min("page_id").alias("_gl_first"), F.count("*").alias("_gl_n")).where("_gl_n > 1").select(F.col("_gl_sha").alias("_gl_key"), "_gl_first")
    small = F.broadcast(firsts) if firsts.count() <= BROADCAST_DIGESTS else firsts
    later = F.when(F.col("page_id") != F.col("_gl_first"), F.col("_gl_first"))
    out = rows.join(small, F.col("_gl_sha") == F.col("_gl_key"), "left").select("page_id", "url", "html", later.alias("refers_to"))
    out.write.format("warc").option("path", path).mode("append").save()


def read_archive(spark: SparkSession, path: str, **options: str) -> DataFrame:
    """Records of an archive; turns on the session's pushdown into Python sources, which the reader relies on."""
    spark.dataSource.register(WarcSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    return spark.read.format("warc").options(path=path, **options).load()


def round_trip(pages: DataFrame) -> DataFrame:
    """Pages written to a fresh archive in the shared folder and read back from their headers."""
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    write_archive(pages, path)
    back = read_archive(spark, path, payload="false", verify="true")
    return back.select(F.expr("try_cast(record_id as bigint)").alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.expr("try_cast(refers_to as bigint)").alias("refers_to"))
