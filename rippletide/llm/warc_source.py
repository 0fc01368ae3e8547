"""A WARC source and sink for Spark as a Python data source.

Writing: each record is a gzip member of its own (or plain bytes), and a member's header carries an
extra field ``sl`` with its compressed and plain lengths, so that a reader steps over a record
without inflating it. A task writes files of about ``roll_bytes``.

Reading: one partition for each file. A record's header block is parsed first, and the payload of a
record that fails a predicate on its headers, or any payload when the option ``payload`` is false,
is never inflated or decoded. Members without the extra field are inflated to find their end.

Predicates on ``record_type``, ``record_id``, ``refers_to``, ``page_id`` and ``payload_digest`` come in
two ways: as the option ``only`` (JSON, column to list of values), or, with the option ``pushdown``,
as equality and IN filters of the query. Spark keeps a pushed-down reader with the loaded table, so a
DataFrame loaded with ``pushdown`` must serve one query only; without it any number may share it.

Files are reached through the Arrow file systems (local or any remote one the URI names).

Defined results: no archives give no rows. Payloads are read as UTF-8, whatever charset their headers name;
bytes that are none become U+FFFD. A record without a page id, length or digest in its headers has nulls
there. An archive that is damaged, or cut off inside a record that is read, fails the read with its path; a
cut inside a payload that is not read goes unnoticed. Pages that repeat an id get record ids by payload.
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from datetime import datetime, timezone

from pyarrow import fs as pafs
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, Filter, In, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

SCHEMA = "record_id string, record_type string, page_id long, target_uri string, date string, payload_digest string, payload_bytes long, refers_to long, payload string"
WRITE_FIELDS = ("page_id", "url", "payload", "record_type", "refers_to")
# A revisit whose payload is null is written with these.
KNOWN_FIELDS = ("payload_bytes", "payload_digest")
PUSHED = ("record_type", "record_id", "page_id", "refers_to", "payload_digest")
_DATE = datetime(2024, 1, 1, tzinfo=timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ")
_HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {}\r\n\r\n"


def file_system(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (pafs.LocalFileSystem(), path)


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_urn(page_id: int | None, digest: str) -> str:
    """The same page and payload have the same id; pages that repeat an id, or have none, differ by payload."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{digest}')}>"


def one_line(value: str) -> str:
    return " ".join(value.split())


def encode_record(page_id: int | None, url: str | None, payload: bytes, record_type: str, refers_to: int | None, size: int | None = None, digest: str | None = None) -> bytes:
    """A response with its HTTP block, or a revisit whose block is empty; the digest and length are
    those of the full payload either way, given as ``digest`` and ``size`` where the payload is not."""
    size, digest = (len(payload), base32_sha1(payload)) if digest is None else (size, digest)
    http = _HTTP.format(size).encode()
    block = http + payload if record_type == "response" else http
    head = [
        "WARC/1.1",
        f"WARC-Type: {record_type}",
        f"WARC-Record-ID: {record_urn(page_id, digest)}",
        f"WARC-Date: {_DATE}",
        f"WARC-Target-URI: {one_line(url or '')}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"X-Payload-Length: {size}",
    ]
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    if record_type == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_urn(refers_to, digest)}", f"X-Refers-To-Page: {refers_to}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def gzip_member(plain: bytes, level: int = 4) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = z.compress(plain) + z.flush()
    extra = b"sl" + struct.pack("<HII", 8, 24 + len(body) + 8, len(plain) & 0xFFFFFFFF)
    return b"\x1f\x8b\x08\x04\0\0\0\0\0\xff" + struct.pack("<H", len(extra)) + extra + body + struct.pack("<II", zlib.crc32(plain), len(plain) & 0xFFFFFFFF)


@dataclass
class _Written(WriterCommitMessage):
    files: list[str]


class WarcWriter(DataSourceWriter):
    def __init__(self, options: dict, schema: StructType) -> None:
        self.path = options["path"].rstrip("/")
        self.compress = options.get("compress", "true").lower() == "true"
        self.roll = int(options.get("roll_bytes", 128 << 20))
        names = schema.fieldNames()
        self.at = [names.index(f) for f in WRITE_FIELDS]
        self.known = [names.index(f) for f in KNOWN_FIELDS] if set(KNOWN_FIELDS) <= set(names) else None

    def write(self, rows: Iterator) -> _Written:
        fs, root = file_system(self.path)
        fs.create_dir(root, recursive=True)
        out, size, files = None, 0, []
        try:
            for row in rows:
                if out is None or size >= self.roll:
                    if out is not None:
                        out.close()
                    name = f"{root}/part-{uuid.uuid4().hex}.warc" + (".gz" if self.compress else "")
                    # Written under another name until commit: a lost or repeated task leaves no archive.
                    out, size = fs.open_output_stream(name + ".tmp", compression=None), 0
                    files.append(name)
                page_id, url, payload, kind, refers = (row[i] for i in self.at)
                known = [row[i] for i in self.known] if self.known and payload is None else []
                data = encode_record(page_id, url, (payload or "").encode(), kind, refers, *known)
                data = gzip_member(data) if self.compress else data
                out.write(data)
                size += len(data)
        finally:
            if out is not None:
                out.close()
        return _Written(files)

    def commit(self, messages: Sequence) -> None:
        fs, root = file_system(self.path)
        fs.create_dir(root, recursive=True)
        for m in messages:
            for f in m.files if m else []:
                fs.move(f + ".tmp", f)

    def abort(self, messages: Sequence) -> None:
        fs, _ = file_system(self.path)
        for m in messages:
            for f in m.files if m else []:
                if fs.get_file_info(f + ".tmp").type != pafs.FileType.NotFound:
                    fs.delete_file(f + ".tmp")


@dataclass
class WarcFile(InputPartition):
    path: str
    size: int


class _Bytes:
    """A buffered reader with skipping."""

    def __init__(self, stream, chunk: int = 1 << 20) -> None:
        self.stream, self.chunk, self.data, self.at = stream, chunk, b"", 0

    def need(self, n: int) -> bytes:
        """At least n bytes from here on, or all that are left."""
        while len(self.data) - self.at < n:
            more = self.stream.read(max(self.chunk, n - (len(self.data) - self.at)))
            if not more:
                break
            self.data, self.at = self.data[self.at :] + more, 0
        return self.data[self.at :] if self.at else self.data

    def take(self, n: int) -> bytes:
        self.need(n)
        out = self.data[self.at : self.at + n]
        self.at += len(out)
        return out

    def skip(self, n: int) -> None:
        held = len(self.data) - self.at
        if n <= held:
            self.at += n
        else:
            self.data, self.at = b"", 0
            self.stream.seek(n - held, 1)


def parse_head(head: bytes) -> dict[str, str]:
    lines = head.decode("utf-8", "replace").split("\r\n")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:] if x)}


def head_row(h: dict[str, str]) -> list:
    number = lambda k: int(h[k]) if h.get(k, "").lstrip("-").isdigit() else None
    digest = h.get("warc-payload-digest")
    return [h.get("warc-record-id"), h.get("warc-type"), number("x-page-id"), h.get("warc-target-uri"), h.get("warc-date"), digest.partition(":")[2] if digest else None, number("x-payload-length"), number("x-refers-to-page"), None]


class WarcReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path = options["path"].rstrip("/")
        self.payload = options.get("payload", "true").lower() == "true"
        self.names = [f.strip().split()[0] for f in SCHEMA.split(",")]
        only = json.loads(options.get("only", "{}"))
        if unknown := set(only) - set(PUSHED):
            raise ValueError(f"no predicate on {sorted(unknown)}")
        self.wanted: dict[int, set] = {self.names.index(k): set(v) for k, v in only.items()}

    def partitions(self) -> list[WarcFile]:
        fs, root = file_system(self.path)
        info = fs.get_file_info(root)
        found = [info] if info.type == pafs.FileType.File else fs.get_file_info(pafs.FileSelector(root, allow_not_found=True))
        files = [x for x in found if x.type == pafs.FileType.File and x.path.endswith((".warc", ".warc.gz"))]
        return [WarcFile(x.path, x.size) for x in sorted(files, key=lambda x: -x.size)] or [WarcFile("", 0)]

    def read(self, partition: WarcFile) -> Iterator[tuple]:
        if not partition.path:
            return
        fs, _ = file_system(self.path)
        with fs.open_input_file(partition.path) as stream:
            source = _Bytes(stream)
            try:
                while source.need(2):
                    yield from self._gzip(source) if source.need(2)[:2] == b"\x1f\x8b" else self._plain(source)
            except (zlib.error, KeyError, ValueError, struct.error) as fault:
                raise ValueError(f"damaged archive {partition.path}: {fault}") from fault

    def _fits(self, row: list) -> bool:
        return all(row[at] in values for at, values in self.wanted.items())

    def _body(self, row: list, block: bytes) -> tuple:
        if row[1] == "response":
            row[8] = block[block.find(b"\r\n\r\n") + 4 :].decode("utf-8", "replace")
        return tuple(row)

    def _plain(self, source: _Bytes) -> Iterator[tuple]:
        n = 1 << 12
        while (end := source.need(n).find(b"\r\n\r\n")) < 0 and len(source.need(n)) >= n:
            n *= 2
        if end < 0:
            if source.take(len(source.need(n))).strip():
                raise ValueError("no record header")
            return
        head = parse_head(source.take(end + 4))
        row, length = head_row(head), int(head["content-length"])
        if not self._fits(row):
            source.skip(length + 4)
        elif not self.payload:
            source.skip(length + 4)
            yield tuple(row)
        else:
            block = source.take(length)
            if len(block) < length:
                raise ValueError("cut off inside a record")
            yield self._body(row, block)
            source.skip(4)

    def _gzip(self, source: _Bytes) -> Iterator[tuple]:
        fixed = source.need(24)
        member = None
        if fixed[3] & 4 and len(fixed) >= 24 and fixed[12:14] == b"sl":
            member = struct.unpack("<I", fixed[16:20])[0]
        z = zlib.decompressobj(31)
        if member:
            packed = source.need(min(member, 4096))[: min(member, 4096)]
            plain = z.decompress(packed, 2048)
            while (end := plain.find(b"\r\n\r\n")) < 0 and z.unconsumed_tail:
                plain += z.decompress(z.unconsumed_tail, 4096)
            if end < 0:
                z, plain = zlib.decompressobj(31), b""
                plain = z.decompress(source.need(member)[:member])
                end = plain.find(b"\r\n\r\n")
            head = parse_head(plain[: end + 4])
            row = head_row(head)
            if not self._fits(row):
                source.skip(member)
                return
            if not self.payload:
                source.skip(member)
                yield tuple(row)
                return
            plain = zlib.decompress(source.take(member), 31)
        else:
            plain, chunk = b"", source.need(1 << 16)
            while True:
                plain += z.decompress(chunk)
                if z.eof:
                    source.skip(len(chunk) - len(z.unused_data))
                    break
                source.skip(len(chunk))
                chunk = source.need(1 << 16)
                if not chunk:
                    raise ValueError("cut off inside a record")
            end = plain.find(b"\r\n\r\n")
            head = parse_head(plain[: end + 4])
            row = head_row(head)
            if not self._fits(row):
                return
            if not self.payload:
                yield tuple(row)
                return
        yield self._body(row, plain[end + 4 : end + 4 + int(head["content-length"])])


class PushdownWarcReader(WarcReader):
    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            name = f.attribute[0] if isinstance(f, (EqualTo, In)) and len(f.attribute) == 1 else None
            if name in PUSHED:
                values = {f.value} if isinstance(f, EqualTo) else set(f.value)
                at = self.names.index(name)
                self.wanted[at] = self.wanted[at] & values if at in self.wanted else values
            else:
                yield f


class WarcDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> WarcReader:
        kind = PushdownWarcReader if self.options.get("pushdown", "false").lower() == "true" else WarcReader
        return kind(dict(self.options))

    def writer(self, schema: StructType, overwrite: bool) -> WarcWriter:
        return WarcWriter(dict(self.options), schema)
