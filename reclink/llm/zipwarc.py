"""Web archives packed in ZIP files: written by ranges of pages, read without extraction.

A package is a ZIP file with stored (uncompressed) members: ``archive/data.warc.gz``, one
gzip member per WARC record, and ``indexes/index.cdxj``, one line per record with its
offset and length.  The reader parses the central directory (with its ZIP64 forms),
finds the archive and index members, and reads any record by its byte range.

Of pages with equal payloads of at least `least` bytes the one with the smallest page_id
is written as a response and the others as revisits of it.  Only digests that occur twice
or more are kept for that; they are broadcast if they are few and joined by a shuffle
otherwise; payloads are never shuffled in the first case.

A null html is an empty payload; empty and short payloads are responses.  Rows that
repeat the smallest page_id of a group are responses too.  A null page_id counts as
larger than any other and is kept as null.  Null urls leave out the target.  Empty tables
give no package and no row; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import struct
import zlib
from collections.abc import Iterator
from urllib.parse import quote, urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import AtomicWriter, SharedFile, bounded, fresh_uri, materialise, tidy

LEAST = 100
PACKAGE_BYTES = 1 << 30
BROADCAST_ROWS = 300_000
ARCHIVE, INDEX = "archive/data.warc.gz", "indexes/index.cdxj"
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"


# ---------------------------------------------------------------- ZIP
class ZipWriter:
    """Appends stored members; sizes follow each member in a data descriptor, so nothing is
    written twice.  `zip64` forces the ZIP64 forms, which large members need."""

    def __init__(self, out, zip64: bool = False):
        self.out, self.zip64, self.members = out, zip64, []

    def begin(self, name: str) -> None:
        raw = name.encode()
        self._name, self._at, self._size, self._crc = raw, self.out.position, 0, 0
        extra = struct.pack("<HHQQ", 1, 16, 0, 0)
        self.out.write(struct.pack("<IHHHHHIIIHH", 0x04034B50, 45, 0x0808, 0, 0, 0x21, 0, 0xFFFFFFFF, 0xFFFFFFFF, len(raw), len(extra)) + raw + extra)

    def write(self, data: bytes) -> None:
        self.out.write(data)
        self._size += len(data)
        self._crc = zlib.crc32(data, self._crc)

    def end(self) -> None:
        self.out.write(struct.pack("<IIQQ", 0x08074B50, self._crc, self._size, self._size))
        self.members.append((self._name, self._at, self._size, self._crc))

    def close(self) -> None:
        start = self.out.position
        for name, at, size, crc in self.members:
            wide = self.zip64 or max(at, size) >= 0xFFFFFFFF
            extra = struct.pack("<HHQQQ", 1, 24, size, size, at) if wide else b""
            short = 0xFFFFFFFF if wide else size
            self.out.write(struct.pack("<IHHHHHHIIIHHHHHII", 0x02014B50, 45, 45, 0x0808, 0, 0, 0x21, crc, short, short, len(name), len(extra), 0, 0, 0, 0, 0xFFFFFFFF if wide else at) + name + extra)
        length, n = self.out.position - start, len(self.members)
        wide = self.zip64 or max(start, length) >= 0xFFFFFFFF or n >= 0xFFFF
        if wide:
            at = self.out.position
            self.out.write(struct.pack("<IQHHIIQQQQ", 0x06064B50, 44, 45, 45, 0, 0, n, n, length, start))
            self.out.write(struct.pack("<IIQI", 0x07064B50, 0, at, 1))
        few, small, low = (0xFFFF, 0xFFFFFFFF, 0xFFFFFFFF) if wide else (n, length, start)
        self.out.write(struct.pack("<IHHHHIIH", 0x06054B50, 0, 0, few, few, small, low, 0))


class ZipReader:
    """Members of a ZIP file by byte range: name -> (method, offset of the data, size)."""

    def __init__(self, file: SharedFile):
        self.file = file
        tail_at = max(0, file.size - 65557)
        tail = file.read_at(tail_at, file.size - tail_at)
        at = tail.rfind(b"PK\x05\x06")
        if at < 0:
            raise ValueError("no end of central directory")
        n, length, start = struct.unpack_from("<HII", tail, at + 10)
        if n == 0xFFFF or 0xFFFFFFFF in (length, start):
            if tail[at - 20 : at - 16] == b"PK\x06\x07":
                (where,) = struct.unpack_from("<Q", tail, at - 12)
                n, length, start = struct.unpack_from("<QQQ", file.read_at(where, 56), 32)
        directory, at = file.read_at(start, length), 0
        self.members: dict[str, tuple[int, int, int]] = {}
        for _ in range(n):
            if directory[at : at + 4] != b"PK\x01\x02":
                raise ValueError("broken central directory")
            method, crc, packed, size, n_name, n_extra, n_comment = struct.unpack_from("<H4xIIIHHH", directory, at + 10)
            (local,) = struct.unpack_from("<I", directory, at + 42)
            name = directory[at + 46 : at + 46 + n_name].decode("utf-8", "replace")
            extra = directory[at + 46 + n_name : at + 46 + n_name + n_extra]
            packed, local = self._wide(extra, size, packed, local)
            self.members[name] = (method, local, packed)
            at += 46 + n_name + n_extra + n_comment

    @staticmethod
    def _wide(extra: bytes, size: int, packed: int, local: int) -> tuple[int, int]:
        at = 0
        while at + 4 <= len(extra):
            kind, length = struct.unpack_from("<HH", extra, at)
            if kind == 1:
                fields = iter(struct.unpack_from(f"<{length // 8}Q", extra, at + 4))
                if size == 0xFFFFFFFF:
                    next(fields)
                packed = next(fields) if packed == 0xFFFFFFFF else packed
                local = next(fields) if local == 0xFFFFFFFF else local
            at += 4 + length
        return packed, local

    def span(self, name: str) -> tuple[int, int]:
        """(offset, length) of the bytes of a stored member in the file."""
        method, local, size = self.members[name]
        if method != 0:
            raise ValueError(f"{name} is compressed")
        n_name, n_extra = struct.unpack_from("<HH", self.file.read_at(local + 26, 4))
        return local + 30 + n_name + n_extra, size


# ---------------------------------------------------------------- WARC records
def _clean(url: str) -> str:
    return quote(url, safe="!#$%&'()*+,/:;=?@[]~-._")


def _record_id(page_id: int | None) -> str:
    return f"<urn:page:{'null' if page_id is None else page_id}>"


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, original: int | None) -> bytes:
    """A response record, or a revisit of page `original`."""
    lines = ["WARC/1.1", f"WARC-Type: {'response' if original is None else 'revisit'}", f"WARC-Record-ID: {_record_id(page_id)}", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {_clean(url)}")
    lines += [f"WARC-Payload-Digest: sha256:{digest}", f"X-Payload-Length: {len(payload)}"]
    body = HTTP
    if original is None:
        body += payload
    else:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {_record_id(original)}"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """(headers in lower case, payload without its HTTP head)."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    headers = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    headers = {k.lower(): v for k, v in headers.items()}
    body = rest[: int(headers["content-length"])]
    return headers, body.partition(b"\r\n\r\n")[2]


def _sort_key(url: str | None) -> str:
    """Host labels reversed, then the path, as index lines are sorted."""
    parts = urlsplit(_clean(url or ""))
    host = ",".join(reversed((parts.hostname or "").split(".")))
    return f"{host}){parts.path}{'?' + parts.query if parts.query else ''}".replace(" ", "%20")


class PackageWriter:
    def __init__(self, uri: str, zip64: bool = False):
        self.uri, self.out = uri, AtomicWriter(uri)
        self.zip = ZipWriter(self.out, zip64)
        self.zip.begin(ARCHIVE)
        self.lines: list[str] = []
        self.bytes = 0

    def add(self, page_id, url, payload: bytes, digest: str, original) -> None:
        packer = zlib.compressobj(1, zlib.DEFLATED, 31)
        raw = packer.compress(record(page_id, url, payload, digest, original)) + packer.flush()
        self.zip.write(raw)
        about = {"url": url, "digest": f"sha256:{digest}", "offset": self.bytes, "length": len(raw), "filename": ARCHIVE.rpartition("/")[2]}
        self.lines.append(f"{_sort_key(url)} {DATE[:4]}0101000000 {json.dumps(about)}\n")
        self.bytes += len(raw)

    def close(self) -> None:
        self.zip.end()
        self.zip.begin(INDEX)
        self.zip.write("".join(sorted(self.lines)).encode("utf-8", "replace"))
        self.zip.end()
        self.zip.close()
        self.out.commit()


class PackageReader:
    """Records of a package; `near` bytes at most are read at once."""

    def __init__(self, uri: str, near: int = 4 << 20):
        self.file, self.near = SharedFile(uri), near
        self.zip = ZipReader(self.file)
        self.base, self.length = self.zip.span(ARCHIVE)

    def index(self) -> list[tuple[int, int]]:
        """(offset, length) of each record in the archive, ascending."""
        at, size = self.zip.span(INDEX)
        found = (json.loads(line.split(" ", 2)[2]) for line in self.file.read_at(at, size).decode().splitlines())
        return sorted((int(x["offset"]), int(x["length"])) for x in found)

    def record(self, offset: int, length: int) -> tuple[dict[str, str], bytes]:
        return parse(zlib.decompress(self.file.read_at(self.base + offset, length), 31))

    def records(self) -> Iterator[tuple[dict[str, str], bytes]]:
        spans, at = self.index(), 0
        while at < len(spans):
            to, first = at + 1, spans[at][0]
            while to < len(spans) and sum(spans[to]) - first <= self.near:
                to += 1
            block = self.file.read_at(self.base + first, sum(spans[to - 1]) - first)
            for offset, length in spans[at:to]:
                yield parse(zlib.decompress(block[offset - first : offset - first + length], 31))
            at = to


# ---------------------------------------------------------------- Spark
def write_packages(pages: DataFrame, folder: str, least: int = LEAST, broadcast_rows: int = BROADCAST_ROWS, package_bytes: int = PACKAGE_BYTES) -> DataFrame:
    """Write pages (page_id, url, html) as packages; returns their table: uri, records."""
    payload = F.encode(F.coalesce(F.col("html"), F.lit("")), "UTF-8")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    long_ones = rows.where(F.octet_length("payload") >= least)
    groups = long_ones.groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    groups = materialise(groups.select(F.col("digest").alias("known"), "first"), "digests")
    same = (F.col("digest") == F.col("known")) & (F.octet_length("payload") >= least)
    marked = rows.join(bounded(groups, broadcast_rows), same, "left")
    original = F.when(~F.col("first").eqNullSafe(F.col("page_id")), F.col("first"))

    def write(batches):
        from pyspark import TaskContext

        part, number, package = TaskContext.get().partitionId(), 0, None
        kind = pa.schema([("uri", pa.string()), ("records", pa.int64())])
        done = lambda p: pa.RecordBatch.from_pylist([{"uri": p.uri, "records": len(p.lines)}], schema=kind)
        for batch in batches:
            for page_id, url, raw, digest, first in zip(*(batch.column(k).to_pylist() for k in range(5))):
                package = package or PackageWriter(f"{folder}/part-{part:06d}-{number:04d}.wacz")
                package.add(page_id, url, raw, digest, first)
                if package.bytes >= package_bytes:
                    package.close()
                    yield done(package)
                    package, number = None, number + 1
        if package:
            package.close()
            yield done(package)

    table = marked.select("page_id", "url", "payload", "digest", original.alias("original")).mapInArrow(tidy(write), "uri string, records long")
    return materialise(table, "packages")


def read_packages(packages: DataFrame) -> DataFrame:
    """Per record of the packages: page_id, url, payload_bytes, payload_digest (of responses
    computed from what was read), record_type, refers_to.  Each package is a task of its own:
    the count is given, as tasks would else be joined by the size of their few names."""
    kind = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])
    number = lambda text: None if text == "<urn:page:null>" else int(text[10:-1])

    def read(batches):
        for batch in batches:
            for uri in batch.column(0).to_pylist():
                out = []
                for headers, payload in PackageReader(uri).records():
                    revisit = headers["warc-type"] == "revisit"
                    out.append(
                        {
                            "page_id": number(headers["warc-record-id"]),
                            "url": headers.get("warc-target-uri"),
                            "payload_bytes": int(headers["x-payload-length"]) if revisit else len(payload),
                            "payload_digest": headers["warc-payload-digest"][7:] if revisit else hashlib.sha256(payload).hexdigest(),
                            "record_type": headers["warc-type"],
                            "refers_to": number(headers["warc-refers-to"]) if revisit else None,
                        }
                    )
                    if len(out) == 2000:
                        yield pa.RecordBatch.from_pylist(out, schema=kind)
                        out = []
                yield pa.RecordBatch.from_pylist(out, schema=kind)

    spread = packages.select("uri").repartition(max(1, packages.count()))
    return spread.mapInArrow(tidy(read), "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive(pages: DataFrame) -> DataFrame:
    """Write pages to the shared folder as packages and read them back."""
    return read_packages(write_packages(pages, fresh_uri(pages.sparkSession, "packages")))
