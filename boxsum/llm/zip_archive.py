"""Web archives packaged as ZIP files: stored members, a record index, and reads of single records by range.

A package holds an archive of WARC records (each its own gzip member), an index of them (one line a record with
its offset and length in the archive) and a description. Members are stored, not deflated, so a record's place
in the file is its member's place plus its offset. Reading takes the end record, the ZIP64 end record where
sizes or offsets need it, and the central directory; then the index; then each record by a range of the file.
Nothing is unpacked to disk and no member is read whole but the index.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import json
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from typing import BinaryIO

LIMIT_16, LIMIT_32 = 0xFFFF, 0xFFFFFFFF
ARCHIVE, INDEX, DESCRIPTION = "archive/data.warc.gz", "indexes/index.cdxj", "datapackage.json"


class ArchiveError(ValueError):
    pass


def digest(payload: bytes) -> str:
    """Bare base32 SHA-1, upper case."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


# -- ZIP ---------------------------------------------------------------------------------------------------


def write_zip(members: list[tuple[str, bytes]], force_zip64: bool = False) -> bytes:
    """A ZIP file of stored members; ZIP64 fields where a number needs them (or always, if forced)."""
    out, central, at = [], [], 0
    for name, data in members:
        raw, crc = name.encode(), zlib.crc32(data)
        big = force_zip64 or len(data) >= LIMIT_32 or at >= LIMIT_32
        size = LIMIT_32 if big else len(data)
        extra = struct.pack("<HHQQ", 1, 16, len(data), len(data)) if big else b""
        local = struct.pack("<4sHHHHHIIIHH", b"PK\3\4", 45 if big else 20, 0x800, 0, 0, 0x21, crc, size, size, len(raw), len(extra)) + raw + extra
        extra_c = struct.pack("<HHQQQ", 1, 24, len(data), len(data), at) if big else b""
        central.append(struct.pack("<4sHHHHHHIIIHHHHHII", b"PK\1\2", 45 if big else 20, 45 if big else 20, 0x800, 0, 0, 0x21, crc, size, size, len(raw), len(extra_c), 0, 0, 0, 0, LIMIT_32 if big else at) + raw + extra_c)
        out += [local, data]
        at += len(local) + len(data)
    directory = b"".join(central)
    n, big = len(members), force_zip64 or at >= LIMIT_32 or len(members) >= LIMIT_16
    out.append(directory)
    if big:
        out.append(struct.pack("<4sQHHIIQQQQ", b"PK\6\6", 44, 45, 45, 0, 0, n, n, len(directory), at))
        out.append(struct.pack("<4sIQI", b"PK\6\7", 0, at + len(directory), 1))
    out.append(struct.pack("<4sHHHHIIH", b"PK\5\6", 0, 0, LIMIT_16 if big else n, LIMIT_16 if big else n, LIMIT_32 if big else len(directory), LIMIT_32 if big else at, 0))
    return b"".join(out)


@dataclass
class Member:
    name: str
    method: int
    size: int
    crc: int
    header: int  # offset of the local header


class ZipReader:
    """Members of a ZIP file that can be read at any offset; `source` has seek and read."""

    def __init__(self, source: BinaryIO, size: int):
        self.source, self.size = source, size
        self.members = {m.name: m for m in self._directory()}

    def at(self, offset: int, n: int) -> bytes:
        if offset < 0 or offset + n > self.size:
            raise ArchiveError("beyond the end of the file")
        self.source.seek(offset)
        data = self.source.read(n)
        if len(data) != n:
            raise ArchiveError("cut off")
        return data

    def _end(self) -> tuple[int, int, int]:
        """Entries, size and offset of the central directory."""
        n = min(self.size, 22 + LIMIT_16)
        tail = self.at(self.size - n, n)
        at = tail.rfind(b"PK\5\6")
        while at >= 0:
            if at + 22 <= n and at + 22 + struct.unpack_from("<H", tail, at + 20)[0] == n:
                break
            at = tail.rfind(b"PK\5\6", 0, at)
        if at < 0:
            raise ArchiveError("no end record")
        entries, length, offset = struct.unpack_from("<HII", tail, at + 10)
        if LIMIT_16 in (entries,) or LIMIT_32 in (length, offset):
            place = self.size - n + at - 20
            if place >= 0 and (locator := self.at(place, 20))[:4] == b"PK\6\7":
                record = self.at(struct.unpack_from("<Q", locator, 8)[0], 56)
                if record[:4] != b"PK\6\6":
                    raise ArchiveError("no ZIP64 end record")
                entries, length, offset = struct.unpack_from("<QQQ", record, 32)
        return entries, length, offset

    def _directory(self) -> Iterator[Member]:
        entries, length, offset = self._end()
        raw, at = self.at(offset, length), 0
        for _ in range(entries):
            if raw[at : at + 4] != b"PK\1\2":
                raise ArchiveError("damaged central directory")
            method, crc, packed, size, n_name, n_extra, n_comment, header = struct.unpack_from("<10xH4xIIIHHH8xI", raw, at)
            name = raw[at + 46 : at + 46 + n_name].decode()
            extra, end = at + 46 + n_name, at + 46 + n_name + n_extra
            while extra + 4 <= end:
                kind, n = struct.unpack_from("<HH", raw, extra)
                if kind == 1:  # the numbers that don't fit, in this order
                    field = extra + 4
                    if size == LIMIT_32:
                        size, field = struct.unpack_from("<Q", raw, field)[0], field + 8
                    if packed == LIMIT_32:
                        packed, field = struct.unpack_from("<Q", raw, field)[0], field + 8
                    if header == LIMIT_32:
                        header = struct.unpack_from("<Q", raw, field)[0]
                extra += 4 + n
            yield Member(name, method, size, crc, header)
            at += 46 + n_name + n_extra + n_comment

    def start(self, member: Member) -> int:
        """Where a stored member's bytes begin."""
        if member.method:
            raise ArchiveError(f"{member.name} isn't stored")
        head = self.at(member.header, 30)
        if head[:4] != b"PK\3\4":
            raise ArchiveError("no local header")
        return member.header + 30 + sum(struct.unpack_from("<HH", head, 26))

    def read(self, member: Member) -> bytes:
        data = self.at(self.start(member), member.size)
        if zlib.crc32(data) != member.crc:
            raise ArchiveError(f"checksum of {member.name}")
        return data


# -- WARC --------------------------------------------------------------------------------------------------


@dataclass
class Record:
    kind: str  # response or revisit
    page: int | None
    uri: str
    payload: bytes
    payload_digest: str
    payload_bytes: int
    refers_to: int | None = None


def record_id(page: int | None) -> str:
    return f"<urn:page:{'' if page is None else page}>"


def clean(value: str) -> str:
    """A header's value on one line, exactly recoverable."""
    return value.encode("unicode_escape").decode()


def write_record(r: Record) -> bytes:
    """One gzip member. A revisit has no payload, but the length and digest of the one it stands for."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % r.payload_bytes
    body = http + (r.payload if r.kind == "response" else b"")
    head = ["WARC/1.1", f"WARC-Type: {r.kind}", f"WARC-Record-ID: {record_id(r.page)}", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Target-URI: {clean(r.uri)}", f"WARC-Payload-Digest: sha1:{r.payload_digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    if r.kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(r.refers_to)}"]
    return gzip.compress("\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n", 1, mtime=0)


def read_record(raw: bytes) -> Record:
    """A record from its gzip member, its lengths and digest tested."""
    data = gzip.decompress(raw)
    top, _, rest = data.partition(b"\r\n\r\n")
    lines = top.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ArchiveError("no record")
    head = dict(x.split(": ", 1) for x in lines[1:])
    body = rest[: int(head["Content-Length"])]
    if rest[len(body) :] != b"\r\n\r\n":
        raise ArchiveError("record's length")
    http, _, payload = body.partition(b"\r\n\r\n")
    size = int(next(x for x in http.decode().split("\r\n") if x.startswith("Content-Length: ")).split(": ")[1])
    kind, stated = head["WARC-Type"], head["WARC-Payload-Digest"].removeprefix("sha1:")
    if kind == "response" and (len(payload) != size or digest(payload) != stated):
        raise ArchiveError("payload's digest")
    number = lambda s: int(x) if (x := s.removeprefix("<urn:page:").removesuffix(">")) else None
    uri = head["WARC-Target-URI"].encode().decode("unicode_escape")
    return Record(kind, number(head["WARC-Record-ID"]), uri, payload, stated, size, number(head["WARC-Refers-To"]) if kind == "revisit" else None)


class PackageWriter:
    """Collects records; `close` gives the package."""

    def __init__(self):
        self.parts: list[bytes] = []
        self.lines: list[str] = []
        self.size = 0

    def add(self, record: Record) -> None:
        raw = write_record(record)
        self.lines.append(json.dumps({"url": record.uri, "digest": record.payload_digest, "kind": record.kind, "offset": self.size, "length": len(raw)}))
        self.parts.append(raw)
        self.size += len(raw)

    def close(self, force_zip64: bool = False) -> bytes:
        about = json.dumps({"profile": "data-package", "resources": [{"path": ARCHIVE, "bytes": self.size, "records": len(self.lines)}]}).encode()
        return write_zip([(ARCHIVE, b"".join(self.parts)), (INDEX, "\n".join(self.lines).encode()), (DESCRIPTION, about)], force_zip64)


def records(source: BinaryIO, size: int) -> Iterator[Record]:
    """All records of a package, each by the range that the index gives."""
    reader = ZipReader(source, size)
    archives = [m for name, m in reader.members.items() if name.startswith("archive/")]
    indexes = [m for name, m in reader.members.items() if name.startswith("indexes/")]
    if len(archives) != 1 or not indexes:
        raise ArchiveError("no archive or index")
    start = reader.start(archives[0])
    for m in indexes:
        for line in filter(None, reader.read(m).decode().split("\n")):
            at = json.loads(line)
            if at["offset"] + at["length"] > archives[0].size:
                raise ArchiveError("index points beyond the archive")
            yield read_record(reader.at(start + at["offset"], at["length"]))
