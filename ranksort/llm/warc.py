"""WARC archives: deduplicating writer and salvage reader.

The writer stores one record a row, each a gzip member of its own.  Of rows with equal payloads of
``min_revisit_bytes`` or more, those with the smallest id carry the payload and the others are
revisits that name it.  Each task writes files of its own, under names that no other attempt has;
the manifest of files that the finished tasks return is what readers go by, so files of lost or
repeated attempts are never read.

The reader checks each record: gzip CRC and length, version line, Content-Length, closing blank
lines, block and payload digests.  After a failed check it searches on, byte by byte, for the next
gzip member that opens a record or the next version line, goes on from there, and logs the bytes
between as a quarantined gap with its reason.  Blocks and members are read through a window and
digested part by part, so there is no limit on a record's length (``max_record_bytes`` sets one);
memory holds the headers, and the payload of a record only where it is asked for.

Defined results: a null payload is empty; a null id sorts last and its record has an id of its own;
equal ids with equal payloads are all responses; a null url has no target line; an empty table gives
no files and no records; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from itertools import chain

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import Files, materialize, scratch

# What the format prescribes.
VERSION = b"WARC/1.1"
END = b"\r\n\r\n"
MANDATORY = ("warc-record-id", "warc-type", "warc-date", "content-length")
MEMBER = b"\x1f\x8b\x08"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

_OPENING = re.compile(rb"WARC/[0-9]\.[0-9]\r\n")
_START = re.compile(rb"\x1f\x8b\x08|WARC/[0-9]\.[0-9]\r\n")
_CHUNK = 1 << 20
#: Bytes that are unpacked or digested at once, and of payloads that are held until a member proves whole.
_PART, _HELD = 1 << 16, 32 << 20
_ID = "urn:x-page:"


def file_system(uri: str) -> tuple[pafs.FileSystem, str]:
    """pyarrow's file system for a path or URI."""
    if uri.startswith("file:"):
        uri = "/" + uri[5:].lstrip("/")
    return (pafs.LocalFileSystem(), uri) if uri.startswith("/") else pafs.FileSystem.from_uri(uri)


# --- writing ---


def _sha(data: bytes) -> str:
    return f"sha256:{hashlib.sha256(data).hexdigest()}"


def record(kind: str, record_id: str, target: str | None, payload: bytes | None, digest: str, length: int, refers_to: str | None = None) -> bytes:
    """One record's bytes, not compressed; ``payload`` None for a revisit, which keeps the HTTP head alone."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {length}\r\n\r\n".encode()
    block = http + (payload or b"")
    head = [VERSION.decode(), f"WARC-Type: {kind}", f"WARC-Record-ID: <{record_id}>", "WARC-Date: 1970-01-01T00:00:00Z"]
    if target is not None:
        head.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", target))
    if refers_to is not None:
        head += [f"WARC-Refers-To: <{refers_to}>", f"WARC-Profile: {REVISIT_PROFILE}"]
    head += [f"WARC-Payload-Digest: sha256:{digest}", f"WARC-Block-Digest: {_sha(block)}", "Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + END + block + END


def member(data: bytes, level: int = 6) -> bytes:
    """A gzip member."""
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress(data) + packer.flush()


def plan_records(pages: DataFrame, *, id: str = "page_id", url: str = "url", payload: str = "html", min_revisit_bytes: int = 100, max_broadcast: int = 200_000, salts: int = 16) -> DataFrame:
    """(id, url, payload, digest, length, refers_to): what is to be written; refers_to is null for responses.

    Digests and ids alone are shuffled, to find the groups of copies.  Payloads stay where they were read
    while there are at most ``max_broadcast`` such groups (counted), a row of some 60 bytes each; beyond,
    rows meet their group by digest and one of ``salts`` parts, and rows that can have no copy by their id.
    """
    rows = pages.select(F.col(id).cast("long").alias("id"), F.col(url).alias("url"), F.coalesce(F.col(payload), F.lit("")).alias("payload"))
    rows = rows.withColumns({"digest": F.sha2("payload", 256), "length": F.octet_length("payload").cast("long")})
    long_enough = F.col("length") >= min_revisit_bytes
    groups = rows.where(long_enough).groupBy(F.unhex("digest").alias("key")).agg(F.min("id").alias("first"), F.count("*").alias("copies"))
    known = materialize(groups.where("copies > 1").select("key", "first"), "warc-copies")
    keyed = rows.withColumn("key", F.when(long_enough, F.unhex("digest")).otherwise(F.unhex(F.hex("id"))))
    if known.limit(max_broadcast + 1).count() <= max_broadcast:
        copied = keyed.join(F.broadcast(known), "key", "left")
    else:
        part = F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int")
        copied = keyed.withColumn("salt", part).join(known.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))), ["key", "salt"], "left")
    later = (F.col("first") < F.col("id")) | (F.col("id").isNull() & F.col("first").isNotNull())
    return copied.select("id", "url", F.when(later, None).otherwise(F.col("payload")).alias("payload"), "digest", "length", F.when(later, F.col("first")).alias("refers_to"))


def write_archives(planned: DataFrame, folder: str, *, roll_bytes: int = 64 << 20) -> DataFrame:
    """Write planned records to archives in ``folder``; the manifest: (file, records, bytes)."""
    Files(planned.sparkSession, folder).make(folder)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, base = file_system(folder)
        done, out, name, count, size = [], None, "", 0, 0

        def close() -> None:
            out.close()
            done.append({"file": f"{folder}/{name}", "records": count, "bytes": size})

        for batch in batches:
            for row in batch.to_pylist():
                if out is None:
                    name, count, size = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    out = system.open_output_stream(f"{base}/{name}", compression=None)
                own = _ID + (str(row["id"]) if row["id"] is not None else f"null:{uuid.uuid4().hex}")
                revisit = row["payload"] is None
                refers = f"{_ID}{row['refers_to']}" if revisit else None
                data = member(record("revisit" if revisit else "response", own, row["url"], None if revisit else row["payload"].encode(), row["digest"], row["length"], refers))
                out.write(data)
                count, size = count + 1, size + len(data)
                if size >= roll_bytes:
                    close()
                    out = None
        if out is not None:
            close()
        kind = pa.schema([("file", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())])
        yield pa.RecordBatch.from_pylist(done, kind)

    return materialize(planned.mapInArrow(write, "file string, records long, bytes long"), "warc-manifest")


# --- reading ---


@dataclass
class Record:
    """A record that passed every check; ``payload`` is the block without its HTTP head, None if it was not asked for."""

    start: int
    end: int
    headers: dict[str, str]
    head: bytes
    payload_bytes: int
    payload: bytes | None

    @property
    def http(self) -> dict[str, str]:
        """The fields of the HTTP head; lines without a colon are passed over."""
        return _fields([line for line in self.head.split(b"\r\n")[1:] if b":" in line])


@dataclass
class Gap:
    """Bytes that no valid record covers."""

    start: int
    end: int
    reason: str


class Damaged(Exception):
    """A record failed a check."""


@dataclass
class _Window:
    """Random access to a file in chunks; keeps the last few."""

    file: object
    size: int
    _held: dict[int, bytes] = field(default_factory=dict)

    def _chunk(self, k: int) -> bytes:
        if k not in self._held:
            if len(self._held) > 8:
                self._held.pop(next(iter(self._held)))
            self.file.seek(k * _CHUNK)
            self._held[k] = self.file.read(_CHUNK)
        return self._held[k]

    def read(self, start: int, length: int) -> bytes:
        end = min(self.size, start + length)
        parts = []
        while start < end:
            k, at = divmod(start, _CHUNK)
            part = self._chunk(k)[at : at + end - start]
            if not part:
                break
            parts.append(part)
            start += len(part)
        return b"".join(parts)

    def find(self, pattern: re.Pattern, start: int, overlap: int = 16) -> int:
        """Where the pattern next occurs, -1 if nowhere."""
        while start < self.size:
            data = self.read(start, _CHUNK)
            if found := pattern.search(data):
                return start + found.start()
            if start + len(data) >= self.size:
                return -1
            start += max(1, len(data) - overlap)
        return -1


def _fields(lines: list[bytes]) -> dict[str, str]:
    out: dict[str, str] = {}
    name = ""
    for line in lines:
        if line[:1] in (b" ", b"\t") and name:  # a folded line goes on
            out[name] += " " + line.strip().decode("utf-8", "replace")
            continue
        head, colon, value = line.partition(b":")
        if not colon:
            raise Damaged("a header line without a colon")
        name = head.strip().decode("utf-8", "replace").lower()
        out[name] = value.strip().decode("utf-8", "replace")
    return out


class _Plain:
    """A file's bytes from a place on."""

    def __init__(self, window: _Window, at: int):
        self.window, self.at = window, at

    def more(self) -> bytes:
        part = self.window.read(self.at, _PART)
        self.at += len(part)
        return part


class _Member:
    """The unpacked bytes of the gzip member at a place."""

    def __init__(self, window: _Window, at: int):
        self.window, self.place, self.rest, self.unpacker = window, at, b"", zlib.decompressobj(31)

    def more(self) -> bytes:
        try:
            while not self.unpacker.eof:
                out = self.unpacker.decompress(self.rest, _PART)
                self.rest = self.unpacker.unconsumed_tail
                if out:
                    return out
                if not self.rest and not self.unpacker.eof:
                    self.rest = self.window.read(self.place, _PART)
                    self.place += len(self.rest)
                    if not self.rest:
                        raise Damaged("a member cut short")
        except zlib.error as error:
            raise Damaged(f"gzip: {error}") from None
        return b""

    @property
    def end(self) -> int:
        return self.place - len(self.unpacker.unused_data)


class _Reader:
    """Lines and stretches of a source of bytes."""

    def __init__(self, source: _Plain | _Member):
        self.source, self.held, self.taken = source, b"", 0

    def ended(self) -> bool:
        if not self.held:
            self.held = self.source.more()
        return not self.held

    def line(self, limit: int | None) -> bytes:
        """Up to the next line break, which is taken too."""
        parts, seen = [self.held], len(self.held)
        while (b"\r\n" not in parts[-1]) and not (len(parts) > 1 and parts[-2][-1:] == b"\r" and parts[-1][:1] == b"\n"):
            part = self.source.more()
            if not part:
                raise Damaged("headers without an end")
            parts.append(part)
            seen += len(part)
            if limit is not None and seen > limit + 2 * _PART:
                raise Damaged("longer than the limit")
        line, _, self.held = b"".join(parts).partition(b"\r\n")
        self.taken += len(line) + 2
        return line

    def stretch(self, count: int) -> Iterator[bytes]:
        """The next ``count`` bytes, in parts."""
        while count:
            if self.ended():
                raise Damaged("the block does not end where Content-Length says")
            part, self.held = self.held[:count], self.held[count:]
            count -= len(part)
            self.taken += len(part)
            yield part


def _digests(*said: str | None) -> list[tuple[str, object] | None]:
    """For each digest that a header names: its value, and the running digest."""
    out = []
    for text in said:
        method, _, value = (text or "").partition(":")
        out.append((value, hashlib.new(method.lower())) if method.lower() in ("sha1", "sha256") and value else None)
    return out


def _check_digest(known: tuple[str, object] | None, what: str) -> None:
    if known and known[0].lower() != known[1].hexdigest() and known[0].upper() != base64.b32encode(known[1].digest()).decode():
        raise Damaged(f"{what} digest does not match")


def _headers(reader: _Reader, limit: int | None) -> tuple[dict[str, str], int]:
    """The headers of the record that opens here, and its block's length; a line that is none ends the search at once."""
    if not _OPENING.match(reader.line(limit) + b"\r\n"):
        raise Damaged("no version line")
    lines: list[bytes] = []
    while line := reader.line(limit):
        if b":" not in line and not (line[:1] in (b" ", b"\t") and lines):
            raise Damaged("a header line without a colon")
        lines.append(line)
    headers = _fields(lines)
    if missing := [name for name in MANDATORY if not headers.get(name)]:
        raise Damaged(f"no {missing[0]}")
    length = headers["content-length"]
    if not length.isascii() or not length.isdigit():
        raise Damaged("no valid content-length")
    if limit is not None and int(length) > limit:
        raise Damaged("longer than the limit")
    return headers, int(length)


def _http_head(parts: Iterator[bytes]) -> tuple[bytes, bytes]:
    """The HTTP head that opens a block, empty if there is none, and what was read beyond it."""
    seen = bytearray()
    for part in parts:
        seen += part
        if not seen.startswith(b"HTTP/"[: len(seen)]):
            break
        if (cut := seen.find(END, max(0, len(seen) - len(part) - 3))) >= 0:
            return bytes(seen[: cut + len(END)]), bytes(seen[cut + len(END) :])
    return b"", bytes(seen)


def _block(reader: _Reader, headers: dict[str, str], length: int, keep: bool) -> tuple[bytes, int, bytes | None]:
    """HTTP head, length of the rest, and the rest if it is kept: checked against both digests part by part."""
    whole, rest = _digests(headers.get("warc-block-digest"), headers.get("warc-payload-digest"))
    parts = reader.stretch(length)
    head, first = _http_head(parts)
    if whole:
        whole[1].update(head)
    size, kept = 0, []
    for part in chain([first], parts):
        size += len(part)
        for known in filter(None, (whole, rest)):
            known[1].update(part)
        if keep:
            kept.append(part)
    if b"".join(reader.stretch(len(END))) != END:
        raise Damaged("the block does not end where Content-Length says")
    _check_digest(whole, "block")
    if headers.get("warc-type") == "response" and head:
        _check_digest(rest, "payload")
    return head, size, b"".join(kept) if keep else None


def _plain(window: _Window, at: int, limit: int | None, keep: bool) -> Iterator[Record]:
    """The uncompressed record at ``at``; its closing blank lines are looked at before its block."""
    reader = _Reader(_Plain(window, at))
    headers, length = _headers(reader, limit)
    if window.read(at + reader.taken + length, len(END)) != END:
        raise Damaged("the block does not end where Content-Length says")
    found = _block(reader, headers, length, keep)
    yield Record(at, at + reader.taken, headers, *found)


def _packed(window: _Window, at: int, limit: int | None, keep: bool) -> Iterator[Record]:
    """All records of the gzip member at ``at``, whose end is set when the last has been read."""
    source = _Member(window, at)
    reader = _Reader(source)
    if reader.ended():
        raise Damaged("an empty member")
    while len(reader.held) < 10 and (part := source.more()):
        reader.held += part
    if not _OPENING.match(reader.held):
        raise Damaged("a member that holds no record")
    while not reader.ended():
        headers, length = _headers(reader, limit)
        yield Record(at, source.end, headers, *_block(reader, headers, length, keep))
    yield Record(at, source.end, {}, b"", 0, None)


def _member(window: _Window, at: int, limit: int | None, keep: bool) -> tuple[int, Iterator[Record]]:
    """The member's end and its records, of which none counts if one is damaged.

    They are held while their payloads are short; a longer member is read a second time.
    """
    held, size = [], 0
    for found in _packed(window, at, limit, keep):
        size += len(found.payload or b"") + 1000
        held = held if size <= _HELD else held[-1:]
        held.append(found)
    end = held.pop().end
    records = iter(held) if size <= _HELD else (r for r in _packed(window, at, limit, keep) if r.headers)
    return end, (replace(r, end=end) for r in records)


def salvage(file, size: int, max_record_bytes: int | None = None, keep: bool = True) -> Iterator[Record | Gap]:
    """Records and gaps of an archive, in order; every byte is in one or the other.  ``keep``: with payloads."""
    window, at, lost, reason = _Window(file, size), 0, -1, ""
    while at < size:
        begin = window.read(at, 10)
        try:
            if begin.startswith(MEMBER):
                end, found = _member(window, at, max_record_bytes, keep)
            elif _OPENING.match(begin):
                whole = list(_plain(window, at, max_record_bytes, keep))
                end, found = whole[0].end, iter(whole)
            else:
                raise Damaged("neither a member nor a version line")
        except Damaged as damage:
            if lost < 0:
                lost, reason = at, str(damage)
            onward = window.find(_START, at + 1)
            at = size if onward < 0 else onward
            continue
        if lost >= 0:
            yield Gap(lost, at, reason)
            lost = -1
        yield from found
        at = end
    if lost >= 0:
        yield Gap(lost, size, reason)


_READ = "file string, start long, end long, gap string, warc_type string, record_id string, target_uri string, refers_to string, payload_digest string, payload_bytes long, payload binary"


def read_archives(spark: SparkSession, manifest: DataFrame, *, with_payload: bool = True, max_record_bytes: int | None = None) -> DataFrame:
    """One row a record, or a quarantined gap (``gap`` is its reason), of every file in the manifest's column ``file``.

    payload_bytes is the HTTP head's length, which a revisit keeps of the payload that it leaves out.
    """
    files = manifest.select("file").where("file is not null")
    schema = pa.schema([(n, {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[t]) for n, t in (c.split() for c in _READ.split(", "))])

    def bare(value: str | None) -> str | None:
        return value.strip("<>") if value else None

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name in batch["file"].to_pylist():
                system, path = file_system(name)
                with system.open_input_file(path) as file:
                    rows, held = [], 0
                    for found in salvage(file, file.size(), max_record_bytes, with_payload):
                        row = {"file": name, "start": found.start, "end": found.end}
                        if isinstance(found, Gap):
                            row["gap"] = found.reason
                        else:
                            h, length = found.headers, found.http.get("content-length", "") if found.head else ""
                            row |= {"warc_type": h.get("warc-type"), "record_id": bare(h.get("warc-record-id")), "target_uri": h.get("warc-target-uri"), "refers_to": bare(h.get("warc-refers-to")),
                                    "payload_digest": h.get("warc-payload-digest"), "payload_bytes": int(length) if length.isdigit() else found.payload_bytes, "payload": found.payload}
                            held += len(found.payload or b"")
                        rows.append(row)
                        if held > 4 << 20 or len(rows) >= 5000:
                            yield pa.RecordBatch.from_pylist(rows, schema)
                            rows, held = [], 0
                    if rows:
                        yield pa.RecordBatch.from_pylist(rows, schema)

    return files.repartition(max(1, files.count())).mapInArrow(read, _READ)


def archive_pages(pages: DataFrame, **columns: str) -> DataFrame:
    """Write pages to archives in a new shared folder; the manifest."""
    return write_archives(plan_records(pages, **columns), Files(pages.sparkSession, scratch(pages.sparkSession, "warc")).root)
