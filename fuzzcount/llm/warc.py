"""WARC archives: one gzip member per record, written and read as streams.

`write_archives` writes each partition's pages as a run of `.warc.gz` files in a folder that all
machines share, under a name of its own per attempt, so a repeated task leaves whole files only.
Of records with equal payloads of at least `MIN_SHARED` bytes the one with the smallest page id is a
response and the others are revisits that name it; smaller payloads are always responses.
`read_archives` walks such files in order: it inflates a member piece by piece, frames the record by its
content length, and verifies block and payload digests as the pieces come, so a long record is never held whole.

Edge cases: a null payload counts as empty; a page with a null id is a response; rows that repeat both
id and payload are each written, with the same type; an empty table leaves no archive and gives no rows.
A broken member, a short record or a digest that does not match raises an error that names the file.
"""

from __future__ import annotations

import hashlib
import os
import posixpath
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut, drop, new_folder

MIN_SHARED = 100
ROLL_BYTES = 128 << 20
CHUNK = 1 << 18
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

MANIFEST = "path string, records bigint, bytes bigint"
RECORDS = "page_id bigint, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, path string, at bigint"


def record_id(page_id: int | None, salt: str = "") -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{salt}')}>"


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """A whole WARC record; a revisit carries the HTTP head but no payload."""
    digest = hashlib.sha256(payload).hexdigest()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {DATE}"]
    if url:
        head.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if page_id is not None:
        head.append(f"Page-Id: {page_id}")
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(refers_to)}", f"Refers-To-Page-Id: {refers_to}"]
    head += [
        f"WARC-Payload-Digest: sha256:{digest}",
        f"WARC-Block-Digest: sha256:{hashlib.sha256(block).hexdigest()}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def open_store(uri: str) -> tuple[fs.FileSystem, str]:
    """The file system of a URI (local paths too) and the path in it."""
    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), os.path.abspath(uri)
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


class ArchiveWriter:
    """Rolls gzip members into files of about `ROLL_BYTES`; a file appears under its final name when whole."""

    def __init__(self, folder: str, roll_bytes: int = ROLL_BYTES):
        self.store, self.folder = open_store(folder)
        self.roll_bytes, self.stream = roll_bytes, None

    def add(self, data: bytes) -> dict | None:
        if self.stream is None:
            self.name = posixpath.join(self.folder, f"pages-{uuid.uuid4().hex}.warc.gz")
            self.store.create_dir(self.folder, recursive=True)
            self.stream = self.store.open_output_stream(self.name + ".part", compression=None)
            self.records = self.bytes = 0
        packer = zlib.compressobj(6, zlib.DEFLATED, 31)
        for at in range(0, len(data), CHUNK):
            self.bytes += self.stream.write(packer.compress(data[at : at + CHUNK])) or 0
        self.stream.write(packer.flush())
        self.records += 1
        return self.close() if self.stream.tell() >= self.roll_bytes else None

    def close(self) -> dict | None:
        if self.stream is None:
            return None
        size = self.stream.tell()
        self.stream.close()
        self.store.move(self.name + ".part", self.name)
        self.stream = None
        return {"path": self.name, "records": self.records, "bytes": size}


def read_members(stream) -> Iterator[tuple[int, Iterator[bytes]]]:
    """(number, pieces) of each gzip member: pieces of `CHUNK` bytes at most, which are to be taken before the next member."""
    waiting, number = b"", 0

    def pieces(inflate, number: int) -> Iterator[bytes]:
        nonlocal waiting
        while not inflate.eof:
            if not waiting:
                waiting = stream.read(CHUNK)
                if not waiting:
                    raise ValueError(f"gzip member {number} is cut off")
            piece = inflate.decompress(waiting, CHUNK)
            waiting = inflate.unused_data if inflate.eof else inflate.unconsumed_tail
            if piece:
                yield piece

    while True:
        if not waiting:
            waiting = stream.read(CHUNK)
            if not waiting:
                return
        yield number, pieces(zlib.decompressobj(31), number)
        number += 1


def _fields(head: bytes) -> tuple[str, dict[str, str]]:
    first, *lines = head.decode("utf-8").split("\r\n")
    return first, {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in lines)}


END = b"\r\n\r\n"


def parse_record(pieces: Iterator[bytes], keep_payload: bool = True) -> dict:
    """The fields of one record, framed by its content length and checked against its digests as its pieces come.

    Without its payload no more than the headers and a piece are held at a time.
    """
    held, pieces = bytearray(), iter(pieces)

    def more() -> bool:
        piece = next(pieces, None)
        held.extend(piece or b"")
        return piece is not None

    while (at := held.find(END)) < 0:
        if not more():
            raise ValueError("no WARC header")
    version, fields = _fields(bytes(held[:at]))
    del held[: at + len(END)]
    if not version.startswith("WARC/"):
        raise ValueError("no WARC header")
    left, head, in_head = int(fields["content-length"]), bytearray(), True
    block, body, size, payload = hashlib.sha256(), hashlib.sha256(), 0, []
    while left:
        if not held and not more():
            raise ValueError(f"the block ends {left} bytes before its content length")
        part = bytes(held[:left])
        del held[: len(part)]
        left -= len(part)
        block.update(part)
        if in_head:
            head += part
            if (at := head.find(END)) < 0:
                continue
            part, in_head = bytes(head[at + len(END) :]), False
            del head[at:]
        body.update(part)
        size += len(part)
        if keep_payload:
            payload.append(part)
    while len(held) <= len(END) and more():
        pass
    if held != END:
        raise ValueError("the record goes on after its content length")
    if fields["warc-block-digest"] != "sha256:" + block.hexdigest():
        raise ValueError("block digest differs")
    stated, kind = int(_fields(bytes(head))[1]["content-length"]), fields["warc-type"]
    digest = fields["warc-payload-digest"].removeprefix("sha256:")
    if kind == "response" and (size != stated or digest != body.hexdigest()):
        raise ValueError("payload differs from its length or digest")
    number = lambda name: int(fields[name]) if name in fields else None
    return {
        "page_id": number("page-id"), "url": fields.get("warc-target-uri"), "payload_bytes": stated, "payload_digest": digest,
        "record_type": kind, "refers_to": number("refers-to-page-id"), "payload": b"".join(payload) if keep_payload else None,
    }


def read_archive(path: str, keep_payload: bool = True) -> Iterator[dict]:
    store, name = open_store(path)
    with store.open_input_stream(name, compression=None) as stream:
        try:
            for number, pieces in read_members(stream):
                yield parse_record(pieces, keep_payload) | {"path": path, "at": number}
        except (ValueError, KeyError, zlib.error) as error:
            raise ValueError(f"{path}: {error}") from error


def with_revisits(pages: DataFrame) -> DataFrame:
    """`pages` (page_id, url, html) with `refers_to`: the page whose record holds an equal payload, else null."""
    pages = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    key = F.unhex(F.sha2(F.col("html"), 256))
    rows = cut(pages.where(F.octet_length("html") >= MIN_SHARED).where("page_id IS NOT NULL").select("page_id", key.alias("digest")))
    shared = cut(rows.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.max("page_id").alias("last")).where("refers_to < last").select("digest", "refers_to"))
    later = cut(rows.join(shared, "digest").where("page_id > refers_to").select("page_id", "digest", "refers_to").distinct())
    drop(rows, shared)
    return pages.withColumn("digest", key).join(later, ["page_id", "digest"], "left").select("page_id", "url", "html", "refers_to")


def write_archives(pages: DataFrame, folder: str, roll_bytes: int = ROLL_BYTES) -> DataFrame:
    """Write every row of `pages` (page_id, url, html) and return the manifest of the files."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        writer, done = ArchiveWriter(folder, roll_bytes), []
        for batch in batches:
            for row in zip(*(batch.column(i) for i in range(4)), strict=True):
                page_id, url, html, refers_to = (v.as_py() for v in row)
                done.append(writer.add(record(page_id, url, html.encode(), refers_to)))
        done = [x for x in [*done, writer.close()] if x]
        yield pa.RecordBatch.from_pylist(done, schema=pa.schema([("path", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())]))

    return cut(with_revisits(pages).mapInArrow(write, MANIFEST))


def read_archives(manifest: DataFrame) -> DataFrame:
    """One row per record of the archives that `manifest.path` names, in order within each file."""
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("path", pa.string()), ("at", pa.int64())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in batch.column(0).to_pylist():
                rows = []
                for found in read_archive(path, keep_payload=False):
                    found.pop("payload")
                    rows.append(found)
                    if len(rows) == 2000:
                        yield pa.RecordBatch.from_pylist(rows, schema=schema)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=schema)

    return manifest.select("path").mapInArrow(read, RECORDS)


def round_trip(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Write the pages to a fresh folder below `folder` (default: one in the shared folder, which goes when the driver ends) and read the archives back."""
    folder = f"{folder.rstrip('/')}/warc-{uuid.uuid4().hex}" if folder else new_folder(pages.sparkSession, "warc")
    return read_archives(write_archives(pages, folder))
