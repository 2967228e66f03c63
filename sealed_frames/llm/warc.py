"""WARC archives: a writer, and a sequential reader that never holds more than one record.

Each record is one gzip member. The reader feeds fixed-size chunks to an incremental inflater, takes
the end of a member from it, frames the record's block by its Content-Length and verifies block and
payload digests. Archives are written to the shared folder, one or more per task, under a name of the
attempt; the manifest names only those of tasks that ended well, so a repeated task does no harm.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from typing import BinaryIO

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import new_path, settle, ship, small_side

CHUNK = 1 << 18
#: Compressed bytes after which a task begins another archive.
ARCHIVE_BYTES = 256 << 20
#: Payloads that occur more than once and may be broadcast; beyond, pages meet them in a shuffled join.
BROADCAST_PAYLOADS = 200_000
LEAST_BYTES = 100
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


class ArchiveError(ValueError):
    """A record that is cut short, badly framed or differs from its digest."""


@dataclass
class Record:
    headers: dict[str, str]
    block: bytes

    @property
    def kind(self) -> str:
        return self.headers["warc-type"]

    def http(self) -> tuple[dict[str, str], bytes]:
        """Headers and payload of the HTTP message in the block."""
        head, sign, payload = self.block.partition(b"\r\n\r\n")
        if not sign:
            raise ArchiveError("no HTTP header in the block")
        return _fields(head.split(b"\r\n")[1:]), payload


def _fields(lines: list[bytes]) -> dict[str, str]:
    out: dict[str, str] = {}
    last = None
    for line in lines:
        if line[:1] in (b" ", b"\t") and last:  # a folded line
            out[last] += " " + line.decode("utf-8", "replace").strip()
            continue
        name, sign, value = line.partition(b":")
        if sign:
            last = name.decode("utf-8", "replace").strip().lower()
            out[last] = value.decode("utf-8", "replace").strip()
    return out


def members(stream: BinaryIO, chunk: int = CHUNK) -> Iterator[Iterator[bytes]]:
    """The inflated pieces of each gzip member in turn; each must be used up before the next."""
    rest = stream.read(chunk)

    def one() -> Iterator[bytes]:
        nonlocal rest
        inflate = zlib.decompressobj(31)
        while not inflate.eof:
            if not rest:
                rest = stream.read(chunk)
                if not rest:
                    raise ArchiveError("a gzip member is cut short")
            try:
                piece = inflate.decompress(rest, chunk)
            except zlib.error as e:
                raise ArchiveError(f"not a gzip member: {e}") from e
            rest = inflate.unused_data if inflate.eof else inflate.unconsumed_tail
            if piece:
                yield piece

    while rest or (rest := stream.read(chunk)):
        yield one()


def _digest(value: str | None, data: bytes, what: str) -> None:
    if value:
        name, _, text = value.partition(":")
        if name.lower() == "sha256" and hashlib.sha256(data).hexdigest() != text:
            raise ArchiveError(f"the {what} differs from its digest")


def records(stream: BinaryIO, verify: bool = True) -> Iterator[Record]:
    """All records of an archive, in order."""
    for member in members(stream):
        held = bytearray()
        for piece in member:
            held += piece
            if (end := held.find(b"\r\n\r\n", max(0, len(held) - len(piece) - 3))) >= 0:
                break
        else:
            raise ArchiveError("a record without a header")
        lines = bytes(held[:end]).split(b"\r\n")
        if not lines[0].startswith(b"WARC/1."):
            raise ArchiveError("a member that holds no record")
        headers = _fields(lines[1:])
        size = headers.get("content-length", "")
        if not size.isdigit():
            raise ArchiveError("a record without a length")
        body = held[end + 4 :]
        for piece in member:
            body += piece
        if bytes(body[int(size) :]) != b"\r\n\r\n":
            raise ArchiveError("a record's block differs from its length")
        out = Record(headers, bytes(body[: int(size)]))
        if verify:
            _digest(headers.get("warc-block-digest"), out.block, "block")
            if out.kind == "response":
                _digest(headers.get("warc-payload-digest"), out.http()[1], "payload")
        yield out


def member(headers: list[tuple[str, str]], block: bytes, level: int = 6) -> bytes:
    """One record as one gzip member; control characters in header values are percent-encoded."""
    clean = lambda v: "".join(f"%{ord(c):02X}" if ord(c) < 32 or ord(c) == 127 else c for c in v)
    fields = [*headers, ("WARC-Block-Digest", "sha256:" + hashlib.sha256(block).hexdigest()), ("Content-Length", str(len(block)))]
    head = "WARC/1.1\r\n" + "".join(f"{k}: {clean(v)}\r\n" for k, v in fields) + "\r\n"
    deflate = zlib.compressobj(level, zlib.DEFLATED, 31)
    return deflate.compress(head.encode() + block + b"\r\n\r\n") + deflate.flush()


def _name(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def page_member(page_id, url, payload: bytes, digest: str, refers_to, level: int = 6) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    headers = [("WARC-Type", "response" if refers_to is None else "revisit"), ("WARC-Record-ID", _name(page_id)), ("WARC-Date", "1970-01-01T00:00:00Z")]
    headers += [("WARC-Target-URI", url)] * (url is not None)
    headers += [("WARC-Payload-Digest", f"sha256:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    if refers_to is None:
        return member(headers, http + payload, level)
    return member([*headers, ("WARC-Profile", PROFILE), ("WARC-Refers-To", _name(refers_to))], http, level)


def _write(batches: Iterator[pa.RecordBatch], folder: str, level: int) -> Iterator[pa.RecordBatch]:
    from pyarrow import fs

    task = TaskContext.get()
    system, root = fs.FileSystem.from_uri(folder)
    system.create_dir(root, recursive=True)
    out, done, size, count, path = None, [], 0, 0, ""
    for batch in batches:
        columns = [batch.column(i) for i in range(5)]
        for i in range(batch.num_rows):
            page_id, url, payload, digest, refers_to = (c[i].as_py() for c in columns)
            if out is None:
                path = f"{root}/{task.partitionId():06d}-{task.taskAttemptId()}-{len(done)}.warc.gz"
                out, size, count = system.open_output_stream(path), 0, 0
            data = page_member(page_id, url, payload, digest, refers_to, level)
            out.write(data)
            size, count = size + len(data), count + 1
            if size >= ARCHIVE_BYTES:
                out.close()
                done.append((path.rsplit("/", 1)[1], count, size))
                out = None
    if out is not None:
        out.close()
        done.append((path.rsplit("/", 1)[1], count, size))
    if done:
        names, counts, sizes = zip(*done)
        yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(counts, pa.int64()), pa.array(sizes, pa.int64())], names=["file", "records", "bytes"])


def write_pages(pages: DataFrame, folder: str, level: int = 6) -> DataFrame:
    """Write a record per row of ``pages`` (page_id, url, html) below ``folder``; the manifest (file, records, bytes).

    Of rows with equal payloads of at least ``LEAST_BYTES`` bytes, those with the smallest page_id are
    responses, the others revisit them; rows with a null page_id revisit too if any row of the group has
    an id. Null html is an empty payload.
    """
    ship(pages.sparkSession)
    html = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    seen = rows.where(F.length("payload") >= LEAST_BYTES).groupBy(F.unhex("digest").alias("d")).agg(F.min("page_id").alias("first"), F.count("*").alias("n"))
    again = settle(seen.where("n > 1 and first is not null").select("d", "first"), "payloads")
    met = rows.join(small_side(again, BROADCAST_PAYLOADS), F.unhex("digest") == F.col("d"), "left")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    ready = met.select("page_id", "url", "payload", "digest", refers.alias("refers_to"))
    return settle(ready.mapInArrow(lambda it: _write(it, folder, level), "file string, records long, bytes long"), "manifest")


def _page(name: str | None) -> int | None:
    text = (name or "")[len("<urn:page:") : -1]
    return int(text) if text not in ("", "none") else None


def _read(batches: Iterator[pa.RecordBatch], folder: str, payloads: bool) -> Iterator[pa.RecordBatch]:
    from pyarrow import fs

    system, root = fs.FileSystem.from_uri(folder)
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()] + [pa.binary()] * payloads
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url"] + ["payload"] * payloads
    held: list[tuple] = []
    size = 0

    def out():
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held), kinds)], names=names)

    for batch in batches:
        for name in batch.column(0).to_pylist():
            with system.open_input_stream(f"{root}/{name}") as stream:
                for r in records(stream):
                    http, payload = r.http()
                    row = (_page(r.headers["warc-record-id"]), int(http["content-length"]), r.headers["warc-payload-digest"].partition(":")[2], r.kind, _page(r.headers.get("warc-refers-to")), r.headers.get("warc-target-uri"))
                    if r.kind == "response" and len(payload) != row[1]:
                        raise ArchiveError("a payload differs from its length")
                    held.append((*row, payload) if payloads else row)
                    size += len(payload) if payloads else 100
                    if size > 1 << 22:
                        yield out()
                        held, size = [], 0
    if held:
        yield out()


def read_archives(manifest: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """A row per record of the archives that ``manifest`` (file) names; a task per archive."""
    ship(manifest.sparkSession)
    dealt = manifest.select("file").repartition(max(1, manifest.count()))
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string" + ", payload binary" * payloads
    return dealt.mapInArrow(lambda it: _read(it, folder, payloads), schema)


def archive_round_trip(pages: DataFrame) -> DataFrame:
    """Write all pages and read the archives back."""
    folder = new_path(pages.sparkSession, "archives")
    return read_archives(write_pages(pages, folder), folder)
