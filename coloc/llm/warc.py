"""WARC archives of pages: writing, and a sequential reader.

Every record is a gzip member of its own. The reader takes a file's bytes in pieces, inflates one member after the other, frames the
block by its content length and checks block and payload digests while the bytes pass, so its memory does not grow with a record.
Archives are written and read by tasks through pyarrow's file systems, into a folder that all executors share; a
file's name is unique to the attempt that wrote it, and only files in the committed manifest are read.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from functools import partial
from typing import BinaryIO
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.llm.ragged import slices
from coloc.llm.tables import joined_by_hot_key, narrow, shared_dir, ship, staged

SMALLEST_REVISIT = 100
LEVEL = 4
PIECE = 1 << 18
ROTATE = 1 << 30
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
MANIFEST = "path string, records long"
SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def _name(page_id: int | None) -> str:
    return f"<urn:x-page:{'none' if page_id is None else page_id}>"


def _page(name: str | None) -> int | None:
    value = (name or "").removeprefix("<urn:x-page:").removesuffix(">")
    return int(value) if value.lstrip("-").isdigit() else None


def _digest(data_hash) -> str:
    return "sha256:" + base64.b32encode(data_hash.digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One gzip member: a response, or a revisit whose block has the HTTP headers only."""
    revisit = refers_to is not None
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = head if revisit else head + payload
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {_name(page_id)}", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append("WARC-Target-URI: " + quote(url, safe="!#$%&'()*+,/:;=?@[]~", errors="replace"))
    if revisit:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {_name(refers_to)}"]
    lines += [
        f"WARC-Payload-Digest: {_digest(hashlib.sha256(payload))}",
        f"WARC-Block-Digest: {_digest(hashlib.sha256(block))}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    packer = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + packer.flush()


class _Members:
    """The bytes of one gzip member after the other, taken as they are asked for."""

    def __init__(self, source: BinaryIO):
        self.source, self.left, self.ready, self.inflater = source, b"", b"", None

    def start(self) -> bool:
        """Moves to the next member; False at the end of the file."""
        self.left = self.left or self.source.read(PIECE)
        self.ready = b""
        self.inflater = zlib.decompressobj(31) if self.left else None
        return bool(self.left)

    def more(self) -> bytes:
        """Some bytes of the member; none at its end."""
        while not self.inflater.eof:
            if not self.left:
                self.left = self.source.read(PIECE)
                if not self.left:
                    raise ValueError("an archive ends inside a record")
            out = self.inflater.decompress(self.left, PIECE)
            self.left = self.inflater.unused_data if self.inflater.eof else self.inflater.unconsumed_tail
            if out:
                return out
        return b""

    def until(self, mark: bytes) -> bytes:
        while (at := self.ready.find(mark)) < 0:
            got = self.more()
            if not got:
                raise ValueError("a record's headers do not end")
            self.ready += got
        out, self.ready = self.ready[:at], self.ready[at + len(mark) :]
        return out

    def take(self, size: int) -> Iterator[bytes]:
        while size:
            if not self.ready:
                self.ready = self.more()
                if not self.ready:
                    raise ValueError("a block is shorter than its content length")
            part, self.ready = self.ready[:size], self.ready[size:]
            size -= len(part)
            yield part


def _fields(lines: bytes) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines.decode("utf-8", "replace").split("\r\n")[1:])}


def read(source: BinaryIO, payloads: bool = False) -> Iterator[dict]:
    """The records of an archive in order: WARC and HTTP header fields, payload size, hexadecimal digest, and the payload if asked for.

    A wrong digest, a short block or a cut-off file raises ValueError.
    """
    members = _Members(source)
    while members.start():
        fields = _fields(members.until(b"\r\n\r\n"))
        whole, body, head, size, kept = hashlib.sha256(), hashlib.sha256(), b"", 0, []
        http: dict[str, str] | None = None
        for part in members.take(int(fields["content-length"])):
            whole.update(part)
            if http is None:
                head += part
                if b"\r\n\r\n" not in head:
                    continue
                lines, _, part = head.partition(b"\r\n\r\n")
                http = _fields(lines)
            body.update(part)
            size += len(part)
            if payloads:
                kept.append(part)
        if b"".join(members.take(4)) != b"\r\n\r\n" or members.ready or members.more():
            raise ValueError("a record does not end where its content length says")
        if _digest(whole) != fields["warc-block-digest"]:
            raise ValueError(f"wrong block digest in {fields['warc-record-id']}")
        revisit = fields["warc-type"] == "revisit"
        if not revisit and (_digest(body) != fields["warc-payload-digest"] or size != int(http["content-length"])):
            raise ValueError(f"wrong payload digest in {fields['warc-record-id']}")
        yield {
            "page_id": _page(fields["warc-record-id"]),
            "url": fields.get("warc-target-uri"),
            "payload_bytes": int(http["content-length"]) if revisit else size,
            "payload_digest": base64.b32decode(fields["warc-payload-digest"].removeprefix("sha256:")).hex(),
            "record_type": fields["warc-type"],
            "refers_to": _page(fields.get("warc-refers-to")),
            "payload": b"".join(kept) if payloads else None,
        }


def _written(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    from pyarrow.fs import FileSystem

    fs, base = FileSystem.from_uri(folder)
    out, path, count, size = None, "", 0, 0
    done: list[tuple[str, int]] = []
    for batch in slices(batches, 2):
        for page_id, url, html, refers_to in zip(*(c.to_pylist() for c in batch.columns)):
            if out is None:
                path, count, size = f"{base}/{uuid.uuid4().hex}.warc.gz", 0, 0
                out = fs.open_output_stream(path)
            data = record(page_id, url, (html or "").encode("utf-8", "surrogatepass"), refers_to)
            out.write(data)
            count, size = count + 1, size + len(data)
            if size >= ROTATE:
                out.close()
                done.append((path, count))
                out = None
    if out is not None:
        out.close()
        done.append((path, count))
    yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64())], ["path", "records"])


def _records(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    from pyarrow.fs import FileSystem

    fs, _ = FileSystem.from_uri(folder)
    kinds = [("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())]

    def batch(rows: list[dict]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in kinds], [k for k, _ in kinds])

    for manifest in batches:
        for path, records in zip(manifest.column(0).to_pylist(), manifest.column(1).to_pylist()):
            seen, rows = 0, []
            with fs.open_input_stream(path) as source:
                for r in read(source):
                    rows.append(r)
                    seen += 1
                    if len(rows) == 5000:
                        yield batch(rows)
                        rows = []
            if seen != records:
                raise ValueError(f"{path} holds {seen} records, not {records}")
            yield batch(rows)


def write_archives(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Writes a record per row into archives under folder; returns their manifest (path, records), already computed.

    Of rows with equal payloads of at least SMALLEST_REVISIT bytes those with the smallest id are responses and the others
    revisit it. Rows without an id are responses if none of their payload's rows has one. A null html is an empty
    payload, a null url leaves the target out. Repeated rows each give a record; other columns are ignored.
    """
    spark = pages.sparkSession
    ship(spark)
    rows = narrow(pages, page_id=id_col, url=url_col, html=html_col).select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    digest = F.sha2(F.coalesce("html", F.lit("")).cast("binary"), 256)
    large = rows.where(F.octet_length("html") >= SMALLEST_REVISIT).select("page_id", digest.alias("digest"))
    first = large.groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).where("n > 1 and first_id is not null")
    first = staged(first, "warc-payloads")
    known = rows.withColumn("digest", F.when(F.octet_length("html") >= SMALLEST_REVISIT, digest))
    joined = joined_by_hot_key(known, first, "digest", "page_id")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("first_id")), F.col("first_id"))
    from pyarrow.fs import FileSystem

    fs, base = FileSystem.from_uri(folder)
    fs.create_dir(base, recursive=True)
    return staged(joined.select("page_id", "url", "html", refers.alias("refers_to")).mapInArrow(partial(_written, folder=folder), MANIFEST), "warc-manifest")


def read_archives(manifest: DataFrame, folder: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every record in the manifest's archives."""
    ship(manifest.sparkSession)
    tasks = max(1, min(manifest.count(), 20_000))
    return manifest.repartition(tasks).mapInArrow(partial(_records, folder=folder), SCHEMA)


def archived(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Writes archives of the pages and reads them back; an empty table gives no rows."""
    folder = folder or f"{shared_dir(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    return read_archives(write_archives(pages, folder), folder)
