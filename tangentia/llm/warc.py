"""WARC archives: one gzip member for each record, read back sequentially with bounded memory.

Writing: equal payloads of at least ``min_bytes`` are one group, whose record with the largest page_id is a
response and whose others are revisits of it. Only the digests of groups of several rows are joined, so that a
small table decides for all pages. Each task streams its rows into archives of about ``ARCHIVE_BYTES`` in the shared
folder, under names of its own attempt; the manifest that the tasks return lists those that count, so a task
that runs again leaves only unlisted files behind.

Reading: one task for an archive inflates it piece by piece, member after member, parses the header, takes exactly
Content-Length bytes of block, and checks the payload's SHA-1 against the header's. No file is held whole.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.session import materialise, scratch_path, ship_package

ARCHIVE_BYTES = 64 << 20
PIECE = 1 << 16
DATE = "2020-01-01T00:00:00Z"
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


class WarcError(ValueError):
    """A record that breaks its framing or whose payload has another digest than its header says."""


def file_system(uri: str):
    from pyarrow import fs

    if re.match(r"[A-Za-z][A-Za-z0-9+.-]*:", uri):
        uri = re.sub(r"^file:/+", "file:///", uri)
        return fs.FileSystem.from_uri(uri)
    return fs.LocalFileSystem(), uri


def decide_records(pages: DataFrame, min_bytes: int = 1000) -> DataFrame:
    """page_id, url, payload (binary), digest (hex), refers_to (null for responses). Rows that tie for a group's largest page_id are all responses."""
    rows = pages.select("page_id", F.col("url").cast("string").alias("url"), F.coalesce(F.encode(F.col("html").cast("string"), "UTF-8"), F.lit(b"")).alias("payload"))
    rows = rows.withColumn("digest", F.sha1("payload"))
    large = rows.where(F.octet_length("payload") >= min_bytes)
    groups = large.groupBy("digest").agg(F.max("page_id").alias("last_id"), F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("digest").alias("d2"), "last_id")
    joined = rows.join(groups, F.col("digest") == F.col("d2"), "left")
    return joined.select("page_id", "url", "payload", "digest", F.when(F.col("last_id") > F.coalesce("page_id", F.col("last_id") - 1), F.col("last_id")).alias("refers_to"))


def render_record(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    """An uncompressed record. A revisit's block ends with its HTTP header, whose Content-Length is the full payload's."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + (b"" if refers_to is not None else payload)
    fields = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {DATE}",
        "WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "about:blank"),
        "Content-Type: application/http; msgtype=response",
        f"WARC-Payload-Digest: sha1:{base64.b32encode(bytes.fromhex(digest)).decode()}",
        f"WARC-Block-Digest: sha1:{base64.b32encode(hashlib.sha1(block).digest()).decode()}",
    ]
    if refers_to is not None:
        fields += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    fields.append(f"Content-Length: {len(block)}")
    return "\r\n".join(fields).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def gzip_member(record: bytes, level: int = 3) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(record) + z.flush()


def _write_batches(folder: str):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = file_system(folder)
        out, path, size, records = None, "", 0, 0
        done: list[tuple[str, int, int]] = []

        def close():
            nonlocal out, size, records
            if out is not None:
                out.close()
                done.append((path, records, size))
            out, size, records = None, 0, 0

        for batch in batches:
            for page_id, url, payload, digest, refers in zip(*(batch.column(i) for i in range(5)), strict=True):
                if out is None:
                    path = f"{root}/{uuid.uuid4().hex}.warc.gz"
                    out = fs.open_output_stream(path, compression=None)
                member = gzip_member(render_record(page_id.as_py(), url.as_py(), payload.as_py(), digest.as_py(), refers.as_py()))
                out.write(member)
                size, records = size + len(member), records + 1
                if size >= ARCHIVE_BYTES:
                    close()
        close()
        yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in done], t) for k, t in enumerate((pa.string(), pa.int64(), pa.int64()))], ["path", "records", "bytes"])

    return write


def write_warc(pages: DataFrame, folder: str, min_bytes: int = 1000) -> DataFrame:
    """Write one record for each row of ``pages`` into archives in ``folder`` (a URI that executors can write to); the manifest (path, records, bytes).

    Null html is an empty payload, null urls become about:blank; repeated rows are records of their own;
    an empty table gives an empty manifest.
    """
    from pyspark.sql import types as T

    ship_package(pages.sparkSession)
    fs, root = file_system(folder)
    fs.create_dir(root, recursive=True)
    rows = decide_records(pages.withColumn("page_id", F.col("page_id").cast(T.LongType())), min_bytes)
    return materialise(rows.mapInArrow(_write_batches(folder), "path string, records long, bytes long"), "warc-manifest")


def inflate_members(stream) -> Iterator[Iterator[bytes]]:
    """For each gzip member of a stream, the pieces of its content."""
    rest = b""
    while True:
        rest = rest or stream.read(PIECE)
        if not rest:
            return
        z = zlib.decompressobj(31)

        def pieces():
            nonlocal rest
            while not z.eof:
                rest = rest or stream.read(PIECE)
                if not rest:
                    raise WarcError("the archive ends within a member")
                piece = z.decompress(rest, PIECE)
                rest = z.unused_data if z.eof else z.unconsumed_tail
                if piece:
                    yield piece

        yield pieces()


def read_record(pieces: Iterator[bytes]) -> tuple[dict[str, str], int, str]:
    """(header, payload bytes, hex SHA-1) of one record: the header, then Content-Length bytes, of which what follows the HTTP header is hashed as it comes."""
    head = b""
    while b"\r\n\r\n" not in head:
        if (piece := next(pieces, None)) is None:
            raise WarcError("no end of the header")
        head += piece
    head, _, block = head.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise WarcError("no WARC version line")
    header = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    length = int(header["content-length"])
    http, payload, digest, whole, seen, tail = b"", 0, hashlib.sha1(), hashlib.sha1(), 0, b""
    http_open, full = True, 0
    while True:
        part = block[: length - seen]
        tail += block[length - seen :]
        seen += len(part)
        whole.update(part)
        if http_open:
            http += part
            at = http.find(b"\r\n\r\n")
            if at >= 0:
                http_open, part = False, http[at + 4 :]
                m = re.search(rb"(?i)content-length:\s*(\d+)", http[:at])
                full = int(m[1]) if m else 0
            else:
                part = b""
        if not http_open:
            digest.update(part)
            payload += len(part)
        if (block := next(pieces, None)) is None:
            break
    if seen != length or tail != b"\r\n\r\n":
        raise WarcError(f"Content-Length is {length}; the block has {seen} bytes and is closed by {tail[:8]!r}")
    said = base64.b32decode(header["warc-payload-digest"].removeprefix("sha1:")).hex()
    if base64.b32decode(header["warc-block-digest"].removeprefix("sha1:")) != whole.digest():
        raise WarcError("the block has another digest than its header says")
    if header["warc-type"] == "response" and (digest.hexdigest() != said or payload != full):
        raise WarcError("the payload has another digest or length than its header says")
    return header, full, said


def _read_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def page(text: str | None):
        m = re.fullmatch(r"<urn:page:(-?\d+)>", text or "")
        return int(m[1]) if m else None

    def batch_of(rows):
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()))], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    for batch in batches:
        for path in batch.column(0).to_pylist():
            fs, plain = file_system(path)
            rows = []
            with fs.open_input_stream(plain, compression=None) as stream:
                for pieces in inflate_members(stream):
                    h, size, digest = read_record(pieces)
                    rows.append((page(h["warc-record-id"]), size, digest, h["warc-type"], page(h.get("warc-refers-to"))))
                    if len(rows) >= 10_000:
                        yield batch_of(rows)
                        rows = []
            yield batch_of(rows)


def read_warc(archives: DataFrame) -> DataFrame:
    """The records of the archives listed in column ``path``: page_id, payload_bytes, payload_digest, record_type, refers_to.

    A damaged archive fails the job with a WarcError; an empty list gives an empty result.
    """
    ship_package(archives.sparkSession)
    parts = max(1, min(archives.count(), 100_000))
    return archives.select("path").repartition(parts).mapInArrow(_read_batches, RECORD)


def round_trip(pages: DataFrame, min_bytes: int = 1000) -> DataFrame:
    """Write ``pages`` to archives in the shared folder and read them back."""
    manifest = write_warc(pages, scratch_path(pages.sparkSession, "warc"), min_bytes)
    return read_warc(manifest)
