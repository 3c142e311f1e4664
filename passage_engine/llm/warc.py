"""WARC archives as seekable Zstandard bundles.

Each task writes bundles of its own: records gather into independent frames of about ``frame_bytes``,
a seek table closes the file in a skippable frame (the public seekable format), and an index maps
every record to bundle, frame and offset within the frame. Files get names that no other attempt
has, so a task that runs again after a lost executor leaves only files that no index names.
Bundles go through pyarrow's file systems to the shared folder.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_path, stored

#: Fixed values of the public formats.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
CRLF = b"\r\n"
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int, sha: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page}:{sha}')}>"


def record(page: int, url: str | None, payload: bytes, sha: str, refers_to: int | None) -> bytes:
    """One record: an HTTP response, or a revisit with its headers alone."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n" + f"Content-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page, sha)}", f"WARC-Date: {DATE}", f"X-Page-ID: {page}", f"WARC-Payload-Digest: sha1:{sha}"]
    if url is not None:
        head.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if refers_to is not None:
        head += [f"WARC-Refers-To: {record_id(refers_to, sha)}", f"X-Refers-To-Page-ID: {refers_to}", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + CRLF * 2 + block + CRLF * 2


def parse(data: bytes, at: int = 0) -> tuple[dict[str, str], dict[str, str], bytes, int]:
    """WARC headers, HTTP headers, payload and where the next record begins."""
    end = data.index(CRLF * 2, at)
    lines = data[at:end].decode().split("\r\n")
    if not lines[0].startswith("WARC/1."):
        raise ValueError("not at the start of a record")
    head = dict(x.split(": ", 1) for x in lines[1:])
    start = end + 4
    stop = start + int(head["Content-Length"])
    block = data[start:stop]
    http, _, payload = block.partition(CRLF * 2)
    return head, dict(x.split(": ", 1) for x in http.decode().split("\r\n")[1:]), payload, stop + 4


class BundleWriter:
    """Frames of whole records; ``add`` tells (frame, offset within the frame)."""

    def __init__(self, out, frame_bytes: int = 1 << 20, level: int = 3):
        self.out, self.frame_bytes, self.level = out, frame_bytes, level
        self.held, self.size, self.table = [], 0, []

    def add(self, data: bytes) -> tuple[int, int]:
        if self.size and self.size + len(data) > self.frame_bytes:
            self.flush()
        at = (len(self.table), self.size)
        self.held.append(data)
        self.size += len(data)
        return at

    def flush(self):
        if self.held:
            raw = b"".join(self.held)
            packed = zstandard.ZstdCompressor(level=self.level).compress(raw)
            self.out.write(packed)
            self.table.append((len(packed), len(raw)))
            self.held, self.size = [], 0

    def close(self):
        self.flush()
        body = b"".join(struct.pack("<II", *x) for x in self.table) + struct.pack("<IBI", len(self.table), 0, SEEKABLE)
        self.out.write(struct.pack("<II", SKIPPABLE, len(body)) + body)


class BundleReader:
    """Random access by the seek table."""

    def __init__(self, file):
        self.file = file
        size = file.size() if hasattr(file, "size") and callable(file.size) else file.seek(0, 2)
        file.seek(size - 9)
        n, flags, magic = struct.unpack("<IBI", file.read(9))
        if magic != SEEKABLE or flags & 0x80:
            raise ValueError("no seek table without checksums")
        file.seek(size - 9 - 8 * n)
        self.table = list(struct.iter_unpack("<II", file.read(8 * n)))
        self.starts = [0]
        for packed, _ in self.table:
            self.starts.append(self.starts[-1] + packed)
        self.held: tuple[int, bytes] = (-1, b"")

    def frame(self, k: int) -> bytes:
        if self.held[0] != k:
            self.file.seek(self.starts[k])
            self.held = (k, zstandard.ZstdDecompressor().decompress(self.file.read(self.table[k][0]), max_output_size=self.table[k][1]))
        return self.held[1]

    def record(self, frame: int, offset: int):
        return parse(self.frame(frame), offset)

    def records(self) -> Iterator[tuple[int, int, dict, dict, bytes]]:
        for k in range(len(self.table)):
            data, at = self.frame(k), 0
            while at < len(data):
                head, http, payload, end = parse(data, at)
                yield k, at, head, http, payload
                at = end


def identified(pages: DataFrame) -> DataFrame:
    """Pages with payload_bytes and the payload's SHA-1 in hexadecimal (sha); null html is empty."""
    html = F.coalesce("html", F.lit(""))
    return pages.withColumns({"payload_bytes": F.octet_length(html).cast("long"), "sha": F.sha1(html.cast("binary"))})


def write(pages: DataFrame, folder: str, least_bytes: int = 0, frame_bytes: int = 1 << 20, bundle_records: int = 100_000) -> DataFrame:
    """Pages (page_id, url, html) to bundles in ``folder``; returns the index (page_id, bundle, frame, offset).

    Of the records with equal payloads of at least ``least_bytes`` the one of smallest page_id is a
    response, the others revisit it. Only payloads that occur more than once are joined with the
    pages, by page_id and payload; one payload of very many pages is split by the adaptive join, as
    both its sides are read from tables. Each row is written once, repeated ones and such that
    repeat a page_id with another payload included; a row without page_id is not written.
    """
    pages = identified(pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").where("page_id is not null"))
    known = stored(pages.select("page_id", "payload_bytes", "sha"), "digests")
    firsts = stored(known.where(F.col("payload_bytes") >= least_bytes).groupBy("sha").agg(F.min("page_id").alias("first"), F.max("page_id").alias("last")).where("first <> last").drop("last"), "firsts")
    later = stored(known.join(firsts, "sha").where("page_id <> first").select("page_id", "sha", "first").distinct(), "later")

    def run(batches):
        system, base = fs.FileSystem.from_uri(folder)
        system.create_dir(base, recursive=True)
        writer = out = None
        for b in batches:
            rows = []
            for page, url, html, first in zip(*(b.column(n).to_pylist() for n in ("page_id", "url", "html", "first")), strict=True):
                if writer is None:
                    name = f"bundle-{uuid.uuid4().hex}.warc.zst"
                    out = system.open_output_stream(f"{base}/{name}", compression=None)
                    writer, n = BundleWriter(out, frame_bytes), 0
                payload = (html or "").encode()
                rows.append((page, name, *writer.add(record(page, url, payload, digest(payload), first))))
                n += 1
                if n >= bundle_records:
                    writer.close()
                    out.close()
                    writer = None
            yield pa.record_batch([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.int32()), pa.array([r[3] for r in rows], pa.int64())], names=["page_id", "bundle", "frame", "offset"])
        if writer is not None:
            writer.close()
            out.close()

    return stored(pages.join(later, ["page_id", "sha"], "left").select("page_id", "url", "html", "first").mapInArrow(run, "page_id long, bundle string, frame int, offset long"), "warc-index")


def read(index: DataFrame, folder: str) -> DataFrame:
    """Every record that the index names, read back by its offset, and checked.

    Returns page_id, payload_bytes, payload_digest, record_type, refers_to. A revisit carries its
    payload's length and digest in its headers; a response's are computed anew.
    """

    def run(batches):
        system, base = fs.FileSystem.from_uri(folder)
        now, reader = None, None
        for b in batches:
            rows = []
            for page, bundle, frame, offset in zip(*(b.column(n).to_pylist() for n in ("page_id", "bundle", "frame", "offset")), strict=True):
                if bundle != now:
                    now, reader = bundle, BundleReader(system.open_input_file(f"{base}/{bundle}"))
                head, http, payload, _ = reader.record(frame, offset)
                if int(head["X-Page-ID"]) != page:
                    raise ValueError(f"the record at {bundle}, frame {frame}, {offset} isn't of page {page}")
                sha = head["WARC-Payload-Digest"].removeprefix("sha1:")
                if head["WARC-Type"] == "response":
                    if digest(payload) != sha:
                        raise ValueError(f"page {page} is damaged")
                    rows.append((page, len(payload), sha, "response", None))
                else:
                    rows.append((page, int(http["Content-Length"]), sha, "revisit", int(head["X-Refers-To-Page-ID"])))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())
            yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    ordered = index.sortWithinPartitions("bundle", "frame", "offset")
    return ordered.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Write all pages and read the archives back."""
    folder = new_path(pages.sparkSession, "warc")
    return read(write(pages, folder, least_bytes), folder)


def bundle_bytes(records: list[bytes], frame_bytes: int = 1 << 20) -> bytes:
    out = io.BytesIO()
    w = BundleWriter(out, frame_bytes)
    for r in records:
        w.add(r)
    w.close()
    return out.getvalue()
