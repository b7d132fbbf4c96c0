"""WARC archives in seekable Zstandard bundles.

Each task writes its pages as WARC/1.1 records to bundle files in the shared folder. Records are grouped into independent Zstandard
frames; after them stands a seek table, a skippable frame with each frame's compressed and plain size (the published seekable
format). The index maps each record to its bundle, its frame and its place within the frame, so one record costs one frame to read.
Of records with equal payloads of at least `least_bytes`, that with the smallest page_id is a response, others are revisits of it.

A bundle is written under a temporary name and renamed when complete; only bundles that the index names are ever read, so the
files of failed or repeated attempts do no harm. Null html is an empty payload, a null url an empty target. Rows with a null page_id are
responses. Rows that repeat the smallest page_id are all responses. Line breaks in a url are percent-encoded.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from . import common as C

#: Fixed values of the seekable format: the skippable frame's and the seek table's magic numbers.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
FRAME_BYTES, BUNDLE_BYTES = 1 << 20, 128 << 20
#: Frames that one task reads from a bundle at a stretch.
FRAMES_TOGETHER = 16
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def filesystem(uri: str):
    """A file system for a shared folder's URI, and the path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}" if uri.startswith("/") else uri.replace("file:/", "file:///", 1))


def record_id(page_id: int | None) -> str:
    return f"<urn:x-page:{'null' if page_id is None else page_id}>"


def record(page_id: int | None, url: str | None, payload: bytes, refers: int | None, date: str) -> bytes:
    """One WARC record. A revisit has the HTTP head, with the payload's length, and no payload."""
    target = "".join(f"%{ord(c):02X}" if c < " " or c == "\x7f" else c for c in url or "")
    body = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    head = [("WARC-Type", "response" if refers is None else "revisit"), ("WARC-Record-ID", record_id(page_id)), ("WARC-Target-URI", target), ("WARC-Date", date), ("WARC-Payload-Digest", "sha1:" + base64.b32encode(hashlib.sha1(payload).digest()).decode())]
    if refers is None:
        body += payload
    else:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers))]
    head += [("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(body)))]
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + body + b"\r\n\r\n"


def parse(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """Headers and block of the record at `at`, and where the next begins."""
    end = data.index(b"\r\n\r\n", at)
    lines = data[at:end].decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("not a WARC record")
    head = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
    stop = end + 4 + int(head["Content-Length"])
    if data[stop : stop + 4] != b"\r\n\r\n":
        raise ValueError("a record's length is wrong")
    return head, data[end + 4 : stop], stop + 4


class Bundle:
    """A seekable bundle that is being written."""

    def __init__(self, folder: str, level: int):
        import zstandard

        self.fs, base = filesystem(folder)
        self.path = f"{base}/{uuid.uuid4().hex}.warc.zst"
        self.out, self.zip = self.fs.open_output_stream(f"{self.path}.part"), zstandard.ZstdCompressor(level=level)
        self.frames: list[tuple[int, int]] = []
        self.parts: list[bytes] = []
        self.plain, self.size = 0, 0

    def add(self, data: bytes) -> tuple[int, int]:
        """The frame the record goes to and its offset there."""
        if self.plain and self.plain + len(data) > FRAME_BYTES:
            self.flush()
        at = (len(self.frames), self.plain)
        self.parts.append(data)
        self.plain += len(data)
        return at

    def flush(self) -> None:
        if self.parts:
            z = self.zip.compress(b"".join(self.parts))
            self.out.write(z)
            self.frames.append((len(z), self.plain))
            self.size += len(z)
            self.parts, self.plain = [], 0

    def close(self) -> str:
        self.flush()
        entries = b"".join(struct.pack("<II", *f) for f in self.frames)
        self.out.write(struct.pack("<II", SKIPPABLE, len(entries) + 9) + entries + struct.pack("<IBI", len(self.frames), 0, SEEKABLE))
        self.out.close()
        self.fs.move(f"{self.path}.part", self.path)
        return self.path.rsplit("/", 1)[1]


class Reader:
    """Random access to a bundle by its seek table."""

    def __init__(self, folder: str, name: str):
        import zstandard

        fs, base = filesystem(folder)
        self.file, self.zip = fs.open_input_file(f"{base}/{name}"), zstandard.ZstdDecompressor()
        size = self.file.size()
        n, _, magic = struct.unpack("<IBI", self.file.read_at(9, size - 9))
        if magic != SEEKABLE:
            raise ValueError("no seek table")
        table = self.file.read_at(8 * n, size - 9 - 8 * n)
        self.frames, at = [], 0
        for i in range(n):
            z, plain = struct.unpack_from("<II", table, 8 * i)
            self.frames.append((at, z, plain))
            at += z

    def frame(self, i: int) -> bytes:
        at, z, plain = self.frames[i]
        return self.zip.decompress(self.file.read_at(z, at), max_output_size=plain) if plain else b""

    def record(self, frame: int, offset: int) -> tuple[dict[str, str], bytes]:
        return parse(self.frame(frame), offset)[:2]


def write(pages: DataFrame, folder: str, least_bytes: int = 0, level: int = 3, date: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Writes the bundles of all pages (page_id, url, html) to `folder`. The index: page_id, bundle, frame, offset."""
    C.ship(pages.sparkSession)
    pages = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    sums = C.stash(pages.where("page_id is not null").select("page_id", F.sha1(F.encode("html", "utf-8")).alias("sha"), F.octet_length("html").alias("n")).where(F.col("n") >= least_bytes), "payloads")
    first = sums.groupBy("sha", "n").agg(F.min("page_id").alias("first"), F.count("*").alias("c")).where("c > 1").drop("c")
    again = C.stash(sums.join(first, ["sha", "n"]).where("page_id > first").select("page_id", "first").distinct(), "revisits")
    rows = pages.join(C.maybe_broadcast(again, 24), "page_id", "left").select("page_id", "url", "html", F.col("first").alias("refers"))
    fs, base = filesystem(folder)
    fs.create_dir(base, recursive=True)

    def run(batches):
        bundle, done = None, []

        def index() -> pa.RecordBatch:
            name = bundle.close()
            ids, frames, offsets = zip(*done)
            return C.batch_of({"page_id": pa.array(ids, pa.int64()), "bundle": pa.array([name] * len(ids)), "frame": pa.array(frames, pa.int32()), "offset": pa.array(offsets, pa.int64())})

        for x in batches:
            ids, urls, refers, html = x.column(0).to_pylist(), x.column(1), x.column(3), x.column(2)
            for i, page in enumerate(ids):
                bundle = bundle or Bundle(folder, level)
                payload = html[i].as_py().encode()
                done.append((page, *bundle.add(record(page, urls[i].as_py(), payload, refers[i].as_py(), date))))
                if bundle.size >= BUNDLE_BYTES:
                    yield index()
                    bundle, done = None, []
        if bundle:
            yield index()

    return C.stash(rows.mapInArrow(run, "page_id long, bundle string, frame int, offset long"), "warc-index")


def read(index: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """Every record of the bundles that the index names: page_id, url, record_type, refers_to, payload_bytes, payload_digest and, if
    asked for, the payload (null for revisits). A response's digest is computed from what is read and must equal its header."""
    C.ship(index.sparkSession)
    # runs of frames of a bundle are dealt to tasks of about as many bytes each; an expression keeps this shuffle apart from that of the distinct
    frames = index.select("bundle", "frame").distinct()
    tasks = C.partitions(index, -(-frames.count() * FRAME_BYTES // BUNDLE_BYTES))
    frames = frames.repartition(tasks, F.xxhash64("bundle", F.floor(F.col("frame") / FRAMES_TOGETHER))).sortWithinPartitions("bundle", "frame")

    def run(batches):
        name, reader = None, None
        for x in batches:
            for b, f in zip(x.column(0).to_pylist(), x.column(1).to_pylist()):
                if b != name:
                    name, reader = b, Reader(folder, b)
                data, at, out = reader.frame(f), 0, []
                while at < len(data):
                    head, block, at = parse(data, at)
                    http, _, payload = block.partition(b"\r\n\r\n")
                    n = int(next(v for v in http.decode().split("\r\n") if v.startswith("Content-Length: "))[16:])
                    sha = head["WARC-Payload-Digest"].removeprefix("sha1:")
                    whole = head["WARC-Type"] == "response"
                    if whole and (len(payload) != n or base64.b32encode(hashlib.sha1(payload).digest()).decode() != sha):
                        raise ValueError("a payload differs from its digest")
                    ids = [None if v in ("", "null") else int(v) for v in (head.get(k, "")[12:-1] for k in ("WARC-Record-ID", "WARC-Refers-To"))]
                    out.append((ids[0], head["WARC-Target-URI"], head["WARC-Type"], ids[1], n, sha, payload if whole and payloads else None))
                cols = list(zip(*out))
                kinds = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary())
                names = ("page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload")
                yield C.batch_of({k: pa.array(v, t) for k, v, t in list(zip(names, cols, kinds))[: 6 + payloads]})

    return frames.mapInArrow(run, "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string" + ", payload binary" * payloads)


def lookup(spark: SparkSession, index: DataFrame, folder: str, page_id: int) -> list[tuple[dict[str, str], bytes]]:
    """The records of one page, each by one seek."""
    return [Reader(folder, r["bundle"]).record(r["frame"], r["offset"]) for r in index.where(F.col("page_id") == page_id).collect()]
