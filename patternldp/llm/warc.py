"""WARC archives of zstandard frames: one frame per record, the dictionary in a leading skippable frame.

Pages are written as ``response`` records.  Of pages with equal payloads the one with the largest id is the response; the
others are ``revisit`` records that name it and hold only the HTTP header.  Archives are written by tasks under names of
their own; only those in the written manifest are read, so that a task that is run again leaves no double record.
Reading takes the dictionary from the archive, decodes frame by frame and checks headers, lengths and digests.

Defined results: a null page has an empty payload; rows that repeat the largest id of a payload are all
responses; a null id is written as a response that nothing refers to; an empty table gives no archive; other columns are
never read, so their names cannot clash.  Payloads are not shuffled while the revisits number at most ``BROADCAST_REVISITS``.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
import uuid
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
import pyarrow.fs
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import fresh_path, materialise

SKIPPABLE = 0x184D2A5D  # the magic number of the frame that holds the dictionary
LEVEL = 3
DICTIONARY_BYTES, DICTIONARY_SAMPLE = 32 << 10, 200
ARCHIVE_BYTES = 64 << 20
BLOCK = 1 << 20
#: Revisits that may be broadcast; beyond it they are joined by a shuffle.
BROADCAST_REVISITS = 200_000
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def file_system(path: str) -> tuple[pa.fs.FileSystem, str]:
    return pa.fs.FileSystem.from_uri(path if "://" in path else re.sub(r"^(file:)?/*", "file:///", path))


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary from sample payloads, or none if they are too few."""
    samples = [s for s in samples if s]
    if len(samples) < 16:
        return b""
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


def record(kind: str, page: int | None, url: str | None, payload: bytes, sha: str, refers_to: int | None = None) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + (payload if kind == "response" else b"")
    name = f"urn:page:{page}" if page is not None else f"urn:uuid:{uuid.uuid4()}"
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{name}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {quote(url, safe=':/?#[]@!$&()*+,;=%~') if url else name}"]
    head += [f"WARC-Payload-Digest: sha1:{sha}", f"WARC-Block-Digest: sha1:{digest(block)}"]
    if kind == "revisit":
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class ArchiveWriter:
    def __init__(self, path: str, dictionary: bytes):
        fs, at = file_system(path)
        fs.create_dir(at.rsplit("/", 1)[0], recursive=True)
        self.path, self.records, self.bytes = path, 0, 0
        self.out = fs.open_output_stream(at, compression=None)
        self.frames = zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None, write_checksum=True, write_content_size=True)
        if dictionary:
            self._put(struct.pack("<II", SKIPPABLE, len(dictionary)) + dictionary)

    def _put(self, data: bytes) -> None:
        self.out.write(data)
        self.bytes += len(data)

    def add(self, data: bytes) -> None:
        self._put(self.frames.compress(data))
        self.records += 1

    def close(self) -> tuple[str, int, int]:
        self.out.close()
        return self.path, self.records, self.bytes


def _exactly(stream, n: int) -> bytes:
    data = stream.read(n)
    if len(data) != n:
        raise ValueError("the archive ends inside a frame")
    return data


def frames(path: str) -> Iterator[bytes]:
    """The content of each frame but the dictionary's; holds one record and one block of the file."""
    fs, at = file_system(path)
    with fs.open_input_stream(at, compression=None) as stream:
        held = stream.read(8)
        dictionary = None
        if len(held) == 8 and struct.unpack("<I", held[:4])[0] == SKIPPABLE:
            data = _exactly(stream, struct.unpack("<I", held[4:])[0])
            if data[:4] == b"\x28\xb5\x2f\xfd":  # a dictionary that is itself compressed
                data = zstandard.ZstdDecompressor().decompress(data)
            dictionary, held = zstandard.ZstdCompressionDict(data), b""
        decoder = zstandard.ZstdDecompressor(dict_data=dictionary)
        while held or (held := stream.read(BLOCK)):
            frame, parts = decoder.decompressobj(), []
            while not frame.eof:
                if not held and not (held := stream.read(BLOCK)):
                    raise ValueError("the archive ends inside a frame")
                parts.append(frame.decompress(held))
                held = frame.unused_data if frame.eof else b""
            yield b"".join(parts)


def fields(head: bytes) -> dict[str, str]:
    """Named fields of a header, names in lower case; folded lines are joined."""
    out: dict[str, str] = {}
    last = ""
    for line in head.decode("utf-8").split("\r\n"):
        if line[:1] in " \t" and last:
            out[last] += " " + line.strip()
            continue
        name, colon, value = line.partition(":")
        if not colon or not name.strip():
            raise ValueError(f"not a header line: {line[:80]!r}")
        last = name.strip().lower()
        out[last] = value.strip()
    return out


def parse(data: bytes) -> dict:
    """A record's fields, block and payload, with lengths and digests checked."""
    head, gap, rest = data.partition(b"\r\n\r\n")
    version, _, named = head.partition(b"\r\n")
    if not gap or not re.fullmatch(rb"WARC/1\.[01]", version):
        raise ValueError(f"not a WARC record: {version[:40]!r}")
    f = fields(named)
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in f:
            raise ValueError(f"the record lacks {name}")
    n = int(f["content-length"])
    if len(rest) != n + 4 or rest[n:] != b"\r\n\r\n":
        raise ValueError(f"the record's length is not {n}")
    block = rest[:n]
    if "warc-block-digest" in f and f["warc-block-digest"] != f"sha1:{digest(block)}":
        raise ValueError("the block's digest differs")
    http, gap, payload = block.partition(b"\r\n\r\n")
    if not gap:
        raise ValueError("the block has no HTTP header")
    full = int(fields(http.partition(b"\r\n")[2])["content-length"])
    if f["warc-type"] == "response" and (len(payload) != full or f["warc-payload-digest"] != f"sha1:{digest(payload)}"):
        raise ValueError("the payload's length or digest differs")
    if f["warc-type"] == "revisit" and (payload or "warc-refers-to" not in f):
        raise ValueError("a revisit has no payload and names its response")
    return {"fields": f, "block": block, "payload": payload, "payload_bytes": full}


def _page(name: str | None) -> int | None:
    m = re.fullmatch(r"<urn:page:(-?\d+)>", name or "")
    return int(m[1]) if m else None


def write_archives(pages: DataFrame, key: str = "page_id", url: str = "url", page: str = "html", least_revisit: int = 0) -> DataFrame:
    """Write all pages; the manifest has ``path``, ``records`` and ``bytes`` of each archive.

    Payloads of fewer than ``least_revisit`` bytes are never revisits.
    """
    spark = pages.sparkSession
    src = pages.select(F.col(key).cast("long").alias("id"), F.col(url).alias("url"), F.encode(F.coalesce(F.col(page), F.lit("")), "UTF-8").alias("payload"))
    dictionary = train_dictionary([bytes(r["payload"]) for r in src.select("payload").limit(DICTIONARY_SAMPLE).collect()])
    named = src.where(F.length("payload") >= least_revisit).select("id", F.sha1("payload").alias("sha"))
    tops = named.groupBy("sha").agg(F.max("id").alias("top"), F.count("*").alias("copies")).where("copies > 1").select("sha", "top")
    revisits = materialise(named.join(tops, "sha").where("id <> top").select(F.col("id").alias("_id"), F.col("sha").alias("_sha"), "top").distinct(), "warc-revisits")
    if revisits.limit(BROADCAST_REVISITS + 1).count() <= BROADCAST_REVISITS:
        revisits = F.broadcast(revisits)
    hashed = src.withColumn("sha", F.sha1("payload"))
    rows = hashed.join(revisits, (F.col("id") == F.col("_id")) & (F.col("sha") == F.col("_sha")), "left").select("id", "url", "payload", "top")
    root = fresh_path(spark, "warc")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, done = None, []
        for batch in batches:
            for i, u, p, top in zip(*(c.to_pylist() for c in batch.columns)):
                out = out or ArchiveWriter(f"{root}/{uuid.uuid4().hex}.warc.zst", dictionary)
                revisit = top is not None and i is not None and i != top
                out.add(record("revisit" if revisit else "response", i, u, p, digest(p), top))
                if out.bytes >= ARCHIVE_BYTES:
                    done.append(out.close())
                    out = None
        if out:
            done.append(out.close())
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), *[pa.array([d[k] for d in done], pa.int64()) for k in (1, 2)]], names=["path", "records", "bytes"])

    return materialise(rows.mapInArrow(write, "path string, records long, bytes long"), "warc-manifest")


def read_archives(manifest: DataFrame) -> DataFrame:
    """One row per record of the archives in ``path``: ids, url, type, digest, payload length and payload."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in batch.column(0).to_pylist():
                rows, size = [], 0
                for data in frames(path):
                    r = parse(data)
                    f = r["fields"]
                    rows.append((_page(f["warc-record-id"]), f.get("warc-target-uri"), f["warc-type"], f["warc-payload-digest"].removeprefix("sha1:"), r["payload_bytes"], _page(f.get("warc-refers-to")), r["payload"]))
                    size += len(data)
                    if size > BLOCK:
                        yield _records(rows)
                        rows, size = [], 0
                if rows:
                    yield _records(rows)

    parts = int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return manifest.select("path").repartition(parts, "path").mapInArrow(read, "id long, url string, record_type string, payload_digest string, payload_bytes long, refers_to long, payload binary")


def _records(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.binary())
    names = ["id", "url", "record_type", "payload_digest", "payload_bytes", "refers_to", "payload"]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)
