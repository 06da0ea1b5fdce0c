"""Interleaved document sequences: ordered text and media references, with payloads in a store keyed by digest.

``parse_sequence`` turns HTML into items in page order; ``resolve`` joins the references to the store by digest and puts
positions, captions and payload columns back side by side.  Payloads never take part in the join: the store is read where
it lies, and the join sees one small row per digest.

``media_columns`` applies this to texts: a text's bytes become a grey image (binary PGM, 192 samples a row, one byte a
sample), stored once per partition and digest; the text's page is its own paragraphs with the image's figure and caption
between their halves; the page is parsed, the references are resolved, and what is read back is described.

Defined results: a null text is empty; an empty payload is one row of blanks; a reference that the store lacks keeps its
position with null payload columns; a paragraph is a line with a character that is no white space, and white space within it
becomes one space; equal texts have equal values; other columns are never read, so their names cannot clash.
"""

from __future__ import annotations

import hashlib
import html
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrowmap import map_texts
from .scratch import materialise
from .wordbytes import chunks

WIDTH = 192
_HEADER = re.compile(rb"P5\n(\d+) (\d+)\n255\n")
_ITEM = re.compile(r"<(img|video|audio|source|embed)\b([^>]*)>|<(/?)(figure|figcaption|p|h[1-6]|div|li|section|article|br)\b[^>]*>|<[^>]*>", re.I)
_ATTRIBUTE = re.compile(r"([\w:-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")

ITEM = T.StructType([T.StructField("position", T.IntegerType()), T.StructField("kind", T.StringType()), T.StructField("text", T.StringType()), T.StructField("ref", T.StringType()), T.StructField("caption", T.StringType())])


def encode(payload: bytes) -> bytes:
    """The payload as a grey image of whole rows."""
    if not payload or len(payload) % WIDTH:
        raise ValueError(f"the payload must be a positive multiple of {WIDTH} bytes")
    return b"P5\n%d %d\n255\n" % (WIDTH, len(payload) // WIDTH) + payload


def decode(image: bytes) -> bytes:
    m = _HEADER.match(image)
    if not m or len(image) - m.end() != int(m[1]) * int(m[2]):
        raise ValueError("not a whole image")
    return image[m.end() :]


def feature(payload: bytes) -> str:
    """An 8 x 8 average hash, the rounded mean and the number of different samples."""
    a = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    rows = np.linspace(0, len(a), 9).astype(int)
    cols = a.astype(np.int64).reshape(len(a), 8, WIDTH // 8).sum(2)
    total = np.concatenate((np.zeros((1, 8), np.int64), np.cumsum(cols, 0)))
    hi = np.maximum(rows[1:], np.minimum(rows[:-1] + 1, len(a)))
    lo = np.minimum(rows[:-1], hi - 1)
    cell = (total[hi] - total[lo]) * 1000 // ((hi - lo) * (WIDTH // 8))[:, None]
    mean = int(a.sum(dtype=np.int64)) * 1000 // a.size
    bits = int("".join("1" if x >= mean else "0" for x in cell.ravel()), 2)
    return f"{bits:016x}-{(mean + 500) // 1000:03d}-{np.count_nonzero(np.bincount(a.ravel(), minlength=256)):03d}"


def parse_sequence(page: str | None) -> list[dict]:
    """Items of a page in order: texts, and media references with the caption of the figure that holds them."""
    items: list[dict] = []
    buffer: list[str] = []
    figure: list[int] | None = None
    in_caption = False

    def flush() -> None:
        text = " ".join(html.unescape("".join(buffer)).split())
        buffer.clear()
        if not text:
            return
        if in_caption and figure is not None:
            for i in figure:
                items[i]["caption"] = text
        else:
            items.append({"position": len(items), "kind": "text", "text": text, "ref": None, "caption": None})

    at = 0
    page = page or ""
    for m in _ITEM.finditer(page):
        buffer.append(page[at : m.start()])
        at = m.end()
        if m[1]:
            flush()
            values = {k.lower(): html.unescape(a or b or c) for k, a, b, c in _ATTRIBUTE.findall(m[2])}
            if values.get("src"):
                if figure is not None:
                    figure.append(len(items))
                items.append({"position": len(items), "kind": m[1].lower(), "text": None, "ref": values["src"], "caption": values.get("alt")})
        elif m[4]:
            name = m[4].lower()
            flush()
            if name == "figure":
                figure = None if m[3] else []
            elif name == "figcaption":
                in_caption = not m[3]
    buffer.append(page[at:])
    flush()
    return items


def sequences(pages: DataFrame, key: str, page: str) -> DataFrame:
    """``key`` and its ``items``."""
    src = pages.select(F.col(key), F.col(page))
    schema = T.StructType([src.schema.fields[0], T.StructField("items", T.ArrayType(ITEM))])
    return map_texts(src, 1, schema, lambda cols: {key: cols[0], "items": [parse_sequence(p) for p in cols[1]]})


def resolve(rows: DataFrame, described: DataFrame, carried: list[str]) -> DataFrame:
    """One row per media item of ``rows`` (``carried`` and ``items``) with the columns of ``described`` by ``digest``."""
    items = rows.select(*carried, F.explode(F.filter("items", lambda x: x["ref"].isNotNull())).alias("_item"))
    flat = items.select(*carried, F.col("_item.position").alias("position"), F.col("_item.caption").alias("caption"), F.regexp_replace("_item.ref", "^sha256:", "").alias("digest"))
    return flat.join(described, "digest", "left")


def image_of(text: str | None) -> tuple[int, bytes]:
    """The size of the text in bytes and its stored form: blanks fill the last row."""
    data = text.encode("utf-8", "surrogatepass") if text else b""
    return len(data), encode(data + b" " * (max(1, -(-len(data) // WIDTH)) * WIDTH - len(data)))


def page_of(text: str | None, n_bytes: int, digest: str) -> str:
    """The text's paragraphs with the figure after the first half of them (the middle one included)."""
    parts = [f"<p>{html.escape(p)}</p>" for p in (text or "").split("\n") if p and not p.isspace()]
    figure = f'<figure><img src="sha256:{digest}"><figcaption>{n_bytes} bytes</figcaption></figure>'
    half = (len(parts) + 1) // 2
    return f"<article>{''.join(parts[:half])}{figure}{''.join(parts[half:])}</article>"


def text_sequences(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``n_bytes`` and the ``items`` of every text's page, in page order."""
    src = docs.select(F.col(key), F.col(text))
    schema = T.StructType([src.schema.fields[0], T.StructField("n_bytes", T.LongType()), T.StructField("items", T.ArrayType(ITEM))])

    def make(cols: list[list]) -> dict[str, list]:
        stored = [image_of(t) for t in cols[1]]
        pages = (page_of(t, n, hashlib.sha256(image).hexdigest()) for t, (n, image) in zip(cols[1], stored))
        return {key: cols[0], "n_bytes": [n for n, _ in stored], "items": [parse_sequence(p) for p in pages]}

    return map_texts(src, 1, schema, make)


def stored_images(docs: DataFrame, text: str = "text") -> DataFrame:
    """``digest`` and ``image`` of every text, written once per partition and digest."""

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in batches:
            texts = batch.column(0).to_pylist()
            for lo, hi in chunks(texts):
                digests, images = [], []
                for t in texts[lo:hi]:
                    image = image_of(t)[1]
                    sha = hashlib.sha256(image)
                    if sha.digest() not in seen:
                        seen.add(sha.digest())
                        digests.append(sha.hexdigest())
                        images.append(image)
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.string()), pa.array(images, pa.binary())], names=["digest", "image"])

    return materialise(docs.select(F.col(text)).mapInArrow(store, "digest string, image binary"), "media")


def media_columns(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``n_bytes``, the image's place and caption, and what is read back of it, one row for every text.

    ``n_items`` and ``sequence_crc32`` (texts and references in page order, a line feed after each) stand for the whole
    sequence, which ``text_sequences`` returns and which takes no part in the join.
    """
    plain = docs.select(F.col(key).alias("_key"), F.col(text).alias("_text"))
    described = describe(stored_images(plain, "_text"))
    line = F.transform("items", lambda x: F.concat(F.coalesce(x["text"], x["ref"]), F.lit("\n")))
    carried = ["_key", "n_bytes", F.size("items").cast("long").alias("n_items"), F.crc32(F.encode(F.concat_ws("", line), "utf-8")).alias("sequence_crc32")]
    rows = text_sequences(plain, "_key", "_text").select(*carried, F.filter("items", lambda x: x["ref"].isNotNull()).alias("items"))
    return resolve(rows, described, ["_key", "n_bytes", "n_items", "sequence_crc32"]).withColumnRenamed("_key", key)


_DESCRIBED = "digest string, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def describe(store: DataFrame) -> DataFrame:
    """What the stored images hold, one row per digest; an image that does not match its digest stops the job."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for digest, image in zip(*(c.to_pylist() for c in batch.columns)):
                sha = hashlib.sha256(image).hexdigest()
                if sha != digest:
                    raise ValueError(f"the stored form of {digest} is damaged")
                p = decode(image)
                rows.append((digest, len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:]), len(image), sha, feature(p)))
            if rows:
                kinds = (pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=[x.split()[0] for x in _DESCRIBED.split(", ")])

    names = [x.split()[0] for x in _DESCRIBED.split(", ")]
    return store.mapInArrow(read, _DESCRIBED).groupBy("digest").agg(*[F.min(c).alias(c) for c in names[1:]])
