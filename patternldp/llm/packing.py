"""Packing of token sequences by exact-complement hashing with a best-fit rest.

Only the histogram of piece lengths reaches the driver: at most ``capacity`` counts, whatever the corpus.  The solver works
on counts.  For each length, longest first, it looks for one, two or three lengths whose sum is exactly the gap and
uses such a combination as often as the counts allow; what is left goes best-fit into the open sequences.  Its answer is
a list of fillings with multiplicities.  Pieces are numbered within their length by a hash-dealt two-step count
and look their place up in it.

Defined results: a null text is an empty one, and an empty text is the closing id alone; equal rows are packed
each; an empty table gives an empty result; columns other than the key and the text are never read, so their names cannot clash.
"""

from __future__ import annotations

import base64
import functools
import os
import re
import zlib
from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .arrowmap import released
from .scratch import materialise
from .wordbytes import chunks

CAPACITY = 2048
END_ID = 0
LONG_SPACE = 10_000  # characters of white space in a run that tiktoken is spared
_LONG_SPACE = re.compile(rf"\s{{{LONG_SPACE}}}")
BLOCK_ROWS = 100_000  # pieces that are numbered together, about


def encoder(name: str = "byte_bpe_50k"):
    """A function from text to ids, as the public tokenizer file gives them without special tokens added.

    The byte-level vocabulary is the same in both files; tiktoken runs it about four times as fast.  A text that holds the
    special token's own string is left to ``tokenizers``, and so is one with a very long run of white space, which the
    other's pattern cannot pass.
    """
    import tiktoken

    with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    @functools.cache
    def whole():
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        return Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))

    def encode(text: str) -> list[int]:
        if "<|endoftext|>" in text or len(text) > LONG_SPACE and _LONG_SPACE.search(text):
            return whole().encode(text, add_special_tokens=False).ids
        return fast.encode_ordinary(text)

    return encode


def pieces_of(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """Start and length of the pieces of ``n`` ids; only the first can be shorter than the capacity."""
    first = n % capacity or min(n, capacity)
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


def cut(docs: DataFrame, key: str = "doc_id", text: str = "text", capacity: int = CAPACITY) -> DataFrame:
    """``key``, ``piece``, ``start``, ``length``, ``ids_crc32`` of every piece of every document."""
    src = docs.select(F.col(key).alias("_key"), F.col(text).alias("_text"))
    kind = src.schema["_key"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder()
        for batch in batches:
            keys, texts = (c.to_pylist() for c in batch.columns)
            for lo, hi in chunks(texts):
                rows: tuple[list, ...] = ([], [], [], [], [])
                for k, t in zip(keys[lo:hi], texts[lo:hi]):
                    ids = np.array([*(encode(t) if t else []), END_ID], "<u4")
                    for p, (s, n) in enumerate(pieces_of(len(ids), capacity)):
                        for col, v in zip(rows, (k, p, s, n, zlib.crc32(ids[s : s + n].tobytes()))):
                            col.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(rows[0], batch.schema.field(0).type), pa.array(rows[1], pa.int32()), *[pa.array(c, pa.int64()) for c in rows[2:]]], names=["_key", "piece", "start", "length", "ids_crc32"])

    return src.mapInArrow(released(run), f"_key {kind}, piece int, start long, length long, ids_crc32 long")


def solve(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """Fillings and how often each is used; together they use every counted length up."""
    have = np.zeros(capacity + 1, np.int64)
    for n, c in counts.items():
        have[n] = c
    out: list[tuple[tuple[int, ...], int]] = []

    def combinations(a: int) -> Iterator[tuple[int, ...]]:
        """Fillings that ``a`` begins exactly: one more length, then two, then three, the longest first."""
        gap, there = capacity - a, have > 0
        if not gap:
            yield (a,)
            return
        if gap <= a and there[gap]:
            yield (a, gap)
        for b in complements(gap, a, there):
            yield (a, b, gap - b)
        for b in np.flatnonzero(there[: max(0, min(a, gap - 2)) + 1])[::-1].tolist():
            if 3 * b < gap:
                return
            for c in complements(gap - b, b, there):
                yield (a, b, c, gap - b - c)

    for a in range(capacity, 0, -1):
        while have[a]:
            for fill in combinations(a):
                need = Counter(fill)
                times = min(int(have[x]) // n for x, n in need.items())
                if times:
                    for x, n in need.items():
                        have[x] -= times * n
                    out.append((fill, times))
                    break
            else:
                break
    return out + best_fit({int(n): int(have[n]) for n in np.flatnonzero(have)}, capacity)


def complements(gap: int, most: int, there: np.ndarray) -> list[int]:
    """Lengths of at least half of ``gap`` and at most ``most`` whose complement is there too, the longest first."""
    low, top = -(-gap // 2), min(most, gap - 1)
    if top < low:
        return []
    hit = there[low : top + 1] & there[gap - top : gap - low + 1][::-1]
    return (low + np.flatnonzero(hit)[::-1]).tolist()


def best_fit(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing on counts: open sequences with the same content are one entry."""
    open_: dict[int, list[tuple[tuple[int, ...], int]]] = {}
    gaps: list[int] = []

    def put(fill: tuple[int, ...], times: int) -> None:
        gap = capacity - sum(fill)
        if gap not in open_:
            open_[gap] = []
            insort(gaps, gap)
        open_[gap].append((fill, times))

    for n in sorted(counts, reverse=True):
        left = counts[n]
        while left:
            at = bisect_left(gaps, n)
            if at == len(gaps):
                each = capacity // n
                if left >= each:
                    put((n,) * each, left // each)
                if left % each:
                    put((n,) * (left % each), 1)
                break
            gap = gaps[at]
            fill, times = open_[gap].pop()
            if not open_[gap]:
                del open_[gap], gaps[at]
            each = min(gap // n, left)
            used = min(times, left // each)
            if used < times:
                put(fill, times - used)
            put(fill + (n,) * each, used)
            left -= used * each
    return [x for fills in open_.values() for x in fills]


class Places:
    """Where the r-th piece of each length goes."""

    def __init__(self, fillings: list[tuple[tuple[int, ...], int]]):
        used: Counter[int] = Counter()
        rows, sequence = [], 0
        for fill, times in fillings:
            at = 0
            for n, m in sorted(Counter(fill).items(), reverse=True):
                rows.append((n, used[n], sequence, m, at))
                used[n] += times * m
                at += n * m
            sequence += times
        self.sequences = sequence
        rows.sort()
        n, self.rank, self.sequence, self.each, self.offset = (np.array(c, np.int64) for c in zip(*rows)) if rows else (np.empty(0, np.int64),) * 5
        self.at = (n << 48) + self.rank

    def find(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        i = np.searchsorted(self.at, (length << 48) + rank, "right") - 1
        r, each = rank - self.rank[i], self.each[i]
        return self.sequence[i] + r // each, self.offset[i] + r % each * length


def ranked(pieces: DataFrame, total: int) -> DataFrame:
    """``pieces`` with ``rank`` from 0 within each length.  A length is numbered in blocks, and the blocks' counts are summed."""
    blocks = max(64, total // BLOCK_ROWS)
    dealt = pieces.withColumn("block", F.pmod(F.xxhash64("_key", "piece"), F.lit(blocks)))
    within = Window.partitionBy("length", "block").orderBy("_key", "piece", "ids_crc32")
    before = Window.partitionBy("length").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("length", "block").agg(F.count("*").alias("n")).select("length", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("skip"))
    return dealt.withColumn("rank", F.row_number().over(within) - 1).join(starts, ["length", "block"]).withColumn("rank", F.col("rank") + F.col("skip")).drop("block", "skip")


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", capacity: int = CAPACITY) -> DataFrame:
    """Every piece with the sequence it is packed in and its place there."""
    pieces = materialise(cut(docs, key, text, capacity), "pieces")
    counts = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    places = Places(solve(counts, capacity))
    rows = ranked(pieces, sum(counts.values())).select("_key", "piece", "start", "length", "ids_crc32", "rank")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sequence, offset = places.find(b.column(3).to_numpy(), b.column(5).to_numpy())
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sequence), pa.array(offset)], names=[*b.schema.names[:5], "sequence_id", "offset"])

    kind = rows.schema["_key"].dataType.simpleString()
    return rows.mapInArrow(released(place), f"_key {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long").withColumnRenamed("_key", key)
