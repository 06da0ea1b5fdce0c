"""Nearest vectors by cosine, in blocks: products of matrices find the candidates, fixed-order sums rank them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 2048  # vectors of a block, about
SLACK = 1e-9  # more than products of matrices and fixed-order sums differ by
PIECE = 1 << 18  # candidates summed together
NOTHING = -2.0  # the similarity of vectors that have none: below every other


def _matrix(batch: pa.RecordBatch, name: str, row: int) -> np.ndarray:
    lists = batch.column(batch.schema.get_field_index(name))[row].values
    flat, ends = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64), lists.value_lengths().to_numpy(zero_copy_only=False)
    ends = np.nan_to_num(ends).astype(np.int64)
    width = int(ends.max(initial=0))
    if len(flat) == width * len(ends):
        return flat.reshape(len(ends), width)
    out = np.full((len(ends), width), np.nan)
    out[np.arange(width) < ends[:, None]] = flat
    return out


def _units(x: np.ndarray) -> np.ndarray:
    square = np.zeros(len(x))
    for d in range(x.shape[1]):
        square += x[:, d] * x[:, d]
    with np.errstate(divide="ignore", invalid="ignore"):
        return x / np.sqrt(square)[:, None]


def _dots(a: np.ndarray, b: np.ndarray, r: np.ndarray, c: np.ndarray) -> np.ndarray:
    out = np.zeros(len(r))
    for lo in range(0, len(r), PIECE):
        x, y, part = a[r[lo : lo + PIECE]], b[c[lo : lo + PIECE]], out[lo : lo + PIECE]
        for d in range(a.shape[1]):
            part += x[:, d] * y[:, d]
    return np.nan_to_num(np.round(out, 12), nan=NOTHING)


def best(ids: np.ndarray, a: np.ndarray, others: np.ndarray, b: np.ndarray, nearest: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions in ``ids``, positions in ``others`` and similarities of the nearest of each row, ties by id."""
    width = max(a.shape[1], b.shape[1])
    a, b = (_units(np.pad(x, ((0, 0), (0, width - x.shape[1])), constant_values=np.nan)) for x in (a, b))
    near = np.nan_to_num(a @ b.T, nan=NOTHING)
    near[ids[:, None] == others] = -np.inf
    k = min(nearest, len(others))
    least = np.partition(near, len(others) - k, axis=1)[:, len(others) - k]
    r, c = np.nonzero((near >= least[:, None] - SLACK) & (near > -np.inf))
    s = _dots(a, b, r, c)
    order = np.lexsort((others[c], -s, r))
    r, c, s = r[order], c[order], s[order]
    first = np.searchsorted(r, r)
    kept = np.arange(len(r)) - first < nearest
    return r[kept], c[kept], s[kept]


def nearest_pairs(vectors: DataFrame, nearest: int) -> DataFrame:
    """``a`` and each of its ``nearest`` others ``b``, from ``vec_id`` and ``embedding``.

    All pairs are scored; a block of others sends on a vector's nearest alone, so no list grows with the table.
    """
    blocks = max(1, -(-vectors.count() // BLOCK))
    own = vectors.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("i")).agg(F.collect_list(F.struct("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))).alias("x"))
    left = own.select("i", F.col("x.vec_id").alias("a"), F.col("x.v").alias("va"))
    right = own.select(F.col("i").alias("j"), F.col("x.vec_id").alias("b"), F.col("x.v").alias("vb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                ids, others = (batch.column(batch.schema.get_field_index(c))[row].values.to_numpy() for c in ("a", "b"))
                r, c, s = best(ids, _matrix(batch, "va", row), others, _matrix(batch, "vb", row), nearest)
                yield pa.RecordBatch.from_pydict({"a": pa.array(ids[r], pa.int64()), "far": pa.array(-s, pa.float64()), "b": pa.array(others[c], pa.int64())})

    dealt = left.crossJoin(right).repartition(min(blocks * blocks, max(64, blocks * blocks // 4)), "i", "j")
    scored = dealt.select("a", "va", "b", "vb").mapInArrow(run, "a long, far double, b long")
    top = scored.groupBy("a").agg(F.slice(F.array_sort(F.collect_list(F.struct("far", "b"))), 1, nearest).alias("top"))
    return top.select("a", F.explode("top.b").alias("b"))
