"""The randomized-response graph in square blocks: every pair's bit drawn once, packed, and multiplied block by block.

Nodes are dealt to blocks by hash; a row is a pair of blocks with the true edges between them.  No table of pairs is written:
a task holds one block's pairs at a time, and what leaves it are sums or an eighth of a byte for each pair.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import draws
from ..functions.noise import keep_probability
from ..sources.views import Graph

BLOCK = 1024  # nodes of a block, about


def block_of(node: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(node), F.lit(blocks)).cast("int")


def block_pairs(graph: Graph, blocks: int) -> DataFrame:
    """``i`` >= ``j``, the ids ``a`` and ``b`` of the blocks, and the edges between them (``ea`` of block i, ``eb`` of block j)."""
    own = graph.nodes.groupBy(block_of(F.col("id"), blocks).alias("i")).agg(F.array_sort(F.collect_list("id")).alias("a"))
    pairs = own.crossJoin(own.select(F.col("i").alias("j"), F.col("a").alias("b"))).where("i >= j")
    edges = graph.arcs.withColumn("i", block_of(F.col("src"), blocks)).withColumn("j", block_of(F.col("dst"), blocks)).where("i > j or (i = j and src > dst)")
    edges = edges.groupBy("i", "j").agg(F.collect_list(F.struct("src", "dst")).alias("e"))
    rows = blocks * (blocks + 1) // 2
    dealt = pairs.join(edges, ["i", "j"], "left").select("i", "j", "a", "b", F.col("e.src").alias("ea"), F.col("e.dst").alias("eb"))
    return dealt.repartition(max(1, min(rows, max(64, rows // 4))), "i", "j")


def _list(batch: pa.RecordBatch, name: str, row: int) -> np.ndarray:
    cell = batch.column(batch.schema.get_field_index(name))[row]
    return cell.values.to_numpy(zero_copy_only=False) if cell.is_valid else np.empty(0, np.int64)


def _draw(batch: pa.RecordBatch, row: int, p: float, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, bool]:
    """Ids of both blocks, which bits are kept, the noisy bits, and whether it is one block with itself (then below the diagonal only)."""
    a, b = _list(batch, "a", row), _list(batch, "b", row)
    same = batch.column(0)[row].as_py() == batch.column(1)[row].as_py()
    bit = np.zeros((len(a), len(b)), bool)
    bit[np.searchsorted(a, _list(batch, "ea", row)), np.searchsorted(b, _list(batch, "eb", row))] = True
    kept = np.ones((len(a), len(b)), bool)
    at = np.tril_indices(len(a), -1) if same else np.unravel_index(np.arange(len(a) * len(b)), kept.shape)
    x, y = a[at[0]], b[at[1]]
    kept[at] = draws.uniform(seed, "r", np.maximum(x, y), np.minimum(x, y)) < p
    return a, b, kept, bit == kept if not same else (bit == kept) & np.tri(len(a), k=-1, dtype=bool), same


def pair_counts(graph: Graph, eps: float, seed: int, blocks: int) -> DataFrame:
    """``n_pairs``, ``n_ones``, ``n_flipped`` of each pair of blocks."""
    p = keep_probability(eps)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                a, b, kept, noisy, same = _draw(batch, row, p, seed)
                n = len(a) * (len(a) - 1) // 2 if same else kept.size
                yield pa.RecordBatch.from_pydict({"n_pairs": pa.array([n], pa.int64()), "n_ones": pa.array([int(noisy.sum())], pa.int64()), "n_flipped": pa.array([int((~kept).sum())], pa.int64())})

    return block_pairs(graph, blocks).mapInArrow(run, "n_pairs long, n_ones long, n_flipped long")


def row_counts(graph: Graph, eps: float, seed: int, blocks: int) -> DataFrame:
    """``id``, ``ones``, ``n``: each node's noisy ones and its other nodes."""
    p = keep_probability(eps)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                a, b, _, noisy, same = _draw(batch, row, p, seed)
                across, down = noisy.sum(1), noisy.sum(0)
                parts = [(a, across + down, len(b) - 1)] if same else [(a, across, len(b)), (b, down, len(a))]
                for ids, ones, n in parts:
                    yield pa.RecordBatch.from_pydict({"id": pa.array(ids, pa.int64()), "ones": pa.array(ones, pa.int64()), "n": pa.array(np.full(len(ids), n), pa.int64())})

    partial = block_pairs(graph, blocks).mapInArrow(run, "id long, ones long, n long")
    return partial.groupBy("id").agg(F.sum("ones").alias("ones"), F.sum("n").alias("n"))


def packed_bits(graph: Graph, eps: float, seed: int, blocks: int) -> DataFrame:
    """``i``, ``j``, ``a``, ``b``, ``bits``: the noisy bits of each pair of blocks, row by row; a block with itself is symmetric."""
    p = keep_probability(eps)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                a, b, _, noisy, same = _draw(batch, row, p, seed)
                bits = np.packbits(noisy | noisy.T if same else noisy).tobytes()
                one = batch.slice(row, 1)
                yield pa.RecordBatch.from_pydict({"i": one.column(0), "j": one.column(1), "a": pa.array([a], pa.list_(pa.int64())), "b": pa.array([b], pa.list_(pa.int64())), "bits": pa.array([bits], pa.binary())})

    return block_pairs(graph, blocks).mapInArrow(run, "i int, j int, a array<long>, b array<long>, bits binary")


def multiply(bits: DataFrame, x: DataFrame, w0: float, w1: float, blocks: int) -> DataFrame:
    """``id``, ``key`` and the sum ``y`` over all other nodes of the pair's weight (``w1`` for a one, else ``w0``) times ``x`` (``id``, ``key``, ``x``).

    ``x`` is a row for each node and key, small beside the pairs; it is what is broadcast.  Every node gets a row for each key.
    """
    keys = sorted(r["key"] for r in x.select("key").distinct().collect())
    own = x.groupBy(block_of(F.col("id"), blocks).alias("i")).agg(F.collect_list(F.struct("id", "key", "x")).alias("x"))
    side = lambda at, to: F.broadcast(own.select(F.col("i").alias(at), F.col("x.id").alias(f"{to}_id"), F.col("x.key").alias(f"{to}_key"), F.col("x.x").alias(f"{to}_x")))
    joined = bits.join(side("j", "r"), "j", "left").join(side("i", "l"), "i", "left").select("i", "j", "a", "b", "bits", "l_id", "l_key", "l_x", "r_id", "r_key", "r_x")

    def dense(batch: pa.RecordBatch, row: int, to: str, ids: np.ndarray) -> np.ndarray:
        out = np.zeros((len(ids), len(keys)))
        np.add.at(out, (np.searchsorted(ids, _list(batch, f"{to}_id", row)), np.searchsorted(keys, _list(batch, f"{to}_key", row))), _list(batch, f"{to}_x", row))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            for row in range(batch.num_rows):
                i, j = batch.column(0)[row].as_py(), batch.column(1)[row].as_py()
                a, b = _list(batch, "a", row), _list(batch, "b", row)
                packed = np.frombuffer(batch.column(4)[row].as_py(), np.uint8)
                w = np.where(np.unpackbits(packed, count=len(a) * len(b)).reshape(len(a), len(b)) == 1, w1, w0)
                parts = [(i, a, w, "r", b)] + ([(j, b, w.T, "l", a)] if i != j else [])
                if i == j:
                    np.fill_diagonal(w, 0.0)
                for at, ids, weight, to, others in parts:
                    y = weight @ dense(batch, row, to, others)
                    if at in sums:
                        sums[at][1] += y
                    else:
                        sums[at] = [ids.copy(), y]
        for ids, y in sums.values():
            for k, key in enumerate(keys):
                yield pa.RecordBatch.from_pydict({"id": pa.array(ids, pa.int64()), "key": pa.array(np.full(len(ids), key), pa.int64()), "y": pa.array(np.ascontiguousarray(y[:, k]), pa.float64())})

    return joined.mapInArrow(run, "id long, key long, y double").groupBy("id", "key").agg(F.sum("y").alias("y"))
