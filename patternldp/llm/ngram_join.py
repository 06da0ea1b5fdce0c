"""Exact similarity join on n-gram sets with a count-vector R-tree.

Tokens (shingle hashes) are hashed into groups; a document becomes the point of its group counts, and the sum of
coordinate minima of two points bounds their overlap.  One tree over all documents cannot prune (the spread of
the counts is below the allowed difference in every coordinate), so trees are built on blocks that no linked
pair can straddle:

* Two sets that reach the threshold differ in at most H elements (H follows from their sizes).  Hashed into more
  than H groups, some group holds the same tokens in both.  Documents that share a group's content, within a size
  class, form a bucket.
* In each bucket a bulk-loaded R-tree over the count vectors finds the pairs whose bound reaches the needed overlap.
  Documents that such pairs connect form a block, and within it a second tree leads to the pairs that are verified on
  the sets.  Buckets and blocks too large for one task are cut into pairs of parts.

No group's pairs are listed: a bucket passes on a spanning forest of the pairs within the bound, a block one of the links.
Sets and groups are compared by 64-bit hashes.

Defined results: null or empty texts have no set and link with nothing; a null id is kept, unlinked, with a null
component; rows of one id are documents of their own, which ``component_id`` names by that id; equal sets are one node
however many documents have them; ids are whole numbers; other columns are never read, so their names cannot clash.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrowmap import released
from .components import components
from .scratch import materialise
from .wordbytes import chunks, mix, shingle_sets

COORDINATES = ((200, 32), (1000, 64), (1 << 62, 256))  # of the count vectors of sets below each size; each divides the next
LEAF = 16
PART_DOCS, PART_SHINGLES = 512, 1 << 20  # of a part of a large block, about
SMALL_RUN = 8  # buckets up to this size are told apart by their members
SEEN = 1 << 20  # sets that a task remembers, to leave out copies
BUCKET_DOCS = 4096  # of a part of a large bucket
BITMAP_BITS = 1 << 23
CLASS_RATIO = 1.2
SEEDS = 4  # hashings tried for sets that leave too many groups empty


class Threshold:
    """Jaccard similarity of at least num / den, in whole numbers."""

    def __init__(self, num: int, den: int):
        if not 0 < num <= den:
            raise ValueError("the threshold must be in (0, 1]")
        self.num, self.den = num, den

    def overlap(self, sizes: int | np.ndarray) -> int | np.ndarray:
        """Least intersection of two sets of ``sizes`` elements together."""
        return -(-self.num * sizes // (self.num + self.den))

    def differ(self, sizes: int) -> int:
        return sizes - 2 * int(self.overlap(sizes))

    def size_class(self, n: int) -> tuple[int, int, int]:
        """Number, least and greatest size of the class of ``n``."""
        at, lo = 0, 1
        while True:
            hi = max(lo, int(lo * CLASS_RATIO))
            if n <= hi:
                return at, lo, hi
            at, lo = at + 1, hi + 1

    def classes(self, n: int) -> list[tuple[int, int, int]]:
        """Classes in which a set of ``n`` meets every partner: its own, and those above that a partner can be in.

        Of each: number, groups, and how many of them may be empty.
        """
        out = []
        at, lo, hi = self.size_class(n)
        most = n * self.den // self.num
        while lo <= most:
            h = max((self.differ(hi + m) for m in (hi, hi - 1) if m > 0), default=0)
            slack = 2 + h // 16 if h else 0
            out.append((at, h + 1 + slack, slack))
            at, lo = at + 1, hi + 1
            hi = max(lo, int(lo * CLASS_RATIO))
        return out


def signatures(s: np.ndarray, classes: list[tuple[int, int, int]]) -> np.ndarray:
    """Hashes of (class, group, content) of the groups that are not empty.

    Of the groups of two linked sets, more than ``slack`` are equal.  If either set has no more than ``slack``
    empty groups, an equal one is not empty.  Sets with more of them are hashed anew with up to four seeds, and at last
    get one signature for all such sets of the class.
    """
    out = []
    for at, groups, slack in classes:
        for seed in range(SEEDS + 1):
            tag = np.uint64((at << 40) + (seed << 32) + 0x51ED)
            if seed == SEEDS:
                out.append(mix(np.array([tag], np.uint64)))
                break
            g = (mix(s + np.uint64(seed * 0x9E3779B1 + 77)) % np.uint64(groups)).astype(np.int64)
            total = np.zeros(groups, np.uint64)
            np.add.at(total, g, mix(s ^ np.uint64(0xA5A5A5A5A5A5A5A5)))
            count = np.bincount(g, minlength=groups)
            full = np.flatnonzero(count)
            out.append(mix(mix(total[full] + count[full].astype(np.uint64)) + (full.astype(np.uint64) << np.uint64(8)) + mix(np.array([tag], np.uint64))[0]))
            if groups - len(full) <= slack:
                break
    return np.concatenate(out)


def _signed(a: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(a).view(np.int64)


def set_hash(s: np.ndarray) -> int:
    return int(_signed(mix(np.bitwise_xor.reduce(mix(s + np.uint64(1)), keepdims=True) + np.add.reduce(s, keepdims=True) + np.uint64(len(s))))[0])


_ROW = pa.schema([("key", pa.int64()), ("a", pa.int64()), ("n", pa.int64()), ("node", pa.int64()), ("vec", pa.binary())])
_ROW_DDL = "key long, a long, n long, node long, vec binary"


def _rows(key, a, n, node, vec) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip((key, a, n, node, vec), _ROW)], schema=_ROW)


def _signature_rows(key: np.ndarray, node: np.ndarray) -> pa.RecordBatch:
    m = len(key)
    return pa.RecordBatch.from_arrays([pa.array(key), pa.array(node), *[pa.nulls(m, f.type) for f in _ROW][2:]], schema=_ROW)


def _describe(k: int, threshold: Threshold):
    """Rows for the shuffle: each document (id, size, set and count vector) and the signatures of each set seen first in its task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        classes = functools.cache(threshold.classes)
        for batch in batches:
            ids, texts = (c.to_pylist() for c in batch.columns)
            for lo, hi in chunks(texts):
                docs, keys, nodes = [], [], []
                for doc, s in zip(ids[lo:hi], shingle_sets(texts[lo:hi], k)):
                    node = vec = None
                    if len(s) and doc is not None:
                        node = set_hash(s)
                        if node not in seen:
                            seen.add(node)
                            vec = count_vector(s).tobytes()
                            keys.append(_signed(signatures(s, classes(len(s)))))
                            nodes.append(np.full(len(keys[-1]), node))
                    docs.append(((doc or 0) * 0x9E3779B97F4A7C15 + 2**63 & 2**64 - 1, doc, len(s), node, vec))
                key, *rest = zip(*docs)
                yield _rows(_signed(np.array(key, np.uint64)), *rest)
                if keys:
                    yield _signature_rows(np.concatenate(keys), np.concatenate(nodes))
            if len(seen) > SEEN:
                seen.clear()

    return run


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by key and set: documents as they are, and the members of each bucket of more than one set.

    A small bucket is named by its members, so that sets that meet in many buckets are passed on once.  A large one is
    passed on as it comes; no bucket is held.
    """
    big = None  # key and last member of a large bucket that goes on
    held_k, held_v = np.empty(0, np.int64), np.empty(0, np.int64)

    def out(k: np.ndarray, v: np.ndarray, last: bool) -> Iterator[pa.RecordBatch]:
        nonlocal big, held_k, held_v
        k, v = np.concatenate((held_k, k)), np.concatenate((held_v, v))
        held_k = held_v = np.empty(0, np.int64)
        if not len(k):
            return
        fresh = np.concatenate(([big is None or k[0] != big[0] or v[0] != big[1]], (k[1:] != k[:-1]) | (v[1:] != v[:-1])))
        k, v = k[fresh], v[fresh]
        if big is not None and len(k):
            more = int(np.searchsorted(k != big[0], True)) if (k != big[0]).any() else len(k)
            if more:
                yield _signature_rows(k[:more], v[:more])
                big = (big[0], int(v[more - 1]))
            if more < len(k):
                big = None
            k, v = k[more:], v[more:]
        if not len(k):
            return
        start = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
        size = np.diff(np.concatenate((start, [len(k)])))
        end = len(k)
        if not last:
            if size[-1] <= SMALL_RUN:
                end = int(start[-1])
                held_k, held_v = k[end:], v[end:]
                start, size = start[:-1], size[:-1]
            else:
                big = (int(k[-1]), int(v[-1]))
        if not len(start):
            return
        each = np.repeat(size, size)
        names = np.repeat(_signed(mix(np.add.reduceat(mix(v[:end].view(np.uint64)), start))), size)
        keep = each > 1
        if keep.any():
            yield _signature_rows(np.where(each <= SMALL_RUN, names, k[:end])[keep], v[:end][keep])

    for batch in batches:
        doc = batch.column(2).is_valid()
        if doc.true_count:
            yield batch.filter(doc)
        if doc.true_count < len(doc):
            rest = batch.filter(pa.compute.invert(doc))
            yield from out(rest.column(0).to_numpy(), rest.column(1).to_numpy(), False)
    yield from out(np.empty(0, np.int64), np.empty(0, np.int64), True)


def coordinates(n: int) -> int:
    return next(g for most, g in COORDINATES if n < most)


def count_vector(s: np.ndarray, groups: int | None = None) -> np.ndarray:
    """Tokens of the set in each group; one that overflows 16 bits would be a set of millions and is held in 32."""
    return np.bincount((s % np.uint64(groups or coordinates(len(s)))).astype(np.int64), minlength=groups or coordinates(len(s))).astype(np.uint32)


def fold(vectors: list[np.ndarray]) -> np.ndarray:
    """Vectors with as many coordinates as the shortest has; groups of one remainder are summed."""
    least = min(map(len, vectors))
    return np.array([v.reshape(-1, least).sum(0) for v in vectors], np.int32)


class CountTree:
    """Bulk-loaded R-tree: points sorted by their sum and tiled by their largest spreads, boxes stored as upper corners and least sums."""

    def __init__(self, points: np.ndarray):
        n = len(points)
        self.points, self.size = points, points.sum(1)
        order = np.argsort(self.size, kind="stable")
        slab = max(LEAF, int(math.sqrt(n * LEAF)))
        spread = np.argmax(points.var(0)) if n else 0
        order = np.concatenate([x[np.argsort(points[x, spread], kind="stable")] for x in (order[i : i + slab] for i in range(0, n, slab))]) if n else order
        self.levels = [[order[i : i + LEAF] for i in range(0, n, LEAF)]]
        self.upper = [np.array([points[x].max(0) for x in self.levels[0]])]
        self.least = [np.array([self.size[x].min() for x in self.levels[0]])]
        while len(self.levels[-1]) > 1:
            m = len(self.levels[-1])
            kids = [np.arange(i, min(m, i + LEAF)) for i in range(0, m, LEAF)]
            self.levels.append(kids)
            self.upper.append(np.array([self.upper[-1][x].max(0) for x in kids]))
            self.least.append(np.array([self.least[-1][x].min() for x in kids]))

    def members(self, level: int, at: int) -> np.ndarray:
        """The points below a node."""
        if level == 0:
            return self.levels[0][at]
        return np.concatenate([self.members(level - 1, k) for k in self.levels[level][at]])

    def pairs(self, other: CountTree, threshold: Threshold, settled: Callable[[np.ndarray, np.ndarray], bool]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Index pairs, by leaf pair, whose summed coordinate minima reach the least overlap of their sizes.

        Node pairs all of whose points are ``settled`` are passed over.
        """
        if not len(self.points) or not len(other.points):
            return
        stack = [(len(self.levels) - 1, 0, len(other.levels) - 1, 0)]
        while stack:
            i, x, j, y = stack.pop()
            bound = int(np.minimum(self.upper[i][x], other.upper[j][y]).sum())
            if bound < threshold.overlap(int(self.least[i][x] + other.least[j][y])) or settled(self.members(i, x), other.members(j, y)):
                continue
            if i == 0 and j == 0:
                p, q = self.levels[0][x], other.levels[0][y]
                bounds = np.minimum(self.points[p][:, None, :], other.points[q][None, :, :]).sum(2)
                u, v = np.nonzero(bounds >= threshold.overlap(self.size[p][:, None] + other.size[q][None, :]))
                yield p[u], q[v]
            elif i >= j:
                stack.extend((i - 1, k, j, y) for k in self.levels[i][x])
            else:
                stack.extend((i, x, j - 1, k) for k in other.levels[j][y])


def forest(points: np.ndarray, side: np.ndarray, whole: bool, threshold: Threshold, verify: Callable[[int, int], bool]) -> list[tuple[int, int]]:
    """Spanning forest of the pairs within the bound that ``verify`` holds for: among all points if ``whole``, else between the sides."""
    label = np.arange(len(points))
    left = np.flatnonzero(side == 0)
    right = left if whole else np.flatnonzero(side == 1)
    tree = CountTree(points[left])
    other = tree if whole else CountTree(points[right])
    found: list[tuple[int, int]] = []

    def settled(p: np.ndarray, q: np.ndarray) -> bool:
        a, b = label[left[p]], label[right[q]]
        return bool((a == a[0]).all() and (b == a[0]).all())

    for us, vs in tree.pairs(other, threshold, settled):
        us, vs = left[us], right[vs]
        open_ = label[us] != label[vs]
        for u, v in zip(us[open_].tolist(), vs[open_].tolist()):
            if label[u] != label[v] and (not whole or u < v) and verify(u, v):
                label[label == label[v]] = label[u]
                found.append((u, v))
    return found


def linked_forest(sets: list[np.ndarray], side: np.ndarray, whole: bool, threshold: Threshold) -> list[tuple[int, int]]:
    """Spanning forest of the links among ``sets``."""

    def linked(u: int, v: int) -> bool:
        a, b = sets[u], sets[v]
        if len(a) > len(b):
            a, b = b, a
        at = np.searchsorted(b, a)
        at[at == len(b)] = 0
        return int((b[at] == a).sum()) >= threshold.overlap(len(a) + len(b))

    return forest(fold([count_vector(s) for s in sets]), side, whole, threshold, linked)


_EDGE = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _by_pair(solve: Callable[[list, np.ndarray, bool], list[tuple[int, int]]]):
    """Over rows (name, i, j, part, node, content) sorted by name, i and j: the edges that ``solve`` finds in each."""

    def close(rows: list[tuple]) -> pa.RecordBatch:
        i, j = rows[0][1], rows[0][2]
        node = [r[4] for r in rows]
        found = solve([r[5] for r in rows], np.array([0 if r[3] == i else 1 for r in rows]), i == j)
        return pa.RecordBatch.from_arrays([pa.array([node[u] for u, _ in found], pa.int64()), pa.array([node[v] for _, v in found], pa.int64())], schema=_EDGE)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        for batch in batches:
            for r in zip(*(c.to_pylist() for c in batch.columns)):
                if rows and rows[0][:3] != r[:3]:
                    if len(rows) > 1:
                        yield close(rows)
                    rows = []
                rows.append(r)
        if len(rows) > 1:
            yield close(rows)

    return run


def _edges(placed: DataFrame, content: str, solve) -> DataFrame:
    """``placed`` has ``name``, ``node``, ``parts`` and ``content``; every two parts of a name meet in one task."""
    parts = int(placed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    meets = F.expr("transform(sequence(0L, parts - 1), p -> struct(least(part, p) AS i, greatest(part, p) AS j))")
    spread = placed.withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts"))).select("name", "part", "node", content, F.explode(meets).alias("m"))
    pairs = spread.select("name", F.col("m.i").alias("i"), F.col("m.j").alias("j"), "part", "node", content)
    return pairs.repartition(parts, "name", "i", "j").sortWithinPartitions("name", "i", "j", "node").mapInArrow(released(_by_pair(solve)), "a long, b long")


def _bitmap(ids: DataFrame) -> bytes:
    """Bits of the hashed ids: 1 MB whatever their number; false positives only cost a larger shuffle."""
    h = ids.select((F.pmod(F.xxhash64("id"), F.lit(BITMAP_BITS)) + 1).alias("h"))  # the functions count bits from 1
    rows = h.groupBy(F.bitmap_bucket_number("h").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("h")).alias("bits")).collect()
    out = bytearray(BITMAP_BITS // 8)
    for r in rows:
        out[(r["k"] - 1) * 4096 : r["k"] * 4096] = r["bits"]
    return bytes(out)


def _texts_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Id and text of the documents in ``ids``; only those whose bit is set are shuffled."""
    spark = docs.sparkSession
    bits = spark.sparkContext.broadcast(_bitmap(ids))
    parts = BITMAP_BITS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b = np.frombuffer(bits.value, np.uint8)
        for batch in batches:
            h = batch.column(0).to_numpy(zero_copy_only=False)
            keep = (b[h // 8] >> (h % 8).astype(np.uint8)) & 1
            yield batch.filter(pa.array(keep.astype(bool))).select([1, 2])

    hashed = docs.where("id is not null").select(F.pmod(F.xxhash64("id"), F.lit(parts)).alias("h"), "id", "text")
    return hashed.mapInArrow(released(run), "id long, text string")


def ngram_classes(docs: DataFrame, key: str = "doc_id", text: str = "text", k: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """``key``, ``n_shingles`` and ``component_id`` (least key reachable by links) of every document."""
    threshold = Threshold(num, den)
    src = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = src.mapInArrow(released(_describe(k, threshold)), _ROW_DDL).repartition(parts, "key").sortWithinPartitions("key", "a")
    rows = materialise(dealt.mapInArrow(released(_buckets), _ROW_DDL), "ngram-rows")
    described = rows.where("n is not null").select(F.col("a").alias("id"), "node", "n")
    firsts = described.where("node is not null").groupBy("node").agg(F.min("id").alias("id"), F.max("n").alias("n"))
    vectors = rows.where("vec is not null").groupBy("node").agg(F.min("vec").alias("vec"))

    def within_bound(vecs: list[bytes], side: np.ndarray, whole: bool) -> list[tuple[int, int]]:
        return forest(fold([np.frombuffer(v, np.uint32) for v in vecs]), side, whole, threshold, lambda u, v: True)

    buckets = rows.where("n is null").select(F.col("key").alias("name"), F.col("a").alias("node")).distinct()
    sizes = buckets.groupBy("name").agg(F.ceil(F.count("*") / BUCKET_DOCS).cast("long").alias("parts"))
    blocks = components(_edges(buckets.join(sizes, "name").join(vectors, "node"), "vec", within_bound))
    members = materialise(blocks.join(firsts, "node").select("node", F.col("label").alias("name"), "id", "n"), "ngram-members")
    sizes = members.groupBy("name").agg(F.greatest(F.ceil(F.count("*") / PART_DOCS), F.ceil(F.sum("n") / PART_SHINGLES)).cast("long").alias("parts"))

    def verified(texts: list[str], side: np.ndarray, whole: bool) -> list[tuple[int, int]]:
        return linked_forest(shingle_sets(texts, k), side, whole, threshold)

    links = materialise(_edges(members.join(sizes, "name").join(_texts_of(src, members), "id"), "text", verified), "ngram-links")
    labels = components(links)
    of_label = labels.join(firsts, "node").groupBy("label").agg(F.min("id").alias("least"))
    answer = firsts.join(labels, "node", "left").join(of_label, "label", "left").select("node", F.coalesce("least", "id").alias("component_id"))
    return described.join(answer, "node", "left").select(F.col("id").alias(key), F.col("n").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"))


#: Documents to drop that may be broadcast; beyond it they are joined by a shuffle.
BROADCAST_DROPS = 500_000


def keep_firsts(docs: DataFrame, key: str = "doc_id", text: str = "text", k: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The rows of ``docs`` without those that have a smaller key in their class; of rows of one key, one stays."""
    classes = materialise(ngram_classes(docs, key, text, k, num, den).select(F.col(key).alias("_id"), "component_id"), "ngram-classes")
    drops = classes.where("_id <> component_id").select("_id").distinct()
    if drops.limit(BROADCAST_DROPS + 1).count() <= BROADCAST_DROPS:
        drops = F.broadcast(drops)
    out = docs.join(drops, F.col(key).eqNullSafe(F.col("_id")), "left_anti")
    again = classes.where("_id is not null").groupBy("_id").count().where("count > 1").select("_id")
    if again.isEmpty():
        return out
    once = out.join(again, out[key].eqNullSafe(again["_id"]), "left_anti")
    return once.unionByName(out.join(again, out[key] == again["_id"], "left_semi").dropDuplicates([key]))
