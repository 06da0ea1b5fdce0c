"""Path and tree counts by marks in many runs at once, the same numbers as ``tree``'s.

Marks and uniform draws depend on a run's seed alone, so runs that differ in epsilon share them, and a node's marks are drawn
once, not at each of its arcs.  Nodes are dealt to blocks by hash; a task holds a block's nodes, their arcs and the marks of
their neighbours, a few bits each, and computes with arrays.  What leaves it are sums for the nodes of another block, combined
by node and seed before the shuffle, and for each run the maxima that are public anyway.  Numbers are 64-bit integers wherever
a bound shows that they fit, else Python's of any length.
"""

from __future__ import annotations

import pickle
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import draws
from ..functions.pattern import RootedPattern
from ..sources.scratch import drop, pin
from ..sources.views import Graph

ARCS = 2_000_000  # of a block, about; a node's arcs are never parted
NUMBERS = 16_000_000  # nodes times runs of a block, about
CELLS = 8_000_000  # arcs times seeds that are looked at together
SAFE = 2.0**62
OUT = "block int, data binary, said binary"


@dataclass
class Seeds:
    """The runs by seed: ``eps[s, e]`` and ``run[s, e]``, -1 where a seed has fewer runs than another."""

    seeds: np.ndarray
    eps: np.ndarray
    run: np.ndarray

    @staticmethod
    def of(runs: DataFrame) -> Seeds:
        by: dict[int, list[tuple[int, float]]] = defaultdict(list)
        for r in runs.select("run", "seed", "eps").collect():
            by[r["seed"]].append((r["run"], r["eps"]))
        wide = max(map(len, by.values()), default=0)
        out = Seeds(np.array(sorted(by), np.int64), np.ones((len(by), wide)), np.full((len(by), wide), -1, np.int64))
        for i, s in enumerate(out.seeds.tolist()):
            for e, (run, eps) in enumerate(by[s]):
                out.eps[i, e], out.run[i, e] = eps, run
        return out


def block_labels(spark: SparkSession, blocks: int) -> list[int]:
    """A name for each block such that every partition by hash of the name holds one block."""
    found: dict[int, int] = {}
    size = 16 * blocks + 64
    while len(found) < blocks:
        found = {r["p"]: r["id"] for r in spark.range(size).select(F.col("id").cast("int").alias("id")).withColumn("p", F.pmod(F.hash("id"), F.lit(blocks))).collect()}
        size *= 2
    return [found[p] for p in range(blocks)]


def number_of_blocks(graph: Graph, runs: int) -> int:
    nodes, arcs = graph.nodes.count(), graph.arcs.count()
    return max(1, min(nodes, max(2 * graph.nodes.sparkSession.sparkContext.defaultParallelism, -(-arcs // ARCS), -(-nodes * runs // NUMBERS))))


def dealt(graph: Graph, blocks: int) -> DataFrame:
    """``block``, ``src``, ``dst``, ``to``: the arcs by the block of their source, and its nodes (``dst`` null)."""
    names = F.array(*[F.lit(x) for x in block_labels(graph.nodes.sparkSession, blocks)])
    label = lambda c: F.element_at(names, (F.pmod(F.xxhash64(c), F.lit(blocks)) + 1).cast("int"))
    arcs = graph.arcs.select(label(F.col("src")).alias("block"), F.col("src").cast("long"), F.col("dst").cast("long"), label(F.col("dst")).alias("to"))
    nodes = graph.nodes.select(label(F.col("id")).alias("block"), F.col("id").cast("long").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(None).cast("int").alias("to"))
    return arcs.unionByName(nodes)


def by_block(df: DataFrame, f, blocks: int) -> DataFrame:
    return df.repartition(blocks, "block").groupBy("block").applyInArrow(f, OUT)


def rows(out: list[tuple[int, object, object]]) -> pa.Table:
    coded = [[None if x is None else pickle.dumps(x, 5) for x in c] for c in ([r[1] for r in out], [r[2] for r in out])]
    return pa.table({"block": pa.array([r[0] for r in out], pa.int32()), "data": pa.array(coded[0], pa.binary()), "said": pa.array(coded[1], pa.binary())})


def column(t: pa.Table, name: str) -> np.ndarray:
    return t.column(name).to_numpy()


def read(t: pa.Table) -> list:
    return [pickle.loads(x.as_py()) for x in t.column("data") if x.is_valid]


def split(ids: np.ndarray, to: np.ndarray) -> list[tuple[int, np.ndarray]]:
    """The distinct ids for each block that they go to."""
    order = np.lexsort((ids, to))
    ids, to = ids[order], to[order]
    new = np.ones(len(ids), bool)
    new[1:] = (ids[1:] != ids[:-1]) | (to[1:] != to[:-1])
    ids, to = ids[new], to[new]
    cuts = np.flatnonzero(np.r_[True, to[1:] != to[:-1]]) if len(to) else np.empty(0, int)
    return [(int(to[lo]), ids[lo:hi]) for lo, hi in zip(cuts, np.r_[cuts[1:], len(to)])]


# Numbers.
def largest(x: np.ndarray) -> float:
    return float(np.abs(x).max()) if x.size else 0.0


def long_numbers(x: np.ndarray) -> np.ndarray:
    return x.astype(object)


def product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    if a.dtype != object and b.dtype != object and largest(a) * largest(b) < SAFE:
        return a * b
    return long_numbers(a) * long_numbers(b)


def plus(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    if a.dtype != object and b.dtype != object and largest(a) + largest(b) < SAFE:
        return a + b
    return long_numbers(a) + long_numbers(b)


def whole_numbers(x: np.ndarray) -> np.ndarray:
    """Doubles rounded half away from zero."""
    r = np.trunc(x)
    r += np.where(np.abs(x - r) >= 0.5, np.sign(x), 0.0)
    if largest(r) < SAFE:
        return r.astype(np.int64)
    return np.array([int(v) for v in r.ravel().tolist()], object).reshape(r.shape)


def grouped(at: np.ndarray, x: np.ndarray, size: int, ufunc=np.add) -> np.ndarray:
    """``ufunc`` over the rows of ``x`` with equal ``at``; 0 where there is none."""
    if ufunc is np.add and x.dtype != object and largest(x) * max(1, len(x)) >= SAFE:
        x = long_numbers(x)
    out = np.zeros((size, x.shape[1]), x.dtype)
    if len(at):
        order = np.argsort(at, kind="stable")
        own = at[order]
        starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
        out[own[starts]] = ufunc.reduceat(x[order], starts, axis=0)
    return out


def joined(parts: list[np.ndarray]) -> np.ndarray:
    if any(p.dtype == object for p in parts):
        parts = [long_numbers(p) for p in parts]
    return np.concatenate(parts)


def drawn(seed, purpose: str, ids: np.ndarray) -> np.ndarray:
    """``draws.hashed``, of negative numbers too."""
    seeds = np.broadcast_to(np.asarray(seed, np.int64), ids.shape)
    if len(ids) and (ids.min() < 0 or seeds.min() < 0):
        return draws.hashed_any(seeds, purpose, ids)
    if len(ids) == 0:
        return np.empty(0, np.int64)
    return draws.hashed(seed if np.ndim(seed) == 0 else seeds, purpose, ids)


def laplace_of_one(h: np.ndarray) -> np.ndarray:
    """What minus the scale is multiplied by."""
    u = (h.astype(np.float64) + 0.5) / draws.TWO_52 - 0.5
    return np.sign(u) * np.log(1.0 - 2.0 * np.abs(u))


# Marks in a few bits.
def packed(m: np.ndarray, planes: int) -> np.ndarray:
    """Of ``m`` (nodes, seeds) in uint8: (planes, nodes, bytes)."""
    return np.stack([np.packbits((m >> p) & 1, axis=1) for p in range(planes)])


def unpacked(bits: np.ndarray, lo: int, hi: int) -> np.ndarray:
    """The marks of the seeds ``lo`` to ``hi``; ``lo`` is a multiple of 8."""
    out = np.zeros((bits.shape[1], hi - lo), np.uint8)
    for p in range(len(bits)):
        out |= np.unpackbits(np.ascontiguousarray(bits[p][:, lo // 8 : -(-hi // 8)]), axis=1, count=hi - lo) << p
    return out


@dataclass
class Shape:
    """A rooted pattern as tables by vertex."""

    tree: RootedPattern
    planes: int
    up: np.ndarray  # the parent; 255 at the root
    slot: np.ndarray  # of a leaf among its parent's leaves; 255 for others
    width: int
    sends: np.ndarray  # internal and not the root

    @staticmethod
    def of(tree: RootedPattern) -> Shape:
        n = tree.k + 1
        up = np.array([255 if p is None else p for p in tree.parent], np.uint8)
        slot = np.full(n, 255, np.uint8)
        for v in range(n):
            for i, c in enumerate(c for c in tree.children[v] if c in tree.leaves):
                slot[c] = i
        sends = np.array([v in tree.internal and v != tree.root for v in range(n)])
        return Shape(tree, max(1, tree.k.bit_length()), up, slot, max([int(s) + 1 for s in slot if s != 255], default=1), sends)


@dataclass
class Chunk:
    """The state of a block for the seeds ``lo`` to ``hi``; keys are node * seeds + seed."""

    lo: int
    hi: int
    marks: np.ndarray  # packed
    leaves: dict[int, np.ndarray]  # of vertices yet to come: the neighbours that hold each leaf, by holder
    down: dict[int, tuple[np.ndarray, np.ndarray]]  # of children yet to come: keys and neighbours that get their counts


@dataclass
class Block:
    label: int
    ids: np.ndarray
    near: np.ndarray  # neighbours by block and id
    to: np.ndarray
    chunks: list[Chunk] = field(default_factory=list)


def smallest(x: np.ndarray) -> np.ndarray:
    return x.astype(np.min_scalar_type(int(x.max()) if x.size else 0))


def _deal(shape: Shape, seeds: Seeds):
    """A block's nodes with marks to itself, and the marks of those with arcs to another block to that."""
    k = shape.tree.k

    def run(t: pa.Table) -> pa.Table:
        label = t.column("block")[0].as_py()
        src, arc = column(t, "src"), t.column("dst").is_valid().to_numpy()
        ids = np.unique(src[~arc])
        m = np.empty((len(ids), len(seeds.seeds)), np.uint8)
        for i, s in enumerate(seeds.seeds.tolist()):
            m[:, i] = drawn(s, "mark", ids) % (k + 1)
        bits = packed(m, shape.planes)
        src, dst, to = src[arc], column(t.filter(pa.array(arc)), "dst"), column(t.filter(pa.array(arc)), "to")
        out: list[tuple[int, object, object]] = [(label, ("own", ids, bits, src, dst, to), None)]
        for j, u in split(src, to):
            out.append((j, ("near", u, bits[:, np.searchsorted(ids, u)], label), None))
        return rows(out)

    return run


def _first(shape: Shape, seeds: Seeds):
    """From marks: what leaves add to every vertex, and the first level."""
    tree, n_seeds = shape.tree, len(seeds.seeds)

    def run(t: pa.Table) -> pa.Table:
        got = read(t)
        _, ids, bits, src, dst, _ = next(x for x in got if x[0] == "own")
        others = [x for x in got if x[0] == "near"]
        label = t.column("block")[0].as_py()
        near = np.concatenate([x[1] for x in others]) if others else np.empty(0, np.int64)
        to = np.concatenate([np.full(len(x[1]), x[3], np.int32) for x in others]) if others else np.empty(0, np.int32)
        near_bits = np.concatenate([x[2] for x in others], axis=1) if others else np.empty((shape.planes, 0, -(-n_seeds // 8)), np.uint8)
        order = np.lexsort((near, to))
        near, to, near_bits = near[order], to[order], near_bits[:, order]
        del got, others
        by_id = np.argsort(near)
        at = np.searchsorted(ids, src)
        order = np.argsort(at, kind="stable")
        at = at[order]
        nb = by_id[np.searchsorted(near[by_id], dst[order])] if len(dst) else np.empty(0, np.int64)
        block = Block(label, ids, near, to)
        said = {"nodes": np.zeros((n_seeds, tree.k + 1), np.int64), "sent": np.zeros(n_seeds, np.int64), "arcs": len(at), "n": len(ids)}
        step = max(8, CELLS // max(1, len(at)) // 8 * 8)
        for lo in range(0, n_seeds, step):
            hi = min(n_seeds, lo + step)
            s = hi - lo
            own = unpacked(bits, lo, hi)
            counts = np.zeros(shape.width * len(ids) * s, np.int64)
            down: dict[int, list] = {v: [] for v in tree.internal if v != tree.root}
            other = unpacked(near_bits, lo, hi)
            part = max(1, CELLS // s)
            for a in range(0, len(at), part):
                own_arc, near_arc = at[a : a + part], nb[a : a + part]
                mine, theirs = own[own_arc].ravel(), other[near_arc].ravel()
                hit = np.flatnonzero(shape.up[theirs] == mine)
                leaf = shape.slot[theirs[hit]]
                hit, leaf = hit[leaf != 255], leaf[leaf != 255].astype(np.int64)
                keys = own_arc[hit // s] * s + hit % s
                first = int(own_arc[0]) * s
                span = (int(own_arc[-1]) + 1) * s - first
                for i in range(shape.width):
                    base = i * len(ids) * s + first
                    counts[base : base + span] += np.bincount(keys[leaf == i] - first, minlength=span)
                hit = np.flatnonzero((shape.up[mine] == theirs) & shape.sends[mine])
                vertex, keys, to_near = mine[hit], (own_arc[hit // s] * s + hit % s).astype(np.int64), near_arc[hit // s].astype(np.int32)
                said["sent"][lo:hi] += np.bincount(hit % s, minlength=s)
                for v in down:
                    down[v].append((keys[vertex == v], to_near[vertex == v]))
            for v in range(tree.k + 1):
                said["nodes"][lo:hi, v] += (own == v).sum(0)
            counts = counts.reshape(shape.width, -1)
            leaves = {}
            for v in tree.internal:
                held = np.flatnonzero(own.ravel() == v)
                for c in tree.children[v]:
                    if c in tree.leaves:
                        leaves[c] = smallest(counts[shape.slot[c]][held])
            sent = {v: tuple(np.concatenate(x) for x in zip(*parts)) if parts else (np.empty(0, np.int64), np.empty(0, np.int32)) for v, parts in down.items()}
            block.chunks.append(Chunk(lo, hi, packed(own, shape.planes), leaves, sent))
        return _level(shape, seeds, block, 0, {}, {}, said)

    return run


def _level(shape: Shape, seeds: Seeds, block: Block, number: int, peaks: dict[int, np.ndarray], sums: dict[int, tuple], said: dict) -> pa.Table:
    """Counts of one level's vertices in a block; ``sums`` by child: ids, seeds and values that other nodes sent."""
    tree, wide = shape.tree, seeds.eps.shape[1]
    level = tree.levels[number]
    out: dict[int, dict[int, list]] = defaultdict(lambda: defaultdict(list))
    for v in level:
        said[v] = np.zeros((len(seeds.seeds), wide + 1), object if v == tree.root else np.float64)
    for chunk in block.chunks:
        s = chunk.hi - chunk.lo
        marks = unpacked(chunk.marks, 0, s).ravel()
        for v in level:
            held = np.flatnonzero(marks == v)
            node, seed = held // s, held % s
            x = None
            for c in tree.children[v]:
                if c in tree.leaves:
                    scale = 1.0 / seeds.eps
                    y = np.repeat(chunk.leaves.pop(c).astype(np.int64)[:, None], wide + 1, 1)
                else:
                    scale = peaks[c][:, :wide] / seeds.eps
                    ids, at, values = sums.get(c, (None, None, None))
                    y = np.zeros((len(held), wide + 1), np.int64)
                    if ids is not None:
                        here = np.flatnonzero((at >= chunk.lo) & (at < chunk.hi))
                        keys = np.searchsorted(block.ids, ids[here]) * s + (at[here] - chunk.lo)
                        y = grouped(np.searchsorted(held, keys), values[here], len(held))
                one = laplace_of_one(drawn(seeds.seeds[chunk.lo + seed], f"t{c}", block.ids[node]))
                noise = whole_numbers(-scale[chunk.lo + seed] * one[:, None])
                y = plus(y, np.concatenate([noise, np.zeros((len(held), 1), noise.dtype)], 1))
                x = y if x is None else product(x, y)
            if v == tree.root:
                said[v][chunk.lo : chunk.hi] = grouped(seed, x, s).astype(object)
                continue
            said[v][chunk.lo : chunk.hi] = grouped(seed, np.abs(x), s, np.maximum).astype(np.float64)
            keys, near = chunk.down.pop(v)
            together = near.astype(np.int64) * s + keys % s
            own, inverse = np.unique(together, return_inverse=True)
            values = grouped(inverse, x[np.searchsorted(held, keys)], len(own))
            near = own // s
            cuts = np.flatnonzero(np.r_[True, block.to[near][1:] != block.to[near][:-1]]) if len(near) else np.empty(0, int)
            for a, b in zip(cuts, np.r_[cuts[1:], len(near)]):
                out[int(block.to[near[a]])][v].append((block.near[near[a:b]], (own[a:b] % s + chunk.lo).astype(np.int32), values[a:b]))
    last = number + 1 == len(tree.levels)
    made: list[tuple[int, object, object]] = [(block.label, None if last else block, said)]
    for j, parts in out.items():
        made.append((j, {v: tuple(joined(list(p)) for p in zip(*ps)) for v, ps in parts.items()}, None))
    return rows(made)


def _next(shape: Shape, seeds: Seeds, number: int, peaks: dict[int, np.ndarray]):
    inner = {c for v in shape.tree.levels[number] for c in shape.tree.children[v] if c not in shape.tree.leaves}

    def run(t: pa.Table) -> pa.Table:
        got = read(t)
        block = next((x for x in got if isinstance(x, Block)))
        parts: dict[int, list] = defaultdict(list)
        later: dict[int, list] = defaultdict(list)
        for x in got:
            if isinstance(x, dict):
                for c, p in x.items():
                    (parts if c in inner else later)[c].append(p)
        sums = {c: tuple(joined(list(q)) for q in zip(*ps)) for c, ps in parts.items()}
        made = _level(shape, seeds, block, number, peaks, sums, {})
        if later:
            made = pa.concat_tables([made, rows([(block.label, {c: tuple(joined(list(q)) for q in zip(*ps)) for c, ps in later.items()}, None)])])
        return made

    return run


@dataclass
class Totals:
    estimate: DataFrame  # run, estimate, marked_estimate, rounds
    sent: DataFrame  # run, channel, messages, bytes


def tree_totals(graph: Graph, runs: DataFrame, tree: RootedPattern) -> Totals:
    """The results of ``tree.tree_dp`` and ``cost.tree_measured`` for all runs; only sums and maxima of runs reach the driver."""
    spark = graph.nodes.sparkSession
    seeds, shape = Seeds.of(runs), Shape.of(tree)
    blocks = number_of_blocks(graph, seeds.run.size)
    df = by_block(by_block(dealt(graph, blocks), _deal(shape, seeds), blocks), _first(shape, seeds), blocks)
    peaks: dict[int, np.ndarray] = {}
    nodes, sent, arcs, n = np.zeros((len(seeds.seeds), tree.k + 1), np.int64), np.zeros(len(seeds.seeds), np.int64), 0, 0
    total, written = np.zeros((len(seeds.seeds), seeds.eps.shape[1] + 1), object), None
    for number, level in enumerate(tree.levels):
        df = pin(df, "level", "zstd")
        if written is not None:
            drop(written)
        written = df
        for row in df.where("said is not null").select("said").toLocalIterator():
            said = pickle.loads(row["said"])
            for v in level:
                if v == tree.root:
                    total = total + said[v]
                else:
                    peaks[v] = np.maximum(peaks[v], said[v]) if v in peaks else said[v]
            if not number:
                nodes, sent, arcs, n = nodes + said["nodes"], sent + said["sent"], arcs + said["arcs"], n + said["n"]
        if number + 1 < len(tree.levels):
            df = by_block(df.where("data is not null").select("block", "data"), _next(shape, seeds, number + 1, dict(peaks)), blocks)
    drop(written)
    inner = [v for v in tree.internal if v != tree.root]
    got, told = [], []
    for s, e in zip(*np.nonzero(seeds.run >= 0)):
        run = int(seeds.run[s, e])
        got.append((run, str(int(total[s, e]) * tree.factor), str(int(total[s, -1]) * tree.factor)))
        downward = sum(int(nodes[s, v]) * sum(c in inner for c in tree.children[v]) for v in tree.internal)
        for name, m in (("marks", arcs + n), ("node_to_node", int(sent[s])), ("node_to_analyzer", int(nodes[s, tree.internal].sum())), ("analyzer_to_node", downward)):
            told.append((run, name, m, 8 * m))
    whole = [F.col(c).cast("decimal(38,0)").alias(c) for c in ("estimate", "marked_estimate")]
    estimate = spark.createDataFrame(got, "run int, estimate string, marked_estimate string").select("run", *whole, F.lit(tree.rounds).alias("rounds"))
    return Totals(estimate, spark.createDataFrame(told, "run int, channel string, messages long, bytes long"))


def tree_dp(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``tree.tree_dp`` for many runs."""
    return tree_totals(graph, runs, tree).estimate


# Walks of three edges: what the first round releases is a function of a node's degree and draws, so these are sent, for all epsilons.
def _first_peaks(seeds: Seeds, k: int):
    def run(batches):
        top = np.zeros(seeds.eps.shape)
        for b in batches:
            ids, degree = b.column("id").to_numpy(), b.column("degree").to_numpy()
            if len(ids):
                for i, s in enumerate(seeds.seeds.tolist()):
                    one = laplace_of_one(drawn(s, "1", ids))
                    for e, eps in enumerate(seeds.eps[i].tolist()):
                        top[i, e] = max(top[i, e], largest(plus(degree, whole_numbers(-(2.0 * k / eps) * one))))
        yield pa.RecordBatch.from_pydict({"said": pa.array([pickle.dumps(top, 5)], pa.binary())})

    return run


def _send_degrees(seeds: Seeds):
    def run(t: pa.Table) -> pa.Table:
        label, src, arc = t.column("block")[0].as_py(), column(t, "src"), t.column("dst").is_valid().to_numpy()
        ids, arcs = np.unique(src[~arc]), t.filter(pa.array(arc))
        src, dst, to = src[arc], column(arcs, "dst"), column(arcs, "to")
        degree = np.bincount(np.searchsorted(ids, src), minlength=len(ids)).astype(np.int64)
        ones = np.stack([laplace_of_one(drawn(s, "1", ids)) for s in seeds.seeds.tolist()])
        out: list[tuple[int, object, object]] = [(label, ("own", ids, degree, src, dst), None)]
        for j, u in split(src, to):
            at = np.searchsorted(ids, u)
            out.append((j, ("near", u, degree[at], ones[:, at]), None))
        return rows(out)

    return run


def _second_round(seeds: Seeds, k: int, peaks: np.ndarray, last: int):
    """The sums over a block's nodes of the second round's counts times the noisy degrees."""

    def run(t: pa.Table) -> pa.Table:
        got = read(t)
        _, ids, degree, src, dst = next(x for x in got if x[0] == "own")
        others = [x for x in got if x[0] == "near"]
        total = np.zeros(seeds.eps.shape, object)
        at = np.searchsorted(ids, src)
        order = np.argsort(at, kind="stable")
        at = at[order]
        starts = np.flatnonzero(np.r_[True, at[1:] != at[:-1]]) if len(at) else np.empty(0, int)
        near = np.concatenate([x[1] for x in others]) if others else np.empty(0, np.int64)
        by_id = np.argsort(near)
        nb = np.searchsorted(near[by_id], dst[order])
        near_degree = np.concatenate([x[2] for x in others])[by_id] if others else near
        ones = np.concatenate([x[3] for x in others], axis=1)[:, by_id] if others else np.empty((len(seeds.seeds), 0))
        for i, s in enumerate(seeds.seeds.tolist()):
            second, own = laplace_of_one(drawn(s, "2", ids)), laplace_of_one(drawn(s, str(last), ids))
            for e, eps in enumerate(seeds.eps[i].tolist()):
                first = plus(near_degree, whole_numbers(-(2.0 * k / eps) * ones[i]))
                if first.dtype != object and largest(first) * max(1, len(at)) >= SAFE:
                    first = long_numbers(first)
                x = np.zeros(len(ids), first.dtype)
                if len(at):
                    x[at[starts]] = np.add.reduceat(first[nb], starts)
                x = plus(x, whole_numbers(-(2.0 * k / eps * peaks[i, e]) * second))
                z = product(x, plus(degree, whole_numbers(-(2.0 * k / eps) * own)))
                total[i, e] = int((z if largest(z) * max(1, len(z)) < SAFE else long_numbers(z)).sum())
        return rows([(t.column("block")[0].as_py(), None, total)])

    return run


def walk3_dp(graph: Graph, runs: DataFrame) -> DataFrame:
    """``walk.walk_dp`` of three edges for many runs: ``run``, ``estimate``, ``rounds``."""
    from .walk import DEGREE_ROUND

    k, spark, seeds = 3, graph.nodes.sparkSession, Seeds.of(runs)
    blocks = number_of_blocks(graph, seeds.seeds.size)
    peaks = np.zeros(seeds.eps.shape)
    parts = graph.degrees().repartition(2 * spark.sparkContext.defaultParallelism)
    for row in parts.mapInArrow(_first_peaks(seeds, k), "said binary").collect():
        peaks = np.maximum(peaks, pickle.loads(row["said"]))
    total = np.zeros(seeds.eps.shape, object)
    sums = by_block(by_block(dealt(graph, blocks), _send_degrees(seeds), blocks), _second_round(seeds, k, peaks, DEGREE_ROUND), blocks)
    for row in sums.select("said").collect():
        total = total + pickle.loads(row["said"])
    got = [(int(seeds.run[s, e]), str(int(total[s, e]))) for s, e in zip(*np.nonzero(seeds.run >= 0))]
    return spark.createDataFrame(got, "run int, estimate string").select("run", F.col("estimate").cast("decimal(38,0)").alias("estimate"), F.lit(k - 1).alias("rounds"))
