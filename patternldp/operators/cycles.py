"""Injective counts of a tree from maps that may repeat vertices.

Every map of a pattern is injective on exactly one of its quotients, so a pattern's injective count is that of its maps less
the injective counts of its proper quotients.  Quotients of trees with cycles start from the maps that are injective on the
cycles' vertices; only quotients that keep these apart are taken off.  What is left are counts of trees, by sums over
neighbours, and of cycles with trees hung on them.  In a forest the latter are none.
"""

from __future__ import annotations

import itertools
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import Pattern
from ..sources.scratch import pin
from ..sources.views import Graph
from .kernel import whole

Edges = tuple[tuple[int, int], ...]
Tree = tuple  # the sorted trees below a root
PEELS = 3  # rounds that take away nodes with one neighbour; more would only save work


def _near(edges: Edges, n: int) -> list[list[int]]:
    out: list[list[int]] = [[] for _ in range(n)]
    for a, b in edges:
        out[a].append(b)
        out[b].append(a)
    return out


@lru_cache(None)
def _canonical(edges: Edges, n: int) -> tuple[Edges, tuple[int, ...]]:
    """The least edges under renamings that order vertices by degree and neighbours' degrees, and the renaming."""
    near = _near(edges, n)
    colour = [(len(x), sorted(len(near[y]) for y in x)) for x in near]
    groups = [list(g) for _, g in itertools.groupby(sorted(range(n), key=lambda v: colour[v]), key=lambda v: colour[v])]
    best = None
    for ps in itertools.product(*[itertools.permutations(g) for g in groups]):
        name = {v: i for i, v in enumerate(itertools.chain(*ps))}
        e = tuple(sorted(tuple(sorted((name[a], name[b]))) for a, b in edges))
        if best is None or e < best[0]:
            best = e, tuple(name[v] for v in range(n))
    return best


def _core(edges: Edges, n: int) -> list[int]:
    """The vertices on or between cycles."""
    left, near = set(range(n)), _near(edges, n)
    while ends := [v for v in left if sum(y in left for y in near[v]) < 2]:
        left -= set(ends)
    return sorted(left)


def _partitions(n: int) -> Iterator[list[int]]:
    """The block of each vertex, blocks numbered by their first."""
    def grow(at: list[int]) -> Iterator[list[int]]:
        if len(at) == n:
            yield at
            return
        for b in range(max(at, default=-1) + 2):
            yield from grow([*at, b])

    return grow([])


@lru_cache(None)
def _injective(edges: Edges, n: int) -> Counter:
    """Weights of the starting counts of (edges, n) patterns in the injective count."""
    out = Counter({(edges, n): 1})
    core = _core(edges, n)
    for block in _partitions(n):
        m = max(block) + 1
        if m == n or len({block[v] for v in core}) < len(core) or any(block[a] == block[b] for a, b in edges):
            continue
        quotient = tuple(sorted({tuple(sorted((block[a], block[b]))) for a, b in edges}))
        for key, weight in _injective(_canonical(quotient, m)[0], m).items():
            out[key] -= weight
    return out


def expansion(pattern: Pattern) -> tuple[dict, dict]:
    """Weights of trees and of patterns with cycles, by edges and number of vertices."""
    got = {k: w for k, w in _injective(tuple(tuple(sorted(e)) for e in pattern.edges), pattern.n).items() if w}
    return {k: w for k, w in got.items() if len(k[0]) == k[1] - 1}, {k: w for k, w in got.items() if len(k[0]) >= k[1]}


def _below(near: list[list[int]], v: int, stop: set[int]) -> Tree:
    return tuple(sorted(_below(near, w, stop | {v}) for w in near[v] if w not in stop))


def height(t: Tree) -> int:
    return 1 + max(map(height, t)) if t else 0


def rooted(edges: Edges, n: int) -> Tree:
    """The tree from a root that keeps it low."""
    near = _near(edges, n)
    return min((_below(near, v, set()) for v in range(n)), key=lambda t: (height(t), t))


def shapes(cyclic: dict) -> dict[tuple[Edges, int], list[tuple[int, tuple[Tree, ...]]]]:
    """By the edges of the cycles: the weights and the trees at each vertex."""
    out: dict = {}
    for (edges, n), weight in cyclic.items():
        core, near = _core(edges, n), _near(edges, n)
        own = {v: i for i, v in enumerate(core)}
        shape, name = _canonical(tuple(sorted((own[a], own[b]) for a, b in edges if a in own and b in own)), len(core))
        at: list[Tree] = [()] * len(core)
        for v in core:
            at[name[own[v]]] = _below(near, v, set(core))
        out.setdefault((shape, len(core)), []).append((weight, tuple(at)))
    return out


@dataclass
class Sums:
    table: DataFrame  # id and, for each tree, the sum over neighbours of the maps of the tree rooted there
    column: dict[Tree, str]

    def product(self, trees: Tree, prefix: str = "") -> Column:
        return reduce(lambda a, t: whole(a * F.col(prefix + self.column[t])), trees, whole(1))


def neighbour_sums(graph: Graph, trees: set[Tree]) -> Sums:
    """Of nodes with a neighbour, level by level of the trees' heights."""
    todo, need = list(trees | {()}), set()
    while todo:
        t = todo.pop()
        if t not in need:
            need.add(t)
            todo += t
    column = {t: f"s{i}" for i, t in enumerate(sorted(need, key=lambda t: (height(t), t)))}
    out = Sums(graph.arcs.groupBy(F.col("dst").alias("id")).agg(whole(F.count("*")).alias(column[()])), column)
    for h in range(1, max(map(height, need)) + 1):
        out.table = pin(out.table, "sums")
        here = [t for t in column if height(t) == h]
        sent = graph.arcs.join(out.table.select(F.col("id").alias("src"), *[out.product(t).alias(column[t]) for t in here]), "src")
        out.table = out.table.join(sent.groupBy(F.col("dst").alias("id")).agg(*[F.sum(column[t]).cast("decimal(38,0)").alias(column[t]) for t in here]), "id")
    out.table = pin(out.table, "sums")
    return out


def without_ends(graph: Graph) -> DataFrame:
    """The arcs after ``PEELS`` rounds that take away nodes with one neighbour; all cycles are there."""
    arcs = graph.arcs
    for _ in range(PEELS):
        keep = arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d")).where("d > 1")
        arcs = arcs.join(keep.select(F.col("id").alias("src")), "src", "left_semi").join(keep.select(F.col("id").alias("dst")), "dst", "left_semi").select("src", "dst")
        arcs = pin(arcs, "core")
    return arcs


def closed(arcs: DataFrame, sums: Sums, edges: Edges, n: int, terms: list[tuple[int, tuple[Tree, ...]]]) -> DataFrame:
    """``ordered``: over the injective placements of the cycles, the weighted products of what hangs on their vertices."""
    placed, seen, todo = None, [], list(edges)
    while todo:
        e = next((x for x in todo if x[0] in seen and x[1] in seen), None) or next(x for x in todo if not seen or x[0] in seen or x[1] in seen)
        todo.remove(e)
        step = arcs.select(F.col("src").alias(f"v{e[0]}"), F.col("dst").alias(f"v{e[1]}"))
        placed = step if placed is None else placed.join(step, [f"v{v}" for v in e if v in seen])
        for new in [v for v in e if v not in seen]:
            for v in seen:
                placed = placed.where(F.col(f"v{v}") != F.col(f"v{new}"))
            seen.append(new)
    for v in range(n):
        own = sorted({t for _, at in terms for t in at[v]}, key=str)
        if own:
            placed = placed.join(sums.table.select(F.col("id").alias(f"v{v}"), *[F.col(sums.column[t]).alias(f"v{v}_{sums.column[t]}") for t in own]), f"v{v}")
    value = whole(0)
    for weight, at in terms:
        value = whole(value + reduce(lambda a, v: whole(a * sums.product(at[v], f"v{v}_")), range(n), whole(weight)))
    return placed.agg(F.coalesce(F.sum(value).cast("decimal(38,0)"), whole(0)).alias("ordered"))
