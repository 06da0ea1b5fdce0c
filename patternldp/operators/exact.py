"""Ground truth: exact counts by joins, closed forms, and repeated-vertex corrections."""

from __future__ import annotations

import itertools
import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import Pattern, RootedPattern
from ..sources.views import Graph
from . import cycles
from .kernel import whole

FORMS = ("walk", "path2", "path3", "fork", "star")


def _one(df: DataFrame, value: Column) -> DataFrame:
    return df.agg(F.coalesce(F.sum(value).cast("decimal(38,0)"), whole(0)).alias("ordered"))


def tree_exact(graph: Graph, pattern: Pattern) -> DataFrame:
    """``ordered``: injective placements of the pattern, none of them formed unless it closes a cycle.

    The count is a sum of maps that may repeat vertices: those of trees, which are sums over neighbours, and those of
    patterns with cycles whose cycles hold distinct nodes, which are joined among the nodes that lie between cycles alone.
    """
    if pattern.k == 0:
        return graph.nodes.agg(whole(F.count("*")).alias("ordered"))
    trees, cyclic = cycles.expansion(pattern)
    if pattern.k > 2:  # more than one pass over the arcs
        graph = graph.pinned()
    rooted = {cycles.rooted(e, n): c for (e, n), c in trees.items()}
    shapes = cycles.shapes(cyclic)
    core = cycles.without_ends(graph) if shapes else None
    if core is not None and core.isEmpty():
        shapes = {}
    hung = {t for ts in shapes.values() for _, at in ts for ts_ in at for t in ts_}
    sums = cycles.neighbour_sums(graph, {t for r in rooted for t in r} | hung)
    parts = [_one(sums.table, sum((whole(sums.product(r) * whole(c)) for r, c in rooted.items()), whole(0)))]
    parts += [cycles.closed(core, sums, edges, n, terms) for (edges, n), terms in shapes.items()]
    return _one(reduce(DataFrame.unionByName, parts), F.col("ordered"))


def tree_exact_by_joins(graph: Graph, pattern: Pattern) -> DataFrame:
    """The same by a chain of joins with distinctness, which forms every placement; for small counts only."""
    if pattern.k == 0:
        return graph.nodes.agg(whole(F.count("*")).alias("ordered"))
    placed, seen = graph.nodes.select(F.col("id").alias("v0")), [0]
    todo = list(pattern.edges)
    while todo:
        a, b = next(e for e in todo if (e[0] in seen) != (e[1] in seen))
        todo.remove((a, b))
        old, new = (a, b) if a in seen else (b, a)
        step = graph.arcs.select(F.col("src").alias(f"v{old}"), F.col("dst").alias(f"v{new}"))
        placed = placed.join(step, f"v{old}")
        for v in seen:
            if v != old:
                placed = placed.where(F.col(f"v{v}") != F.col(f"v{new}"))
        seen.append(new)
    return placed.agg(whole(F.count("*")).alias("ordered"))


def path_exact(graph: Graph, k: int) -> DataFrame:
    return tree_exact(graph, Pattern.path(k))


def star_exact(graph: Graph, k: int) -> DataFrame:
    """The falling products of the degrees."""
    d = whole(F.col("degree"))
    value = d
    for i in range(1, k):
        value = (value * (d - whole(i))).cast("decimal(38,0)")
    return _one(graph.degrees(), value)


def triangles(graph: Graph) -> DataFrame:
    """``a``, ``b``, ``c`` of each triangle once: arcs go up in (degree, id), so no hub is squared."""
    d = graph.degrees()
    up = graph.arcs.join(d.select(F.col("id").alias("src"), F.col("degree").alias("ds")), "src").join(d.select(F.col("id").alias("dst"), F.col("degree").alias("dd")), "dst")
    up = up.where("ds < dd or (ds = dd and src < dst)").select("src", "dst")
    ab, ac = up.select(F.col("src").alias("a"), F.col("dst").alias("b")), up.select(F.col("src").alias("a"), F.col("dst").alias("c"))
    bc = up.select(F.col("src").alias("b"), F.col("dst").alias("c"))
    return ab.join(ac, "a").where("b <> c").join(bc, ["b", "c"])


def closed_form(graph: Graph, form: str, k: int = 0) -> DataFrame:
    """``ordered`` of a small pattern from degrees and triangles alone."""
    deg = graph.degrees().select("id", whole(F.col("degree")).alias("d"))
    if form == "star":
        return star_exact(graph, k)
    if form == "path2":
        return _one(deg, F.col("d") * (F.col("d") - 1))
    ends = graph.arcs.join(deg.select(F.col("id").alias("src"), F.col("d").alias("du")), "src").join(deg.select(F.col("id").alias("dst"), F.col("d").alias("dv")), "dst")
    du, dv = F.col("du"), F.col("dv")
    t = triangles(graph)
    if form == "path3":
        return _one(ends, (du - 1) * (dv - 1)).crossJoin(t.agg(whole(F.count("*")).alias("t"))).select((F.col("ordered") - 6 * F.col("t")).cast("decimal(38,0)").alias("ordered"))
    if form == "fork":
        corners = t.select(F.explode(F.array("a", "b", "c")).alias("id")).join(deg, "id").agg(F.coalesce(F.sum(2 * (F.col("d") - 2)), whole(0)).alias("t"))
        return _one(ends, (du - 1) * (du - 2) * (dv - 1)).crossJoin(corners).select((F.col("ordered") - 2 * F.col("t")).cast("decimal(38,0)").alias("ordered"))
    raise ValueError(f"unknown form {form!r}; known: {FORMS}")


def quotients(pattern: Pattern) -> list[tuple[tuple[tuple[int, int], ...], int, int]]:
    """Partitions of the pattern's vertices into blocks without an edge inside: edges and size of the quotient, and the
    Moebius weight with which its homomorphisms enter the injective count."""
    def partitions(items: list[int]):
        if not items:
            yield []
            return
        head, rest = items[0], items[1:]
        for p in partitions(rest):
            yield [[head], *p]
            for i in range(len(p)):
                yield [*p[:i], [head, *p[i]], *p[i + 1 :]]

    out: dict[tuple, int] = {}
    for p in partitions(list(range(pattern.n))):
        block = {v: i for i, b in enumerate(p) for v in b}
        if any(block[a] == block[b] for a, b in pattern.edges):
            continue
        weight = math.prod((-1) ** (len(b) - 1) * math.factorial(len(b) - 1) for b in p)
        edges = {tuple(sorted((block[a], block[b]))) for a, b in pattern.edges}
        names = min(tuple(sorted(tuple(sorted((q[a], q[b]))) for a, b in edges)) for q in itertools.permutations(range(len(p)))) if len(p) <= 6 else tuple(sorted(edges))
        out[(names, len(p))] = out.get((names, len(p)), 0) + weight
    return [(e, n, w) for (e, n), w in out.items() if w]


def tree_exact_by_quotients(graph: Graph, pattern: Pattern) -> DataFrame:
    """``ordered`` from the homomorphism counts of all quotients; trees among them by neighbour sums, the others by joins.

    For forests every quotient that is not a tree has no homomorphism without a triangle or longer cycle to hold it.
    """
    total = None
    for edges, n, weight in quotients(pattern):
        count = homomorphisms(graph, edges, n).select((F.col("ordered") * weight).cast("decimal(38,0)").alias("ordered"))
        total = count if total is None else total.unionByName(count)
    return total.agg(F.sum("ordered").cast("decimal(38,0)").alias("ordered"))


def homomorphisms(graph: Graph, edges: tuple[tuple[int, int], ...], n: int) -> DataFrame:
    if len(edges) == n - 1:
        return tree_homomorphisms(graph, Pattern.of(edges, n).best_rooting())
    placed, seen, todo = None, set(), list(edges)
    while todo:
        e = next(x for x in todo if not seen or x[0] in seen or x[1] in seen)
        todo.remove(e)
        step = graph.arcs.select(F.col("src").alias(f"v{e[0]}"), F.col("dst").alias(f"v{e[1]}"))
        placed = step if placed is None else placed.join(step, [f"v{v}" for v in e if v in seen])
        seen.update(e)
    return placed.agg(whole(F.count("*")).alias("ordered"))


def tree_homomorphisms(graph: Graph, tree: RootedPattern) -> DataFrame:
    """``ordered``: maps of the tree that keep edges, vertices may repeat."""
    def below(v: int) -> DataFrame:
        parts = None
        for c in tree.children[v]:
            x = None if not tree.children[c] else below(c)
            sent = graph.arcs if x is None else graph.arcs.join(x.select(F.col("id").alias("src"), "x"), "src")
            s = sent.groupBy(F.col("dst").alias("id")).agg((whole(F.count("*")) if x is None else F.sum("x").cast("decimal(38,0)")).alias("y"))
            parts = s.withColumnRenamed("y", "x") if parts is None else parts.join(s, "id").select("id", (F.col("x") * F.col("y")).cast("decimal(38,0)").alias("x"))
        return parts

    if tree.k == 0:
        return graph.nodes.agg(whole(F.count("*")).alias("ordered"))
    return _one(below(tree.root), F.col("x"))


def unordered(exact: DataFrame, pattern: Pattern) -> DataFrame:
    """``ordered`` and ``unordered``: every placement counted once for its automorphisms."""
    return exact.select("ordered", F.floor(F.col("ordered") / pattern.automorphisms).cast("decimal(38,0)").alias("unordered"))
