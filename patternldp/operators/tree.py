"""Path and tree counts by random marks.

Each node draws a public mark, the one position of the pattern it may hold, so no node repeats.  Only arcs from a mark to
its parent's mark matter: they are kept before anything is shuffled.  Subtrees are counted from the leaves up: for each
child the sum over the neighbours that hold it, over the children the product.  An edge serves one sum of one node, so every
sum gets the whole epsilon.  The root's total times (k+1)^(k+1) estimates the ordered count.

All vertices of one height are done together, so shuffles grow with the height, not with the number of vertices; the rounds
reported are the protocol's.  Paths are trees rooted at the last vertex but one.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import mark
from ..functions.pattern import RootedPattern, path_tree
from ..sources.views import Graph
from .kernel import Noise, pin, round_max


def parent_of(tree: RootedPattern, vertex: Column) -> Column:
    """The parent's mark; null at the root."""
    return F.element_at(F.array(*[F.lit(p).cast("int") for p in tree.parent]), vertex + 1)


Kinds = tuple[int | None, ...] | None  # of nodes that may hold each vertex; None: any


def may_hold(node: Column, vertex: Column, kinds: Kinds) -> Column:
    """Whether the node is of the public kind that the vertex asks for; a node's kind is its id modulo 8."""
    if kinds is None:
        return F.lit(True)
    wanted = F.element_at(F.array(*[F.lit(k).cast("int") for k in kinds]), vertex + 1)
    return wanted.isNull() | (node % 8 == wanted)


def marked_nodes(graph: Graph, runs: DataFrame, tree: RootedPattern, kinds: Kinds = None) -> DataFrame:
    """``run``, ``seed``, ``eps``, ``id``, ``vertex``; a node whose mark is not for its kind holds none."""
    drawn = graph.nodes.crossJoin(F.broadcast(runs)).withColumn("vertex", mark(F.col("id"), tree.k, F.col("seed")))
    return drawn if kinds is None else drawn.where(may_hold(F.col("id"), F.col("vertex"), kinds))


def kept_arcs(graph: Graph, runs: DataFrame, tree: RootedPattern, kinds: Kinds = None) -> DataFrame:
    """``run``, ``src``, ``dst``, ``child``, ``vertex`` of the arcs from a child's mark to its parent's."""
    both = graph.arcs.crossJoin(F.broadcast(runs.select("run", "seed")))
    drawn = both.withColumn("child", mark(F.col("src"), tree.k, F.col("seed"))).withColumn("vertex", mark(F.col("dst"), tree.k, F.col("seed")))
    kept = drawn.where(parent_of(tree, F.col("child")) == F.col("vertex"))
    kept = kept if kinds is None else kept.where(may_hold(F.col("src"), F.col("child"), kinds) & may_hold(F.col("dst"), F.col("vertex"), kinds))
    return kept.select("run", "src", "dst", "child", "vertex")


@dataclass
class TreeRun:
    levels: list[DataFrame]  # run, seed, eps, id, vertex, x (private), y (marks only)
    tree: RootedPattern
    noise: Noise


def tree_levels(graph: Graph, runs: DataFrame, tree: RootedPattern, noise: Noise | None = None, kinds: Kinds = None) -> TreeRun:
    """Released counts of the internal vertices, level by level, each written once.

    A node that holds an internal vertex reports even if it has no neighbour for a child: its sum is zero plus noise.
    The scale of a child's noise is the public maximum over the nodes that hold the child, over epsilon; for a leaf it is 1.
    """
    noise = noise or Noise()
    nodes = marked_nodes(graph, runs, tree, kinds)
    arcs = kept_arcs(graph, runs, tree, kinds)
    arcs = pin(arcs, "marked-arcs") if len(tree.levels) > 1 else arcs
    leaves = [F.lit(v) for v in tree.leaves]
    done: list[DataFrame] = []
    for level in tree.levels:
        if not any(tree.children[v] for v in level):  # the single vertex
            done.append(pin(nodes.select("run", "seed", "eps", "id", "vertex", noise.number(1).alias("x"), noise.number(1).alias("y"))))
            continue
        here = arcs.where(F.col("vertex").isin(level))
        sums = here.where(F.col("child").isin(*leaves)).groupBy("run", F.col("dst").alias("id"), "child").agg(noise.number(F.count("*")).alias("sx"), noise.number(F.count("*")).alias("sy"))
        peaks = None
        inner = [c for v in level for c in tree.children[v] if c not in tree.leaves]
        for vertices, below in zip(tree.levels, done):
            if not set(vertices) & set(inner):
                continue
            below = below.where(F.col("vertex").isin(inner))
            sent = here.join(below.select("run", F.col("id").alias("src"), "x", "y"), ["run", "src"])
            sums = sums.unionByName(sent.groupBy("run", F.col("dst").alias("id"), "child").agg(noise.total(F.col("x")).alias("sx"), noise.total(F.col("y")).alias("sy")))
            peak = round_max(below, "x", ("run", "vertex")).withColumnRenamed("vertex", "child")
            peaks = peak if peaks is None else peaks.unionByName(peak)
        lists = F.element_at(F.array(*[F.array(*[F.struct(F.lit(i).alias("slot"), F.lit(c).alias("child")) for i, c in enumerate(tree.children[v])]) if v in level else F.array().cast("array<struct<slot:int,child:int>>") for v in range(tree.k + 1)]), F.col("vertex") + 1)
        grid = nodes.where(F.col("vertex").isin(level)).withColumn("c", F.explode(lists)).select("run", "seed", "eps", "id", "vertex", "c.slot", "c.child")
        full = grid.join(sums, ["run", "id", "child"], "left")
        if peaks is not None:
            full = full.join(F.broadcast(peaks), ["run", "child"], "left")  # a row for each run and vertex
            peak = F.when(F.col("child").isin(*leaves), F.lit(1.0)).otherwise(F.coalesce(F.col("peak").cast("double"), F.lit(0.0)))
        else:
            peak = F.lit(1.0)
        noisy = noise.number(F.coalesce("sx", noise.number(0)) + noise.draw(peak / F.col("eps"), F.col("seed"), F.concat(F.lit("t"), F.col("child")), F.col("id")))
        full = full.withColumn("nx", noisy).withColumn("ny", F.coalesce("sy", noise.number(0)))
        width = max(len(tree.children[v]) for v in level)
        slots = full.groupBy("run", "seed", "eps", "id", "vertex").agg(*[F.max(F.when(F.col("slot") == i, F.col(c))).alias(f"{c}{i}") for i in range(width) for c in ("nx", "ny")])

        def product(c: str) -> Column:
            out = F.coalesce(F.col(f"{c}0"), noise.number(1))
            for i in range(1, width):
                out = noise.number(out * F.coalesce(F.col(f"{c}{i}"), noise.number(1)))
            return out

        done.append(pin(slots.select("run", "seed", "eps", "id", "vertex", product("nx").alias("x"), product("ny").alias("y")), "level"))
    return TreeRun(done, tree, noise)


def tree_dp(graph: Graph, runs: DataFrame, tree: RootedPattern, noise: Noise | None = None, kinds: Kinds = None) -> DataFrame:
    """``run``, ``estimate`` (private), ``marked_estimate`` (the same marks without noise), ``rounds``.

    ``kinds`` labels the pattern: vertex v is held by nodes of kind ``kinds[v]`` alone, so that the count is that of an acyclic
    join of several relations.  Kinds and marks are public, so privacy and the factor stay as they are.
    """
    got = tree_levels(graph, runs, tree, noise, kinds)
    factor = got.noise.number(tree.factor)
    root = got.levels[-1].where(F.col("vertex") == tree.root)
    sums = root.groupBy("run").agg(got.noise.total(F.col("x")).alias("sx"), got.noise.total(F.col("y")).alias("sy"))
    zero = got.noise.number(0)
    return runs.select("run").join(sums, "run", "left").select(
        "run", got.noise.number(F.coalesce("sx", zero) * factor).alias("estimate"), got.noise.number(F.coalesce("sy", zero) * factor).alias("marked_estimate"), F.lit(tree.rounds).alias("rounds")
    )


def tree_marked(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``run``, ``estimate`` by the marks alone, not private; no noise is drawn."""
    kept = kept_arcs(graph, runs, tree)
    whole = Noise()
    x: dict[int, DataFrame] = {}
    for v in [v for level in tree.levels for v in level]:
        parts = None
        for c in tree.children[v]:
            here = kept.where((F.col("child") == c) & (F.col("vertex") == v))
            if c not in tree.leaves:
                here = here.join(x[c].select("run", F.col("id").alias("src"), "x"), ["run", "src"])
            s = here.groupBy("run", F.col("dst").alias("id")).agg((whole.number(F.count("*")) if c in tree.leaves else whole.total(F.col("x"))).alias("y"))
            parts = s.withColumnRenamed("y", "x") if parts is None else parts.join(s, ["run", "id"]).select("run", "id", whole.number(F.col("x") * F.col("y")).alias("x"))
        x[v] = pin(parts, "marked")
    sums = x[tree.root].groupBy("run").agg(whole.total(F.col("x")).alias("s"))
    return runs.select("run").join(sums, "run", "left").select("run", whole.number(F.coalesce("s", whole.number(0)) * whole.number(tree.factor)).alias("estimate"))


def path_dp(graph: Graph, runs: DataFrame, k: int, noise: Noise | None = None) -> DataFrame:
    """The same for paths with ``k`` edges; ``k`` rounds, the marking included."""
    return tree_dp(graph, runs, path_tree(k), noise).withColumn("rounds", F.lit(max(1, k)))


def mark_stats(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``run``, ``kind`` (node or arc), ``child`` (-1 for nodes), ``vertex``, ``n``: nodes by mark, kept arcs by pair of marks."""
    nodes = marked_nodes(graph, runs, tree).groupBy("run", "vertex").agg(F.count("*").alias("n")).select("run", F.lit("node").alias("kind"), F.lit(-1).alias("child"), "vertex", "n")
    arcs = kept_arcs(graph, runs, tree).groupBy("run", "child", "vertex").agg(F.count("*").alias("n")).select("run", F.lit("arc").alias("kind"), "child", "vertex", "n")
    return nodes.union(arcs)


def tree_trace(graph: Graph, runs: DataFrame, tree: RootedPattern, noise: Noise | None = None) -> DataFrame:
    """``run``, ``vertex``, ``active``, ``max_abs``, ``sum_x`` of each internal vertex."""
    got = tree_levels(graph, runs, tree, noise)
    out = got.levels[0]
    for x in got.levels[1:]:
        out = out.unionByName(x)
    return out.groupBy("run", "vertex").agg(F.count("*").alias("active"), F.max(F.abs("x")).alias("max_abs"), got.noise.total(F.col("x")).alias("sum_x"))
