"""Communication, rounds and operations of each method, as formulas and as counted from the marks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import RootedPattern
from ..sources.views import Graph
from .tree import kept_arcs, marked_nodes

VALUE = 8  # bytes of a number
MB, GB = 2.0**20, 2.0**30


def walk_bytes(n: float, m: float, k: int, variant: str = "rounds_k_minus_1", routing: str = "neighbours") -> float:
    """Counts to neighbours and analyzer and the maximum back, in all rounds but the last; then one upload a node."""
    if routing == "broadcast" or variant == "rounds_k":
        return VALUE * ((k - 1) * n * n + n)
    return VALUE * (max(0, k - 2) * (2 * m + 2 * n) + n)


def tree_bytes(n: float, m: float, k: int, internal: int, inactive: str = "silent") -> float:
    """Marks to neighbours and analyzer; each internal vertex but the root to its parent's holders; uploads; maxima down.

    Expected over marks.  ``inactive="zero"``: nodes without the vertex of a round send zeros to all neighbours.
    """
    if inactive == "zero":
        return VALUE * (2 * m + n + (internal - 1) * 2 * m + (2 * internal - 1) * n)
    return VALUE * (2 * m + n + (internal - 1) * 2 * m / (k + 1) ** 2 + (2 * internal - 1) * n / (k + 1))


def path_bytes(n: float, m: float, k: int) -> float:
    return tree_bytes(n, m, k, k - 1)


def star_bytes(n: float) -> float:
    return VALUE * n


def capped_star_bytes(n: float) -> float:
    return 3 * VALUE * n


def noisy_graph_bytes(n: float) -> float:
    """A byte for each pair."""
    return n * (n - 1) / 2


def clipped_walk_bytes(n: float, k: int) -> float:
    return VALUE * k * n * n


def rounds(method: str, k: int, tree: RootedPattern | None = None) -> int:
    return {"walk_base": k, "walk": max(1, k - 1), "path": k, "tree": tree.rounds if tree else 0, "star": 1, "noisy_graph": 1, "clipped_walk": k + 1, "capped_star": 2}[method]


def tree_measured(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``run``, ``channel``, ``messages``, ``bytes`` that the marks of each run make, every channel listed."""
    inner = [v for v in tree.internal if v != tree.root]
    nodes = marked_nodes(graph, runs, tree)
    marks = runs.select("run").crossJoin(graph.arcs.agg(F.count("*").alias("arcs")).crossJoin(graph.nodes.agg(F.count("*").alias("n"))))
    marks = marks.select("run", F.lit("marks").alias("channel"), (F.col("arcs") + F.col("n")).alias("messages"))
    sent = kept_arcs(graph, runs, tree).where(F.col("child").isin(inner)).groupBy("run").agg(F.count("*").alias("messages"))
    uploads = nodes.where(F.col("vertex").isin(tree.internal)).groupBy("run").agg(F.count("*").alias("messages"))
    per = {v: sum(c in inner for c in tree.children[v]) for v in tree.internal}
    weight = F.element_at(F.array(*[F.lit(per.get(v, 0)) for v in range(tree.k + 1)]), F.col("vertex") + 1)
    maxima = nodes.groupBy("run").agg(F.sum(weight).alias("messages"))
    out = marks
    for name, df in (("node_to_node", sent), ("node_to_analyzer", uploads), ("analyzer_to_node", maxima)):
        out = out.unionByName(runs.select("run").join(df, "run", "left").select("run", F.lit(name).alias("channel"), F.coalesce("messages", F.lit(0)).cast("long").alias("messages")))
    return out.withColumn("bytes", F.col("messages") * VALUE)


def walk_measured(graph: Graph, k: int) -> DataFrame:
    """``channel``, ``messages``, ``bytes`` of the optimized walk: independent of the data but for its size."""
    size = graph.nodes.agg(F.count("*").alias("n")).crossJoin(graph.arcs.agg(F.count("*").alias("arcs")))
    r = max(0, k - 2)
    rows = F.array(
        F.struct(F.lit("node_to_node").alias("channel"), (F.col("arcs") * r).alias("messages")),
        F.struct(F.lit("node_to_analyzer").alias("channel"), (F.col("n") * (r + 1)).alias("messages")),
        F.struct(F.lit("analyzer_to_node").alias("channel"), (F.col("n") * r).alias("messages")),
    )
    return size.select(F.explode(rows).alias("x")).select("x.channel", "x.messages", (F.col("x.messages") * VALUE).alias("bytes"))


def walk_operations(graph: Graph, k: int) -> DataFrame:
    """``max_at``, ``node_ops``, ``analyzer_ops`` of the optimized walk: values read by the busiest node and by the analyzer.

    Where the analyzer takes the maxima, a node reads its neighbours alone; otherwise every node reads all counts as well.
    """
    r = max(1, k - 1)
    size = graph.degrees().agg(F.max("degree").alias("d"), F.count("*").alias("n"))
    rows = F.array(
        F.struct(F.lit("analyzer").alias("max_at"), (F.col("d") * r).alias("node_ops"), (F.col("n") * r).alias("analyzer_ops")),
        F.struct(F.lit("node").alias("max_at"), ((F.col("d") + F.col("n")) * r).alias("node_ops"), F.col("n").alias("analyzer_ops")),
    )
    return size.select(F.explode(rows).alias("x")).select("x.*")


def operations(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``run``, ``max_node_ops``, ``analyzer_ops``: values read by the busiest node, and by the analyzer."""
    arcs = kept_arcs(graph, runs, tree)
    node = arcs.groupBy("run", "dst").agg(F.count("*").alias("c")).groupBy("run").agg(F.max("c").alias("max_node_ops"))
    analyzer = marked_nodes(graph, runs, tree).where(F.col("vertex").isin(tree.internal)).groupBy("run").agg(F.count("*").alias("analyzer_ops"))
    return runs.select("run").join(node, "run", "left").join(analyzer, "run", "left").select("run", F.coalesce("max_node_ops", F.lit(0)).alias("max_node_ops"), F.coalesce("analyzer_ops", F.lit(0)).alias("analyzer_ops"))
