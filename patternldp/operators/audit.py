"""Exact privacy loss of a released transcript when one edge is left out.

All noise is Laplace with public scales, so given the transcript the log-likelihood ratio between the graph and its
neighbour is at most the sum of |change of mean| / scale over the released numbers.  It must not exceed epsilon for any edge.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import RootedPattern
from ..sources.views import Graph
from .baselines import star_sensitivity
from .kernel import Noise, round_max
from .tree import kept_arcs, tree_levels
from .walk import walk_rounds


def walk_loss(graph: Graph, runs: DataFrame, k: int) -> DataFrame:
    """``run``, ``max_loss`` over all edges of the optimized walk mechanism."""
    noise = Noise()
    edges = graph.arcs.where("src < dst").crossJoin(F.broadcast(runs.select("run", "eps")))
    per = F.col("eps") / (2.0 * k)
    loss = 2.0 * per  # the two noisy degrees
    total = edges.withColumn("loss", loss)
    if k > 1:
        total = total.withColumn("loss", F.col("loss") + 2.0 * per)  # round 1: all counts are 1
        for x in walk_rounds(graph, runs, k, k - 1, noise)[:-1]:
            peak = F.broadcast(round_max(x, "x"))
            size = lambda side: x.join(peak, "run").select("run", F.col("id").alias(side), F.when(F.col("peak") > 0, F.abs(F.col("x")).cast("double") / F.col("peak").cast("double")).otherwise(0.0).alias(f"r_{side}"))  # noqa: B023, E731
            total = total.join(size("src"), ["run", "src"]).join(size("dst"), ["run", "dst"]).withColumn("loss", F.col("loss") + per * (F.col("r_src") + F.col("r_dst"))).drop("r_src", "r_dst")
    return total.groupBy("run").agg(F.max("loss").alias("max_loss"))


def tree_loss(graph: Graph, runs: DataFrame, tree: RootedPattern) -> DataFrame:
    """``run``, ``max_loss``, ``max_sums``: also the most released sums that one edge enters, which must be one."""
    got = tree_levels(graph, runs, tree)
    arcs = kept_arcs(graph, runs, tree).join(F.broadcast(runs.select("run", "eps")), "run")
    parts = [arcs.where(F.col("child").isin(tree.leaves)).select("run", "src", "dst", F.col("eps").alias("loss"))]
    inner = [v for v in tree.internal if v != tree.root]
    for x in got.levels:
        x = x.where(F.col("vertex").isin(inner))
        ratio = x.join(F.broadcast(round_max(x, "x", ("run", "vertex"))), ["run", "vertex"]).select("run", F.col("id").alias("src"), F.when(F.col("peak") > 0, F.abs(F.col("x")).cast("double") / F.col("peak").cast("double")).otherwise(0.0).alias("r"))
        parts.append(arcs.where(F.col("child").isin(inner)).join(ratio, ["run", "src"]).select("run", "src", "dst", (F.col("eps") * F.col("r")).alias("loss")))
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    edge = every.groupBy("run", F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.sum("loss").alias("loss"), F.count("*").alias("sums"))
    found = edge.groupBy("run").agg(F.max("loss").alias("max_loss"), F.max("sums").alias("max_sums"))
    return runs.select("run").join(found, "run", "left").select("run", F.coalesce("max_loss", F.lit(0.0)).alias("max_loss"), F.coalesce("max_sums", F.lit(0)).alias("max_sums"))


def central_star_loss(graph: Graph, runs: DataFrame, k: int, cap: int) -> DataFrame:
    """``run``, ``eps``, ``max_loss``: the change of the curator's capped count without an edge, over its scale."""
    def change(c: str) -> Column:
        def count(d: Column) -> Column:
            d = F.least(d, F.lit(cap)).cast("double")
            out = d
            for i in range(1, k):
                out = out * (d - i)
            return out

        return count(F.col(c)) - count(F.col(c) - 1)

    d = graph.degrees()
    edges = graph.arcs.where("src < dst").join(d.select(F.col("id").alias("src"), F.col("degree").alias("a")), "src").join(d.select(F.col("id").alias("dst"), F.col("degree").alias("b")), "dst")
    most = edges.agg(F.coalesce(F.max(change("a") + change("b")), F.lit(0.0)).alias("change"))
    return runs.crossJoin(F.broadcast(most)).select("run", "eps", (F.col("change") * F.col("eps") / float(star_sensitivity(k, cap))).alias("max_loss"))


def star_loss(graph: Graph, runs: DataFrame) -> DataFrame:
    """Two degrees change by one each, with scale 2 / eps."""
    return runs.crossJoin(F.broadcast(graph.arcs.agg(F.count("*").alias("n")))).select("run", F.when(F.col("n") > 0, F.col("eps")).otherwise(0.0).alias("max_loss"))
