"""Walk counts: exact, private in k or k-1 rounds, and of a single edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.views import Graph
from .kernel import Noise, active, neighbour_sum, pin, round_max

DEGREE_ROUND = 99  # the round number in the keys of the degree's noise


def walk_exact(graph: Graph, k: int) -> DataFrame:
    """``ordered``: the number of walks with ``k`` edges."""
    if k < 0:
        raise ValueError("k must not be negative")
    noise = Noise()
    if k == 0:
        return graph.nodes.agg(noise.number(F.count("*")).alias("ordered"))
    x = graph.arcs.groupBy(F.col("dst").alias("id")).agg(noise.number(F.count("*")).alias("x"))
    if k == 1:
        return x.agg(F.coalesce(noise.total(F.col("x")), noise.number(0)).alias("ordered"))
    half = pin(x, "walks") if k > 2 else x
    for _ in range(k // 2 - 1):
        half = pin(neighbour_sum(graph.arcs, half, "x", noise, ()), "walks")
    rest = half if k % 2 == 0 else neighbour_sum(graph.arcs, half, "x", noise, ())
    both = half.select("id", "x").join(rest.select("id", F.col("x").alias("y")), "id")  # a walk is two, from one of its middle nodes
    return both.agg(F.coalesce(noise.total(noise.number(F.col("x") * F.col("y"))), noise.number(0)).alias("ordered"))


def walk_rounds(graph: Graph, runs: DataFrame, k: int, rounds: int, noise: Noise) -> list[DataFrame]:
    """The released table (``run``, ``seed``, ``eps``, ``id``, ``x``) of each round, written once.

    The noise of a round has the scale 2k / eps times the public maximum of the round before: an edge touches two nodes
    and every round.
    """
    nodes = active(graph, runs)
    out: list[DataFrame] = []
    for level in range(1, rounds + 1):
        if level == 1:  # all counts before are 1: the sum is the degree and the maximum 1
            sums = graph.arcs.groupBy(F.col("dst").alias("id")).agg(noise.number(F.count("*")).alias("x"))
            joined = nodes.join(sums, "id", "left").withColumn("peak", F.lit(1.0))
        else:
            sums = neighbour_sum(graph.arcs, out[-1], "x", noise)
            joined = nodes.join(sums, ["run", "id"], "left").join(F.broadcast(round_max(out[-1], "x")), "run")
        scale = F.lit(2.0 * k) / F.col("eps") * F.col("peak").cast("double")
        released = F.coalesce(F.col("x"), noise.number(0)) + noise.draw(scale, F.col("seed"), F.lit(level), F.col("id"))
        out.append(pin(joined.select("run", "seed", "eps", "id", noise.number(released).alias("x"))))
    return out


def walk_dp(graph: Graph, runs: DataFrame, k: int, variant: str = "rounds_k_minus_1", noise: Noise | None = None) -> DataFrame:
    """``run``, ``estimate``, ``rounds`` of the private walk count.

    ``rounds_k`` sums the last round; ``rounds_k_minus_1`` (the default) leaves the last edge to the nodes, which multiply
    by their noisy degree.  One edge is the sum of noisy degrees.
    """
    noise = noise or Noise()
    if k < 0 or variant not in ("rounds_k", "rounds_k_minus_1"):
        raise ValueError("k must not be negative and the variant known")
    if k == 0:
        return runs.select("run").crossJoin(graph.nodes.agg(noise.number(F.count("*")).alias("estimate"))).withColumn("rounds", F.lit(0))
    if variant == "rounds_k":
        last = walk_rounds(graph, runs, k, k, noise)[-1]
        return last.groupBy("run").agg(noise.total(F.col("x")).alias("estimate"), F.lit(k).alias("rounds"))
    degree = active(graph, runs).join(graph.degrees(), "id")
    noisy = noise.number(F.col("degree")) + noise.draw(F.lit(2.0 * k) / F.col("eps"), F.col("seed"), F.lit(DEGREE_ROUND), F.col("id"))
    if k == 1:
        return degree.groupBy("run").agg(noise.total(noisy).alias("estimate"), F.lit(1).alias("rounds"))
    last = walk_rounds(graph, runs, k, k - 1, noise)[-1]
    paired = last.select("run", "id", "x").join(degree, ["run", "id"])
    return paired.groupBy("run").agg(noise.total(noise.number(F.col("x") * noisy)).alias("estimate"), F.lit(k - 1).alias("rounds"))


def walk_trace(graph: Graph, runs: DataFrame, k: int, noise: Noise | None = None) -> DataFrame:
    """``run``, ``round``, ``max_abs``, ``sum_x``, ``active`` of the released tables."""
    noise = noise or Noise()
    parts = [x.groupBy("run").agg(F.lit(i + 1).alias("round"), F.max(F.abs("x")).alias("max_abs"), noise.total(F.col("x")).alias("sum_x"), F.count("*").alias("active")) for i, x in enumerate(walk_rounds(graph, runs, k, max(1, k - 1), noise))]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def edge_count_dp(graph: Graph, runs: DataFrame, noise: Noise | None = None) -> DataFrame:
    """``run``, ``estimate``: twice the number of edges, as one-edge walks."""
    return walk_dp(graph, runs, 1, noise=noise)
