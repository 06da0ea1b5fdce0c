"""Star counts in one round: the falling product of each node's noisy degree."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.views import Graph
from .kernel import Noise


def falling(x: Column, k: int, noise: Noise) -> Column:
    out = x
    for i in range(1, k):
        out = noise.number(out * (x - noise.number(i)))
    return out


def noisy_degrees(graph: Graph, runs: DataFrame, noise: Noise) -> DataFrame:
    """``run``, ``eps``, ``id``, ``d``: the degree with noise of scale 2 / eps, as an edge changes two degrees."""
    return graph.degrees().crossJoin(F.broadcast(runs)).select("run", "eps", "id", "degree", noise.number(noise.number(F.col("degree")) + noise.draw(F.lit(2.0) / F.col("eps"), F.col("seed"), F.lit("s"), F.col("id"))).alias("d"))


def star_dp(graph: Graph, runs: DataFrame, k: int, debias: bool = False, noise: Noise | None = None) -> DataFrame:
    """``run``, ``estimate``, ``rounds`` of the ordered star count.

    The product uses one noisy degree k times and so is biased from k = 2 on.  ``debias`` (continuous noise) replaces it by
    the polynomial whose mean is the falling product: with scale b, p(d) - b^2 p''(d) has the mean p of the true degree.
    """
    if k < 1:
        raise ValueError("a star has at least one edge")
    if debias:
        noise = Noise(lattice=False)
        d = noisy_degrees(graph, runs, noise)
        b2 = (F.lit(2.0) / F.col("eps")) ** 2
        value = falling_polynomial(F.col("d"), k) - b2 * falling_polynomial(F.col("d"), k, 2)
        return d.groupBy("run").agg(F.sum(value).alias("estimate"), F.lit(1).alias("rounds"))
    noise = noise or Noise()
    return noisy_degrees(graph, runs, noise).groupBy("run").agg(noise.total(falling(F.col("d"), k, noise)).alias("estimate"), F.lit(1).alias("rounds"))


def coefficients(k: int) -> list[int]:
    """Of x(x-1)...(x-k+1), from the constant up."""
    c = [1]
    for i in range(k):
        c = [(c[j - 1] if j else 0) - i * (c[j] if j < len(c) else 0) for j in range(len(c) + 1)]
    return c


def falling_polynomial(x: Column, k: int, derivative: int = 0) -> Column:
    c = coefficients(k)
    for _ in range(derivative):
        c = [i * v for i, v in enumerate(c)][1:]
    out = F.lit(0.0)
    for v in reversed(c):
        out = out * x + F.lit(float(v))
    return out
