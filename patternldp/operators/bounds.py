"""Error bounds that hold with probability 1 - beta, tail bounds, and the table of asymptotic costs."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.views import Graph


def check_beta(beta: float) -> float:
    if not 0 < beta < 1:
        raise ValueError(f"beta must be in (0, 1): {beta!r}")
    return beta


def laplace_sum_bound(scales: list[float], beta: float) -> float:
    """What a sum of independent Laplace variables stays within, for scales not dominated by one."""
    return math.sqrt(8 * sum(b * b for b in scales) * math.log(2 / check_beta(beta)))


def chernoff_upper(mean: float, delta: float) -> float:
    """Probability that a sum of independent indicators exceeds (1 + delta) times its mean, delta in (0, 1]."""
    if not 0 < delta <= 1:
        raise ValueError("delta must be in (0, 1]")
    return math.exp(-delta * delta * mean / 3)


def chebyshev(deviations: float) -> float:
    return min(1.0, 1 / deviations**2)


def walk_bound(n: Column, d: Column, k: int, eps: float, beta: float) -> Column:
    gamma = F.lit(2.0 * k / eps) * F.sqrt(8.0 * F.ln(2.0 * k * n / beta))
    return k * gamma * F.sqrt(n) * F.pow(d + gamma, F.lit(float(k - 1)))


def sampling_bound(n: Column, d: Column, k: int, beta: float) -> Column:
    """Of the marks alone."""
    return (k + 1) * F.sqrt(n / beta) * F.pow(d + float(k + 1), F.lit(float(k)))


def noise_bound(n: Column, d: Column, k: int, eps: float, beta: float, kind: str = "path", share: float = 1.0) -> Column:
    """Of the noise given the marks; ``share`` multiplies the number of events for total bounds."""
    events = (6.0 if kind == "path" else 6.0 * k) * share
    gamma = F.lit((k + 1.0) / eps) * F.sqrt(8.0 * F.ln(events * n / beta))
    dd = F.greatest(d.cast("double"), F.ceil(gamma * gamma).cast("double"))
    return k * (k + 1.0) * gamma * F.sqrt(n) * F.pow(dd + gamma * F.sqrt(dd) + gamma, F.lit(float(k - 1)))


def total_bound(n: Column, d: Column, k: int, eps: float, beta: float, kind: str = "path") -> Column:
    return sampling_bound(n, d, k, beta / 2) + noise_bound(n, d, k, eps, beta, kind, 2.0)


def count_cap(n: Column, d: Column, k: int) -> Column:
    """No count exceeds it."""
    return n * F.pow(d.cast("double"), F.lit(float(k)))


def bounds_table(graph: Graph, k: int, eps: float = 1.0, beta: float = 0.1) -> DataFrame:
    s = graph.stats()
    n, d = F.col("n_nodes").cast("double"), F.col("max_degree").cast("double")
    cols = {
        "walk": walk_bound(n, d, k, eps, beta), "sampling": sampling_bound(n, d, k, beta), "path_noise": noise_bound(n, d, k, eps, beta),
        "tree_noise": noise_bound(n, d, k, eps, beta, "tree"), "path_total": total_bound(n, d, k, eps, beta), "tree_total": total_bound(n, d, k, eps, beta, "tree"), "cap": count_cap(n, d, k),
    }
    return s.select(*[v.alias(k_) for k_, v in cols.items()])


def theory_table(graph: Graph, k: int) -> DataFrame:
    """``task``, ``method`` and the leading terms of count, error, communication and time on this graph."""
    s = graph.stats()
    n, m, d = F.col("n_nodes").cast("double"), F.col("n_edges").cast("double"), F.col("max_degree").cast("double")
    def row(task: str, method: str, error: Column, comm: Column, time: Column) -> Column:
        return F.struct(F.lit(task).alias("task"), F.lit(method).alias("method"), count_cap(n, d, k).alias("count_cap"), error.alias("error"), comm.alias("communication"), time.alias("time"))

    p = lambda x, e: F.pow(x, F.lit(float(e)))
    rows = [row("walk", "rounds", F.sqrt(n) * p(d, k - 1), m + n, n * d), row("walk", "clipped", F.lit(None).cast("double"), n * n, n * d)]
    for task in ("path", "tree"):
        rows += [row(task, "marks", F.sqrt(n) * p(d, k), m + n, n * d), row(task, "noisy_graph", p(n, k), n * n, p(n, k + 1))]
    return s.select(F.explode(F.array(*rows)).alias("x")).select("x.*")
