"""What all round-based mechanisms are made of.

Runs are rows: ``run``, ``seed``, ``eps``.  Every table of a mechanism carries ``run`` as a key, so that repetitions, sweeps of
epsilon and averaged runs are one program with as many shuffles as a single run has.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import WHOLE, check_epsilon, laplace, lattice_laplace
from ..sources.scratch import pin
from ..sources.views import Graph

__all__ = ["Noise", "make_runs", "neighbour_sum", "pin", "round_max", "whole"]


def make_runs(spark: SparkSession, eps: float | list[float] = 1.0, seed: int = 42, reps: int = 1) -> DataFrame:
    """One run for each epsilon and repetition; repetition r uses ``seed + r``.

    Runs of different epsilon share their draws, which suits experiments.  Results that are published together need
    different seeds.
    """
    values = [check_epsilon(e) for e in (eps if isinstance(eps, list) else [eps])]
    return spark.createDataFrame([(i * reps + r, seed + r, e) for i, e in enumerate(values) for r in range(reps)], "run int, seed long, eps double")


def whole(x: int | Column) -> Column:
    return (F.lit(x) if isinstance(x, int) else x).cast(WHOLE)


class Noise:
    """The number type of a mechanism: whole decimals and rounded noise (``lattice``), or doubles."""

    def __init__(self, lattice: bool = True, hasher: str = "md5"):
        self.lattice, self.hasher = lattice, hasher

    def number(self, x: int | Column) -> Column:
        x = F.lit(x) if isinstance(x, int) else x
        return x.cast(WHOLE) if self.lattice else x.cast("double")

    def draw(self, scale: Column, *key: Column) -> Column:
        return (lattice_laplace if self.lattice else laplace)(scale, *key, hasher=self.hasher)

    def total(self, x: Column) -> Column:
        return F.sum(x).cast(WHOLE) if self.lattice else F.sum(x)


def neighbour_sum(arcs: DataFrame, x: DataFrame, value: str, noise: Noise, by: tuple[str, ...] = ("run",)) -> DataFrame:
    """``by``, ``id`` and the sum of ``value`` over each node's neighbours; nodes without neighbours have no row.

    Sums are combined before the shuffle by ``dst``, so nodes of large degree as receivers are harmless; as senders they
    only meet their arcs in the join, which Spark splits when it is skewed.
    """
    sent = arcs.join(x.select(*by, F.col("id").alias("src"), value), "src")
    return sent.groupBy(*by, F.col("dst").alias("id")).agg(noise.total(F.col(value)).alias(value))


def round_max(x: DataFrame, value: str, by: tuple[str, ...] = ("run",)) -> DataFrame:
    """The public maximum of |value|: a row for each run (and vertex), which is what is broadcast to the nodes."""
    return x.groupBy(*by).agg(F.max(F.abs(F.col(value))).alias("peak"))


def active(graph: Graph, runs: DataFrame) -> DataFrame:
    """Every node in every run.  Runs are few and counted; they are the broadcast side."""
    return graph.nodes.crossJoin(F.broadcast(runs))
