"""Experiment protocols: repeated runs, trimmed means, error splits, sweeps."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import check_epsilon
from ..operators import many
from ..operators.kernel import Noise
from ..operators.tree import path_dp, tree_dp
from ..sources.views import Graph

REPS, DROPPED = 10, 2


def relative_error(estimate: Column, true: Column) -> Column:
    """Per cent; null where the true count is 0."""
    t = true.cast("double")
    return F.when(t != 0, 100.0 * F.abs(estimate.cast("double") - t) / F.abs(t))


def trimmed_mean(runs: DataFrame, value: str, by: list[str] | None = None, dropped: int = DROPPED) -> DataFrame:
    """``by``, ``trimmed``: the mean without the ``dropped`` highest and lowest; nulls never count."""
    by = by or []
    part = Window.partitionBy(*(by or [F.lit(1)]))
    ranked = runs.where(F.col(value).isNotNull()).withColumn("_r", F.row_number().over(part.orderBy(value))).withColumn("_n", F.count("*").over(part))
    return ranked.where((F.col("_r") > dropped) & (F.col("_r") <= F.col("_n") - dropped)).groupBy(*by).agg(F.avg(value).alias("trimmed"))


def errors(runs: DataFrame, estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """``run``, ``seed``, ``eps``, ``estimate``, ``ordered``, ``error`` of each run."""
    return runs.join(estimates, "run").crossJoin(F.broadcast(exact.select("ordered"))).withColumn("error", relative_error(F.col("estimate"), F.col("ordered")))


def protocol(runs: DataFrame, estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """``eps``, ``rel_err``: per epsilon, the trimmed mean of the relative errors."""
    return trimmed_mean(errors(runs, estimates, exact), "error", ["eps"]).withColumnRenamed("trimmed", "rel_err")


def decompose(runs: DataFrame, estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """``run`` and the errors of the marks alone, of the noise under the same marks, and of both, in per cent of the truth."""
    joined = runs.join(estimates, "run").crossJoin(F.broadcast(exact.select("ordered")))
    t = F.col("ordered").cast("double")
    share = lambda a, b: F.when(t != 0, 100.0 * F.abs(a.cast("double") - b.cast("double")) / F.abs(t))
    e, m = F.col("estimate"), F.col("marked_estimate")
    return joined.select("run", "eps", share(m, F.col("ordered")).alias("sampling_err"), share(e, m).alias("dp_err"), share(e, F.col("ordered")).alias("total_err"))


def averaged(graph: Graph, mechanism: Callable[[Graph, DataFrame], DataFrame], n_rep: int | list[int], eps: float = 1.0, seed: int = 42, trials: int = 1) -> DataFrame:
    """``n_rep``, ``trial``, ``estimate``: the mean of so many runs with an equal share of epsilon each.

    All runs of all values are rows of one program.
    """
    values = n_rep if isinstance(n_rep, list) else [n_rep]
    spark = graph.nodes.sparkSession
    rows = [(i, seed + 1000 * t + 100 * n + r, check_epsilon(eps) / n, n, t) for i, (n, t, r) in enumerate((n, t, r) for n in values for t in range(trials) for r in range(n))]
    plan = spark.createDataFrame(rows, "run int, seed long, eps double, n_rep int, trial int")
    got = mechanism(graph, plan.select("run", "seed", "eps"))
    return plan.join(got, "run").groupBy("n_rep", "trial").agg(F.sum(F.col("estimate")).alias("s")).select("n_rep", "trial", (F.col("s").cast("double") / F.col("n_rep")).alias("estimate"))


def sweep_nrep(graph: Graph, mechanism: Callable[[Graph, DataFrame], DataFrame], exact: DataFrame, values: list[int], eps: float = 1.0, seed: int = 42, trials: int = REPS) -> DataFrame:
    """``n_rep``, ``rel_err``, ``gain`` (the error of one run over it)."""
    runs = averaged(graph, mechanism, values, eps, seed, trials).crossJoin(F.broadcast(exact.select("ordered"))).withColumn("error", relative_error(F.col("estimate"), F.col("ordered")))
    by = trimmed_mean(runs, "error", ["n_rep"])
    one = by.where("n_rep = 1").select(F.col("trimmed").alias("one"))
    return by.crossJoin(F.broadcast(one)).select("n_rep", F.col("trimmed").alias("rel_err"), (F.col("one") / F.col("trimmed")).alias("gain"))


def mean_bytes(runs: DataFrame, sent: DataFrame) -> DataFrame:
    """``eps``, ``comm_mean``: the bytes of all channels, averaged over the runs of an epsilon."""
    total = sent.groupBy("run").agg(F.sum("bytes").alias("bytes"))
    return runs.join(total, "run").groupBy("eps").agg(F.avg("bytes").alias("comm_mean"))


def sweep_nrep_split(graph: Graph, mechanism: Callable[[Graph, DataFrame], DataFrame], exact: DataFrame, values: list[int], eps: float = 1.0, seed: int = 42, trials: int = REPS) -> DataFrame:
    """``n_rep`` and trimmed ``total_err``, ``sampling_err``, ``dp_err`` of the averages; ``gain`` of the total over one run's; ``best``.

    The mechanism also gives ``marked_estimate``.
    """
    spark = graph.nodes.sparkSession
    rows = [(i, seed + 1000 * t + 100 * n + r, check_epsilon(eps) / n, n, t) for i, (n, t, r) in enumerate((n, t, r) for n in values for t in range(trials) for r in range(n))]
    plan = spark.createDataFrame(rows, "run int, seed long, eps double, n_rep int, trial int")
    got = plan.join(mechanism(graph, plan.select("run", "seed", "eps")), "run").groupBy("n_rep", "trial").agg(F.sum("estimate").alias("s"), F.sum("marked_estimate").alias("u"))
    means = got.select("n_rep", "trial", (F.col("s").cast("double") / F.col("n_rep")).alias("a"), (F.col("u").cast("double") / F.col("n_rep")).alias("m")).crossJoin(F.broadcast(exact.select(F.col("ordered").cast("double").alias("t"))))
    share = lambda x, y: F.when(F.col("t") != 0, 100.0 * F.abs(x - y) / F.abs(F.col("t")))
    a, m, t = F.col("a"), F.col("m"), F.col("t")
    kinds = {"total_err": share(a, t), "sampling_err": share(m, t), "dp_err": share(a, m)}
    long = means.select("n_rep", F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), c.alias("error")) for k, c in kinds.items()])).alias("x")).select("n_rep", "x.kind", "x.error")
    wide = trimmed_mean(long, "error", ["n_rep", "kind"]).groupBy("n_rep").pivot("kind", list(kinds)).agg(F.max("trimmed"))
    ends = wide.agg(F.max(F.when(F.col("n_rep") == 1, F.col("total_err"))).alias("one"), F.min("total_err").alias("least"))
    return wide.crossJoin(F.broadcast(ends)).select("n_rep", *kinds, (F.col("one") / F.col("total_err")).alias("gain"), (F.col("total_err") == F.col("least")).alias("best"))


def improvement(ours: DataFrame, other: DataFrame) -> DataFrame:
    """``error_gain``: how many times larger the other's error is (both ``rel_err``)."""
    return ours.select(F.col("rel_err").alias("a")).crossJoin(F.broadcast(other.select(F.col("rel_err").alias("b")))).select((F.col("b") / F.col("a")).alias("error_gain"))


def path_mechanism(k: int, noise: Noise | None = None) -> Callable[[Graph, DataFrame], DataFrame]:
    return lambda g, r: path_dp(g, r, k, noise)


def tree_mechanism(tree, noise: Noise | None = None) -> Callable[[Graph, DataFrame], DataFrame]:
    return lambda g, r: many.tree_dp(g, r, tree) if noise is None else tree_dp(g, r, tree, noise)
