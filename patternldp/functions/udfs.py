"""Python functions for users of the methods: vectorised noise, exact counts by group, table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .pattern import Pattern


def laplace_numpy(u: pd.Series, scale: pd.Series) -> pd.Series:
    """Laplace noise from uniforms, in numpy; the column form in ``noise`` stays in the JVM."""
    c = u - 0.5
    return -scale * np.sign(c) * np.log1p(-2 * np.abs(c))


def laplace_np(u: Column, scale: Column) -> Column:
    return F.pandas_udf(laplace_numpy, "double")(u, scale)


def trimmed(values: Column, dropped: int = 2) -> Column:
    """A grouped aggregate as a pandas function: the mean without the extremes."""

    @F.pandas_udf("double")
    def mean(x: pd.Series) -> float:
        s = np.sort(x.dropna().to_numpy(float))
        s = s[dropped : len(s) - dropped]
        return float(s.mean()) if len(s) else float("nan")

    return mean(values)


def grouped_paths(arcs: DataFrame, group: str, k: int) -> DataFrame:
    """``group``, ``ordered``: injective paths of ``k`` edges within each group, for many small groups."""

    def count(pdf: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, list[int]] = {}
        for a, b in zip(pdf["src"], pdf["dst"]):
            near.setdefault(a, []).append(b)

        def extend(path: list[int]) -> int:
            if len(path) == k + 1:
                return 1
            return sum(extend([*path, n]) for n in near.get(path[-1], ()) if n not in path)

        return pd.DataFrame({group: [pdf[group].iloc[0]], "ordered": [sum(extend([v]) for v in near)]})

    return arcs.groupBy(group).applyInPandas(count, f"{group} long, ordered long")


class FreeTrees:
    """The number of tree shapes on 1 to ``most`` vertices and their automorphism counts."""

    def eval(self, most: int) -> Iterator[tuple[int, int, str]]:
        for n in range(1, most + 1):
            trees = Pattern.free_trees(n)
            yield n, len(trees), ",".join(map(str, sorted(t.automorphisms for t in trees)))


class CommModel:
    """Bytes of each method for a graph's size and a pattern's."""

    def eval(self, n: float, m: float, k: int) -> Iterator[tuple[str, float]]:
        from ..operators import cost

        yield "walk", cost.walk_bytes(n, m, k)
        yield "path", cost.path_bytes(n, m, k)
        yield "star", float(cost.star_bytes(n))
        yield "capped_star", float(cost.capped_star_bytes(n))
        yield "noisy_graph", cost.noisy_graph_bytes(n)
        yield "clipped_walk", cost.clipped_walk_bytes(n, k)


def register(spark: SparkSession) -> None:
    spark.udtf.register("free_trees", F.udtf(FreeTrees, returnType="n int, trees int, automorphisms string"))
    spark.udtf.register("comm_model", F.udtf(CommModel, returnType="method string, bytes double"))
    spark.udf.register("laplace_np", F.pandas_udf(laplace_numpy, "double"))
