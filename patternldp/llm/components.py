"""Connected components by repeated contraction, all in tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import materialise


def components(edges: DataFrame) -> DataFrame:
    """``node``, ``label`` for every node of the edges (columns ``a``, ``b``, longs); one label per component.

    Each round maps a node to the least node beside it and contracts the edges.  Node numbers must be hashes:
    then a fixed share of the nodes goes in each round and rounds grow with the logarithm of the longest chain.
    """
    e = materialise(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    labels = None
    while not e.isEmpty():
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        step = materialise(both.groupBy(F.col("a").alias("v")).agg(F.min("b").alias("m")).select("v", F.least("v", "m").alias("m")), "contract")
        low = step.select(F.col("v").alias("a"), F.col("m").alias("ma"))
        high = step.select(F.col("v").alias("b"), F.col("m").alias("mb"))
        e = materialise(e.join(low, "a").join(high, "b").where("ma <> mb").select(F.least("ma", "mb").alias("a"), F.greatest("ma", "mb").alias("b")).distinct(), "edges")
        if labels is None:
            labels = step.select(F.col("v").alias("node"), F.col("m").alias("label"))
        else:
            moved = step.select(F.col("v").alias("label"), F.col("m").alias("_to"))
            labels = materialise(labels.join(moved, "label", "left").select("node", F.coalesce("_to", "label").alias("label")), "labels")
    if labels is None:
        labels = edges.sparkSession.createDataFrame([], "node long, label long")
    return labels
