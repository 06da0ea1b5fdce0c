"""Exact counts that form no placement, against the chain of joins and on a star too large to enumerate."""

import random

import pytest
from pyspark.sql import functions as F

from patternldp.functions.pattern import ROOTED, Pattern
from patternldp.operators import exact
from patternldp.sources.views import Graph


def test_hubs_are_not_enumerated(spark):
    """Two hubs with 20,000 leaves each on a common root: 8e8 ordered 4-paths, which joins would form one by one."""
    pairs = spark.range(40000).select((F.col("id") + 10).alias("a"), (F.col("id") % 2 + 1).alias("b")).union(spark.createDataFrame([(1, 0), (2, 0)], "a long, b long"))
    g = Graph.from_pairs(pairs.select(F.col("a").alias("id")).union(spark.range(3).toDF("id")).distinct(), pairs)
    assert int(exact.path_exact(g, 4).first()[0]) == 2 * 20000 * 20000
    d22 = exact.tree_exact(g, ROOTED["d22"].pattern()).first()[0]  # edges hub-root: the root has one other neighbour, too few
    assert int(d22) == 0


@pytest.mark.parametrize("pattern", [Pattern.path(3), Pattern.path(4), ROOTED["fork"].pattern(), ROOTED["d22"].pattern(), ROOTED["d212"].pattern()])
def test_cycles_equal_joins(spark, pattern):
    """A graph with triangles, squares, chords, ends and an isolated node."""
    rng = random.Random(11)
    pairs = [(a, b) for a in range(9) for b in range(a) if rng.random() < 0.5] + [(9, 0), (10, 9), (11, 3)]
    g = Graph.from_pairs(spark.range(13).toDF("id"), spark.createDataFrame(pairs, "a long, b long")).pinned()
    want = exact.tree_exact_by_joins(g, pattern).first()[0]
    assert want > 0 and exact.tree_exact(g, pattern).first()[0] == want


def test_a_pinned_graph_is_dealt_to_all_cores(spark):
    """Its few bytes lay in one file, so that one task drew the noise of all runs."""
    g = Graph(spark.range(0, 5000, 1, 1).toDF("id"), spark.range(0, 5000, 1, 1).select(F.col("id").alias("src"), F.col("id").alias("dst"))).pinned()
    assert len(g.nodes.inputFiles()) > 1 and len(g.arcs.inputFiles()) > 1 and g.pinned() is g and g.nodes.count() == 5000
