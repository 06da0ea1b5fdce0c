"""The noisy graph in blocks against the table of all pairs, and on more nodes than a table of pairs should hold."""

import hashlib
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from patternldp.functions import draws
from patternldp.functions.pattern import ROOTED, Pattern
from patternldp.operators import baselines, noisy_graph
from patternldp.sources.views import Graph


@pytest.fixture
def several_blocks(spark, monkeypatch):
    """37 nodes in five blocks, with their noisy matrix."""
    monkeypatch.setattr(noisy_graph, "BLOCK", 8)
    nodes = spark.range(0, 370, 10).toDF("id")
    g = Graph.from_pairs(nodes, spark.range(0, 360, 10).select(F.col("id").alias("a"), ((F.col("id") * 7 + 30) % 370).alias("b"))).pinned()
    at, m = {10 * i: i for i in range(37)}, np.zeros((37, 37), int)
    table = baselines.noisy_pairs(g, 1.0).collect()
    for r in table:
        m[at[r["a"]], at[r["b"]]] = m[at[r["b"]], at[r["a"]]] = r["noisy"]
    return g, m, table


def test_draws_are_those_of_the_column_expressions():
    a, b = np.array([0, 9, 10, 99999, 2**52 - 1]), np.array([7, 0, 12, 3, 2**40])
    assert list(draws.hashed(42, "r", a, b)) == [int(hashlib.md5(f"42:r:{x}:{y}".encode()).hexdigest()[:13], 16) for x, y in zip(a, b)]
    with pytest.raises(ValueError):
        draws.hashed(42, "r", np.array([-1]))


def test_blocks_equal_the_table_of_pairs(several_blocks):
    g, m, table = several_blocks
    assert tuple(baselines.pair_stats(g, 1.0).first()) == (37 * 18, sum(r["noisy"] for r in table), sum(r["bit"] != r["noisy"] for r in table))
    w0, w1 = baselines.weights(1.0)
    w = np.where(m == 1, w1, w0)
    np.fill_diagonal(w, 0)
    walks = np.linalg.matrix_power(w, 3).sum()
    assert math.isclose(baselines.rr_walk(g, 3, 1.0).first()[0], walks, rel_tol=1e-9)
    assert math.isclose(baselines.rr_walk(g, 3, 1.0, sparse=False).first()[0], walks, rel_tol=1e-9)
    ones = m.sum(1)
    paths = sum(o * (o - 1) * w1 * w1 + 2 * o * (36 - o) * w1 * w0 + (36 - o) * (35 - o) * w0 * w0 for o in map(int, ones))
    assert math.isclose(baselines.rr_enumerate(g, Pattern.path(2), 1.0).first()[0], paths, rel_tol=1e-9)
    assert math.isclose(baselines.rr_star(g, 2, 1.0).first()[0], paths, rel_tol=1e-9)


def test_more_nodes_than_a_table_of_pairs_was_allowed(spark):
    """Over 7071 nodes the noisy pairs, and over 584 nodes the enumeration of 2-paths, were refused."""
    g = Graph(spark.range(7200).toDF("id"), spark.createDataFrame([(1, 2), (2, 1)], "src long, dst long"))
    n, ones, flipped = baselines.pair_stats(g, 1.0).first()
    assert n == 7200 * 7199 // 2 and abs(ones / n - 0.2689) < 0.001 and abs(ones - flipped) <= 1
    assert baselines.rr_enumerate(g, Pattern.path(2), 1.0).first()[0] != 0 and baselines.rr_star(g, 3, 1.0).first()[0] != 0


def test_walks_and_marked_trees_over_many_nodes(spark, monkeypatch):
    """Refused before as well; a block with one node or none and a graph of one node have their results."""
    monkeypatch.setattr(noisy_graph, "BLOCK", 4096)
    g = Graph(spark.range(7200).toDF("id"), spark.createDataFrame([(1, 2), (2, 1)], "src long, dst long"))
    assert math.isfinite(baselines.rr_walk(g, 2, 1.0).first()[0]) and math.isfinite(baselines.rr_tree_marked(g, ROOTED["fork"], 1.0, reps=1).first()[0])
    one = Graph(spark.range(1).toDF("id"), spark.createDataFrame([], "src long, dst long"))
    assert baselines.rr_walk(one, 2, 1.0).first()[0] == 0 and baselines.rr_star(one, 3, 1.0).first()[0] == 0
