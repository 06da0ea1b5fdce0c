"""Many runs in blocks against one program of rows for each run."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from patternldp.functions.pattern import ROOTED, path_tree
from patternldp.operators import baselines, cost, many, tree, walk
from patternldp.operators.kernel import make_runs
from patternldp.sources.views import Graph


@pytest.fixture(scope="module")
def graph(spark):
    """90 nodes, some isolated, one in most edges, two with negative ids."""
    rng = random.Random(3)
    pairs = [(a, b) for a in range(80) for b in range(a) if rng.random() < 0.06] + [(80, b) for b in range(60)] + [(-5, 80), (-5, -900), (-900, 3)]
    nodes = spark.createDataFrame([(i,) for i in [*range(88), -5, -900]], "id long")
    return Graph.from_pairs(nodes, spark.createDataFrame(pairs, "a long, b long")).pinned()


def as_rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("name", ["pt1", "pt2", "pt5", "fork", "d22", "d212", "path4_end", "star4_centre"])
def test_blocks_equal_rows(spark, graph, monkeypatch, name):
    monkeypatch.setattr(many, "NUMBERS", 90)
    monkeypatch.setattr(many, "CELLS", 500)  # several parts of the arcs and of the seeds
    t = path_tree(int(name[2:])) if name.startswith("pt") else ROOTED[name]
    runs = make_runs(spark, [0.2, 1.0, 30.0], reps=11)
    got = many.tree_totals(graph, runs, t)
    assert as_rows(got.estimate) == as_rows(tree.tree_dp(graph, runs, t))
    assert as_rows(got.sent) == as_rows(cost.tree_measured(graph, runs, t))


def test_draws_are_shared_by_epsilons(spark, graph, monkeypatch):
    """A node's mark was drawn for every epsilon and at every arc: 4 x 5 runs of 90 nodes and their arcs."""
    seeds = many.Seeds.of(make_runs(spark, [0.5, 1.0, 2.0, 4.0], reps=5))
    assert seeds.seeds.tolist() == [42, 43, 44, 45, 46] and seeds.eps.shape == (5, 4) and sorted(seeds.run.ravel().tolist()) == list(range(20))
    uneven = many.Seeds.of(spark.createDataFrame([(0, 7, 1.0), (1, 7, 2.0), (2, 8, 4.0)], "run int, seed long, eps double"))
    assert sorted(uneven.run.ravel().tolist()) == [-1, 0, 1, 2]
    runs = spark.createDataFrame([(0, 7, 1.0), (1, 7, 2.0), (2, 8, 4.0)], "run int, seed long, eps double")
    assert as_rows(many.tree_dp(graph, runs, ROOTED["fork"])) == as_rows(tree.tree_dp(graph, runs, ROOTED["fork"]))


def test_numbers_beyond_64_bits_stay_exact():
    a = np.array([[2**40, 3]])
    assert many.product(many.product(a, a), a).tolist() == [[2**120, 27]]
    assert many.grouped(np.array([0, 0]), np.array([[2**61], [2**61]]), 1).tolist() == [[2**62]]
    assert many.whole_numbers(np.array([0.5, -0.5, 2.5, 0.49999999999999994, 2.0**70])).tolist() == [1, -1, 3, 0, 2**70]


def test_empty_graphs(spark):
    g = Graph(spark.range(5).toDF("id"), spark.createDataFrame([], "src long, dst long"))
    runs = make_runs(spark, 1.0, reps=3)
    assert as_rows(many.tree_dp(g, runs, ROOTED["d22"])) == as_rows(tree.tree_dp(g, runs, ROOTED["d22"]))


def test_walks_of_three_edges_equal_rows(spark, graph, monkeypatch):
    monkeypatch.setattr(many, "ARCS", 40)
    runs = make_runs(spark, [0.2, 1.0, 1e9], reps=3)
    assert as_rows(many.walk3_dp(graph, runs)) == as_rows(walk.walk_dp(graph, runs, 3))
    lone = Graph(spark.range(4).toDF("id"), spark.createDataFrame([], "src long, dst long"))
    assert as_rows(many.walk3_dp(lone, runs)) == as_rows(walk.walk_dp(lone, runs, 3))


def test_exact_walks_from_the_middle(spark, graph):
    near = np.zeros((90, 90), object)
    at = {r["id"]: i for i, r in enumerate(graph.nodes.orderBy("id").collect())}
    for r in graph.arcs.collect():
        near[at[r["src"]], at[r["dst"]]] = 1
    power = np.eye(90, dtype=object)
    for k in range(1, 7):
        power = power.dot(near)
        assert int(walk.walk_exact(graph, k).first()[0]) == power.sum()


def test_clipped_walks_in_columns_equal_single_runs(spark, graph, monkeypatch):
    """Every run repeated all arcs; now a run is a column, in groups."""
    monkeypatch.setattr(baselines, "TOGETHER", 3)
    runs = make_runs(spark, [1.0, 4.0], reps=4)
    got = {r["run"]: r for r in baselines.walk_clipped(graph, runs, 3).collect()}
    assert sorted(got) == list(range(8))
    one = baselines.walk_clipped(graph, runs.where("run = 5"), 3).first()
    assert got[5]["estimate"] == pytest.approx(one["estimate"], rel=1e-9) and got[5]["top"] == one["top"] and one["rounds"] == 4
