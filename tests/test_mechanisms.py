import math
import random
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from patternldp.functions.noise import check_epsilon, laplace, lattice_laplace, mark, to_whole, unbiased_bit
from patternldp.functions.pattern import ROOTED, NotSupported, Pattern, path_tree
from patternldp.operators import audit, baselines, bounds, cost, exact, star, tree, walk
from patternldp.operators.kernel import Noise, make_runs
from patternldp.plans import ledger, protocol
from patternldp.sources.views import Graph, view


def graph_of(spark, n, pairs):
    nodes = spark.createDataFrame([(i,) for i in range(n)], "id long")
    return Graph.from_pairs(nodes, spark.createDataFrame(pairs or [(0, 0)], "a long, b long"))


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(5)
    pairs = [(a, b) for a in range(12) for b in range(a) if rng.random() < 0.35]
    return graph_of(spark, 13, pairs).pinned(), pairs


def placements(n, pairs, pattern):
    near = defaultdict(set)
    for a, b in pairs:
        near[a].add(b)
        near[b].add(a)

    def extend(at):
        v = len(at)
        if v == pattern.n:
            return 1
        old = [u for u in pattern.neighbours(v) if u < v]
        return sum(extend([*at, x]) for x in range(n) if x not in at and all(x in near[at[u]] for u in old))

    return extend([])


def one(df):
    return int(df.first()[0])


def test_exact_counts(small):
    g, pairs = small
    for p in (Pattern.path(2), Pattern.path(3), ROOTED["fork"].pattern(), Pattern.star(3)):
        want = placements(13, pairs, p)
        assert one(exact.tree_exact(g, p)) == want
        assert one(exact.tree_exact_by_quotients(g, p)) == want
    assert one(exact.closed_form(g, "path2")) == placements(13, pairs, Pattern.path(2))
    assert one(exact.closed_form(g, "path3")) == placements(13, pairs, Pattern.path(3))
    assert one(exact.closed_form(g, "fork")) == placements(13, pairs, ROOTED["fork"].pattern())
    assert one(exact.star_exact(g, 3)) == placements(13, pairs, Pattern.star(3))
    assert one(walk.walk_exact(g, 0)) == 13


def test_golden_walks(spark):
    g = view(spark, "/root/testdata/sf0.01", "copurchase").pinned()
    runs = make_runs(spark)
    for k, want in {2: 86170, 3: 549997, 4: -10587735}.items():
        assert int(walk.walk_dp(g, runs, k).first()["estimate"]) == want
    assert one(walk.walk_exact(g, 3)) == 654740 and one(exact.closed_form(g, "fork")) == 3518034


def test_large_epsilon_is_exact(spark, small):
    g, pairs = small
    runs = make_runs(spark, 1e9)
    assert int(walk.walk_dp(g, runs, 3).first()["estimate"]) == one(walk.walk_exact(g, 3))
    assert int(walk.walk_dp(g, runs, 3, "rounds_k").first()["estimate"]) == one(walk.walk_exact(g, 3))
    assert int(star.star_dp(g, runs, 3).first()["estimate"]) == one(exact.star_exact(g, 3))
    for t in (path_tree(3), ROOTED["fork"]):
        r = tree.tree_dp(g, runs, t).first()
        assert r["estimate"] == r["marked_estimate"]


def test_marked_counts_by_brute_force(spark, small):
    g, pairs = small
    near = defaultdict(set)
    for a, b in pairs:
        near[a].add(b)
        near[b].add(a)
    for t in (path_tree(2), path_tree(3), ROOTED["fork"], ROOTED["d22"]):
        marks = {r["id"]: r["m"] for r in g.nodes.select("id", mark(F.col("id"), t.k, F.lit(42)).alias("m")).collect()}

        def below(v, x):
            return math.prod(sum(below(c, y) for y in near[x] if marks[y] == c) for c in t.children[v])

        want = t.factor * sum(below(t.root, x) for x in range(13) if marks[x] == t.root)
        assert int(tree.tree_dp(g, make_runs(spark), t).first()["marked_estimate"]) == want


def test_unbiased(spark, small):
    g, pairs = small
    runs = make_runs(spark, 8.0, reps=400)
    for df, true in ((walk.walk_dp(g, runs, 2), one(walk.walk_exact(g, 2))), (tree.path_dp(g, runs, 2), placements(13, pairs, Pattern.path(2)))):
        m, s, n = df.select(F.avg(F.col("estimate").cast("double")), F.stddev(F.col("estimate").cast("double")), F.count("*")).first()
        assert abs(m - true) <= 4.5 * s / math.sqrt(n)
    d = star.star_dp(g, make_runs(spark, 1.0, reps=400), 2, debias=True).select(F.avg("estimate"), F.stddev("estimate")).first()
    assert abs(d[0] - one(exact.star_exact(g, 2))) <= 4.5 * d[1] / 20


def test_walk_bound_holds(spark, small):
    g, _ = small
    runs = make_runs(spark, 1.0, reps=60)
    b = bounds.bounds_table(g, 3).first()
    true = one(walk.walk_exact(g, 3))
    off = [abs(float(r["estimate"]) - true) for r in walk.walk_dp(g, runs, 3).collect()]
    assert sum(x <= b["walk"] for x in off) >= 54


def test_privacy_loss(spark, small):
    g, _ = small
    runs = make_runs(spark, 1.0, reps=3)
    assert all(r["max_loss"] <= 1 + 1e-9 for r in audit.walk_loss(g, runs, 4).collect())
    for t in (path_tree(3), ROOTED["d22"]):
        assert all(r["max_loss"] <= 1 + 1e-9 and r["max_sums"] <= 1 for r in audit.tree_loss(g, runs, t).collect())


def test_edge_cases(spark):
    empty = graph_of(spark, 4, [])
    runs = make_runs(spark, 1e9)
    assert int(walk.walk_dp(empty, runs, 3).first()["estimate"]) == 0
    assert int(tree.tree_dp(empty, runs, ROOTED["fork"]).first()["estimate"]) == 0
    assert one(exact.closed_form(empty, "path3")) == 0 and one(walk.walk_exact(empty, 2)) == 0
    triangle = graph_of(spark, 3, [(0, 1), (1, 2), (2, 0), (1, 0), (1, 1)])
    assert triangle.arcs.count() == 6
    assert one(exact.path_exact(triangle, 3)) == 0 and one(walk.walk_exact(triangle, 3)) == 24
    triangle.validate()
    single = tree.tree_dp(triangle, runs, Pattern.parse("").rooted_at(0)).first()
    assert int(single["marked_estimate"]) == 3
    for bad in (0, -1, float("nan"), float("inf")):
        with pytest.raises(ValueError):
            check_epsilon(bad)
    with pytest.raises(ValueError):
        walk.walk_exact(triangle, -1)
    with pytest.raises(ValueError):
        bounds.check_beta(1.0)


def test_baselines(spark, small):
    g, _ = small
    w = baselines.rr_walk(g, 3, 1.0).first()[0]
    assert math.isclose(w, baselines.rr_walk(g, 3, 1.0, sparse=False).first()[0], rel_tol=1e-9)
    assert math.isclose(w, baselines.rr_enumerate(g, Pattern.path(3), 1.0, walk=True).first()[0], rel_tol=1e-9)
    assert math.isclose(baselines.rr_star(g, 2, 1.0).first()[0], baselines.rr_enumerate(g, Pattern.star(2), 1.0).first()[0], rel_tol=1e-9)
    with pytest.raises(ValueError):
        baselines._guard(g, 9, 10, "enumeration")
    p1, p0 = (spark.range(1).select(unbiased_bit(F.lit(b), 1.0)).first()[0] for b in (1, 0))
    q = math.e / (1 + math.e)
    assert math.isclose(q * p1 + (1 - q) * p0, 1) and math.isclose(q * p0 + (1 - q) * p1, 0, abs_tol=1e-12)


def test_ours_beat_the_baselines(spark):
    g = view(spark, "/root/testdata/sf0.01", "trade").pinned()
    runs = make_runs(spark, reps=10)
    true = walk.walk_exact(g, 3)
    ours = protocol.protocol(runs, walk.walk_dp(g, runs, 3), true).first()["rel_err"]
    other = protocol.protocol(runs, baselines.walk_clipped(g, runs, 3), true).first()["rel_err"]
    assert ours < 3 and other > 80
    s, c = (protocol.protocol(runs, f, exact.star_exact(g, 4)).first()["rel_err"] for f in (star.star_dp(g, runs, 4), baselines.star_capped(g, runs, 4)))
    assert s < c


def test_byte_formulas():
    mb = lambda x: round(x / cost.MB, 2)
    n, m = 18_771, 198_050
    assert [mb(cost.walk_bytes(n, m, k)) for k in (4, 5, 6)] == pytest.approx([6.76, 10.07, 13.38], rel=0.0025)
    assert [mb(cost.path_bytes(n, m, k)) for k in (4, 5, 6)] == pytest.approx([3.55, 3.58, 3.60], rel=0.0025)
    assert [mb(cost.tree_bytes(n, m, k, i)) for k, i in ((4, 2), (5, 2), (6, 3))] == pytest.approx([3.37, 3.32, 3.39], rel=0.0025)
    assert mb(cost.noisy_graph_bytes(n)) == pytest.approx(168.0, rel=0.0025)
    assert cost.clipped_walk_bytes(n, 4) / cost.GB == pytest.approx(10.50, rel=0.0025)
    assert mb(cost.star_bytes(n)) == pytest.approx(0.14, abs=0.01) and mb(cost.capped_star_bytes(n)) == pytest.approx(0.43, abs=0.01)


def test_measured_bytes_follow_the_formula(spark):
    g = view(spark, "/root/testdata/sf0.01", "trade").pinned()
    s = g.stats().first()
    runs = make_runs(spark, reps=10)
    for t in (path_tree(4), ROOTED["fork"]):
        mean = cost.tree_measured(g, runs, t).groupBy("run").agg(F.sum("bytes").alias("b")).agg(F.avg("b")).first()[0]
        assert mean == pytest.approx(cost.tree_bytes(s["n_nodes"], s["n_edges"], t.k, len(t.internal)), rel=0.02)


def test_ledgers():
    assert ledger.walk_ledger(4, 1.0).total == pytest.approx(1.0) and ledger.walk_ledger(4, 1.0, "rounds_k").total == pytest.approx(1.0)
    assert ledger.tree_ledger(ROOTED["d212"], 1.0).total == 1.0 and ledger.star_ledger(2.0).total == 2.0
    assert ledger.averaged_ledger(5, 1.0).total == pytest.approx(1.0) and ledger.baseline_ledger("capped_star", 1.0).total == pytest.approx(1.0)
    with pytest.raises(ValueError):
        ledger.window_ledger(3, 1.0).demand(2.0)
    with pytest.raises(NotSupported):
        ledger.PrivacyLedger(ledger.Neighbouring.NODE)


def test_noise(spark):
    df = spark.range(20000)
    x = df.select(laplace(F.lit(2.0), F.lit(1), F.col("id")).alias("x")).select(F.avg("x"), F.var_pop("x")).first()
    assert abs(x[0]) < 0.1 and abs(x[1] - 8) < 0.8
    y = df.select(lattice_laplace(F.lit(2.0), F.lit(1), F.col("id")).alias("y")).agg(F.avg(F.col("y").cast("double"))).first()[0]
    assert abs(y) < 0.1
    big = spark.range(1).select(*[to_whole(F.lit(v)).cast("string") for v in (-(2.0**70), 2.0**60 + 2.0**10, -3.0)]).first()
    assert list(big) == [str(-(2**70)), str(2**60 + 2**10), "-3"]
    c = df.select(mark(F.col("id"), 4, F.lit(9)).alias("m")).groupBy("m").count().collect()
    assert len(c) == 5 and sum((r["count"] - 4000) ** 2 / 4000 for r in c) < 20


def test_continuous_and_lattice_agree(spark, small):
    g, _ = small
    runs = make_runs(spark, 4.0)
    a = float(walk.walk_dp(g, runs, 2).first()["estimate"])
    b = walk.walk_dp(g, runs, 2, noise=Noise(lattice=False)).first()["estimate"]
    assert abs(a - b) < 13 * 12 * 2


def test_plans_have_no_cartesian_or_python(spark, small):
    g, _ = small
    text = tree.kept_arcs(g, make_runs(spark), path_tree(3))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "Python" not in text
    scan = view(spark, "/root/testdata/sf0.001", "copurchase").arcs._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity)" in scan and "l_extendedprice" not in scan


def test_scales_of_the_worked_examples():
    """Two rounds at epsilon 4 give every node and round a share of 1; a three-edge path under marks is rescaled by 256."""
    shares = [e for name, e in ledger.walk_ledger(2, 4.0).entries if e]
    assert shares == [2.0, 2.0] and ledger.walk_ledger(2, 4.0).total == pytest.approx(4.0)  # both endpoints, 1 each
    assert path_tree(3).factor == 256 and path_tree(3).rounds == 3
    assert ledger.tree_ledger(path_tree(3), 1.0).total == 1.0  # public marks give neither a split nor a discount


def test_bytes_depend_on_neither_epsilon_nor_much_on_the_pattern(spark):
    g = view(spark, "/root/testdata/sf0.001", "trade").pinned()
    means = []
    for t in (path_tree(4), path_tree(5), path_tree(6), ROOTED["fork"], ROOTED["fork_alt"], ROOTED["d22"]):
        by = {e: protocol.mean_bytes(make_runs(spark, e, reps=4), cost.tree_measured(g, make_runs(spark, e, reps=4), t)).first()["comm_mean"] for e in (0.2, 4.0)}
        assert len(set(by.values())) == 1
        means.append(by[0.2])
    assert max(means) < 1.35 * min(means)


def test_zero_reporting_costs_more_and_routing_less():
    n, m = 1000, 5000
    for k in (4, 5, 6):
        assert cost.tree_bytes(n, m, k, k - 1, "zero") > cost.path_bytes(n, m, k)
        assert cost.walk_bytes(n, m, k) < cost.walk_bytes(n, m, k, routing="broadcast")


def test_tail_bounds_hold():
    rng = random.Random(9)
    scales = [1.0, 2.0, 0.5, 3.0]
    draw = lambda b: b * math.log(rng.random() / rng.random())
    sums = [abs(sum(draw(b) for b in scales)) for _ in range(4000)]
    assert sum(s > bounds.laplace_sum_bound(scales, 0.1) for s in sums) / len(sums) <= 0.1
    heads = [sum(rng.random() < 0.5 for _ in range(100)) for _ in range(4000)]
    for delta in (0.1, 0.2, 0.4):
        assert sum(h >= (1 + delta) * 50 for h in heads) / len(heads) <= bounds.chernoff_upper(50.0, delta)
    assert sum(abs(h - 50) >= 3 * 5 for h in heads) / len(heads) <= bounds.chebyshev(3.0)


def test_labelled_patterns_by_brute_force(spark, small):
    """A node's kind is its id modulo 8; only nodes of the asked kind hold a vertex."""
    g, pairs = small
    t, kinds = path_tree(2), (None, 3, 1)
    near = defaultdict(set)
    for a, b in pairs:
        near[a].add(b)
        near[b].add(a)
    marks = {r["id"]: r["m"] for r in g.nodes.select("id", mark(F.col("id"), t.k, F.lit(42)).alias("m")).collect()}
    holds = {x: m for x, m in marks.items() if kinds[m] is None or x % 8 == kinds[m]}
    want = t.factor * sum(math.prod(sum(holds.get(y) == c for y in near[x]) for c in t.children[t.root]) for x, m in holds.items() if m == t.root)
    got = tree.tree_dp(g, make_runs(spark, 1e9), t, kinds=kinds).first()
    assert int(got["marked_estimate"]) == want == int(got["estimate"])


def test_marked_only_equals_the_marked_estimate(spark, small):
    g, _ = small
    runs = make_runs(spark, reps=5)
    for t in (path_tree(3), ROOTED["fork"], ROOTED["d212"]):
        a = {r["run"]: r["estimate"] for r in tree.tree_marked(g, runs, t).collect()}
        assert a == {r["run"]: r["marked_estimate"] for r in tree.tree_dp(g, runs, t).collect()}


def test_central_noise_covers_both_ends(spark, small):
    g, _ = small
    runs = make_runs(spark)
    for cap in (3, 5, 64):
        assert audit.central_star_loss(g, runs, 3, cap).first()["max_loss"] <= 1.0
    star5 = graph_of(spark, 8, [(a, b) for a in range(7) for b in range(a)])
    assert audit.central_star_loss(star5, runs, 3, 6).first()["max_loss"] == pytest.approx(1.0)  # tight where both ends are at the cap
