"""What the mechanisms are compared with: a noisy graph, clipped walks, capped-degree stars, a central curator."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import check_epsilon, laplace, laplace_mechanism, randomized_response
from ..functions.pattern import Pattern
from ..sources.scratch import pin
from ..sources.views import Graph
from . import noisy_graph
from .kernel import whole

MAX_SEQUENCES = 200_000_000
TOGETHER = 20  # runs of a clipped walk that are columns of one table


def weights(eps: float) -> tuple[float, float]:
    """The unbiased estimates of a pair whose noisy bit is 0 and 1."""
    e = math.exp(check_epsilon(eps))
    return -1 / (e - 1), e / (e - 1)


def _guard(graph: Graph, power: int, most: int, what: str) -> int:
    n = graph.nodes.count()
    if n**power > most:
        raise ValueError(f"{what}: {n} nodes make {n**power:.3g} rows, more than {most:.3g}; its cost in nodes is why the method is a baseline")
    return n


def noisy_pairs(graph: Graph, eps: float, seed: int = 42) -> DataFrame:
    """``a`` > ``b``, ``bit``, ``noisy`` of every pair of nodes: the larger id owns the pair and perturbs it once."""
    a, b = graph.nodes.select(F.col("id").alias("a")), graph.nodes.select(F.col("id").alias("b"))
    pairs = a.join(b, F.col("a") > F.col("b"))
    bits = graph.arcs.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(1).alias("bit"))
    joined = pairs.join(bits, ["a", "b"], "left").withColumn("bit", F.coalesce("bit", F.lit(0)))
    return joined.withColumn("noisy", randomized_response(F.col("bit"), eps, F.lit(seed), F.lit("r"), F.col("a"), F.col("b")))


def _blocks(graph: Graph) -> int:
    return max(1, -(-graph.nodes.count() // noisy_graph.BLOCK))


def pair_stats(graph: Graph, eps: float, seed: int = 42) -> DataFrame:
    p = noisy_graph.pair_counts(graph, eps, seed, _blocks(graph))
    return p.agg(F.sum("n_pairs").alias("n_pairs"), F.sum("n_ones").alias("n_ones"), F.sum("n_flipped").alias("n_flipped"))


def _both(pairs: DataFrame) -> DataFrame:
    return pairs.select("a", "b", "noisy").union(pairs.select(F.col("b"), F.col("a"), "noisy"))


def rr_enumerate(graph: Graph, pattern: Pattern, eps: float, seed: int = 42, walk: bool = False, repeat: str = "product") -> DataFrame:
    """``estimate``: the sum over vertex sequences of the product of the pairs' estimates.

    Placements of a tree have distinct nodes; a walk's may repeat.  ``repeat="distinct"`` takes each pair of a walk once,
    which is unbiased; ``"product"`` takes it as often as it is walked.  Sequences are grouped by their number of pairs and of
    ones, and only the group totals meet the real-valued weights.  Placements of a star are grouped without being formed:
    a centre's noisy ones tell how many of its placements have so many ones, whatever the number of nodes.
    """
    w0, w1 = weights(eps)
    if not walk and any(all(v in e for e in pattern.edges) for v in range(pattern.n)):
        return _grouped(_star_groups(graph, pattern.k, eps, seed), w0, w1)
    _guard(graph, pattern.k + 1, MAX_SEQUENCES, "enumeration")
    pairs = pin(_both(noisy_pairs(graph, eps, seed)), "pairs")
    seqs, seen, todo = None, [0], list(pattern.edges)
    while todo:
        x, y = next(e for e in todo if (e[0] in seen) != (e[1] in seen))
        todo.remove((x, y))
        old, new = (x, y) if x in seen else (y, x)
        step = pairs.select(F.col("a").alias(f"v{old}"), F.col("b").alias(f"v{new}"), F.col("noisy").alias(f"n{new}"))
        seqs = step if seqs is None else seqs.join(step, f"v{old}")
        if not walk:
            for v in seen:
                if v != old:
                    seqs = seqs.where(F.col(f"v{v}") != F.col(f"v{new}"))
        seen.append(new)
    bits = [F.col(f"n{v}") for v in seen[1:]]
    if walk and repeat == "distinct":
        ends = [(F.least(F.col(f"v{a}"), F.col(f"v{b}")), F.greatest(F.col(f"v{a}"), F.col(f"v{b}"))) for a, b in ((v - 1, v) for v in seen[1:])]
        distinct = F.array_distinct(F.array(*[F.struct(lo.alias("lo"), hi.alias("hi"), n.alias("n")) for (lo, hi), n in zip(ends, bits)]))
        seqs = seqs.select(F.size(distinct).alias("m"), F.aggregate(distinct, F.lit(0), lambda s, e: s + e["n"]).alias("ones"))
    else:
        seqs = seqs.select(F.lit(pattern.k).alias("m"), sum(bits[1:], bits[0]).alias("ones"))
    return _grouped(seqs.groupBy("m", "ones").agg(F.count("*").alias("c")), w0, w1)


def _grouped(groups: DataFrame, w0: float, w1: float) -> DataFrame:
    return groups.agg(F.coalesce(F.sum(F.col("c") * F.pow(F.lit(w1), F.col("ones")) * F.pow(F.lit(w0), F.col("m") - F.col("ones"))), F.lit(0.0)).alias("estimate"))


def _star_groups(graph: Graph, k: int, eps: float, seed: int) -> DataFrame:
    """``m``, ``ones``, ``c``: the placements of a star with ``k`` edges by their number of noisy ones."""
    def falling(x: Column, j: int) -> Column:
        out = whole(1)
        for i in range(j):
            out = whole(out * whole(F.greatest(x - i, F.lit(0))))
        return out

    rows = noisy_graph.row_counts(graph, eps, seed, _blocks(graph)).groupBy("ones", "n").agg(F.count("*").alias("nodes"))
    each = [F.struct(F.lit(j).alias("ones"), whole(whole(F.col("nodes") * math.comb(k, j)) * whole(falling(F.col("ones"), j) * falling(F.col("n") - F.col("ones"), k - j))).alias("c")) for j in range(k + 1)]
    return rows.select(F.explode(F.array(*each)).alias("x")).groupBy(F.lit(k).alias("m"), F.col("x.ones").alias("ones")).agg(F.sum("x.c").cast("double").alias("c"))


def rr_walk(graph: Graph, k: int, eps: float, seed: int = 42, sparse: bool = True) -> DataFrame:
    """``estimate`` of the noisy-graph walk count without enumeration, by ``k`` products with the estimated matrix.

    The estimated matrix is a constant off the diagonal plus a multiple of the noisy graph; the sparse form multiplies by
    the noisy edges and one global sum, the dense form by all pairs.
    """
    w0, w1 = weights(eps)
    blocks = _blocks(graph)
    bits = pin(noisy_graph.packed_bits(graph, eps, seed, blocks), "pairs")
    x = pin(graph.nodes.select("id", F.lit(0).cast("long").alias("key"), F.lit(1.0).alias("x")), "nodes")
    for _ in range(k):
        if sparse:
            near = noisy_graph.multiply(bits, x, 0.0, 1.0, blocks)
            total = x.agg(F.sum("x").alias("t"))
            x = pin(x.join(near, ["id", "key"], "left").crossJoin(F.broadcast(total)).select("id", "key", ((w1 - w0) * F.coalesce("y", F.lit(0.0)) + w0 * (F.col("t") - F.col("x"))).alias("x")))
        else:
            x = pin(noisy_graph.multiply(bits, x, w0, w1, blocks).withColumnRenamed("y", "x"))
    return x.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("estimate"))


def rr_star(graph: Graph, k: int, eps: float, seed: int = 42) -> DataFrame:
    """``estimate`` of the noisy-graph ordered star count: the elementary symmetric sums of each row of estimates, which
    depend on the row's number of ones alone."""
    w0, w1 = weights(eps)
    rows = noisy_graph.row_counts(graph, eps, seed, _blocks(graph)).groupBy("ones", "n").agg(F.count("*").alias("c"))
    value = sum((choose(F.col("ones"), j) * choose(F.col("n") - F.col("ones"), k - j) * F.lit(w1**j * w0 ** (k - j)) for j in range(k + 1)), F.lit(0.0))
    return rows.agg(F.coalesce(F.sum(F.col("c") * value * float(math.factorial(k))), F.lit(0.0)).alias("estimate"))


def choose(n: Column, k: int) -> Column:
    """Binomial coefficient of a whole-numbered column, 0 below k."""
    out = F.lit(1.0)
    for i in range(k):
        out = out * (n.cast("double") - i) / (i + 1.0)
    return F.when(n < k, 0.0).otherwise(out)


def rr_tree_marked(graph: Graph, tree, eps: float, seed: int = 42, reps: int = 20) -> DataFrame:
    """``estimate``: the noisy-graph tree count itself estimated, by averaging marked counts over many markings.

    For patterns too large to enumerate; what it estimates is the baseline, not the graph.
    """
    from ..functions.noise import mark

    w0, w1 = weights(eps)
    blocks = _blocks(graph)
    bits = pin(noisy_graph.packed_bits(graph, eps, seed, blocks), "pairs")
    runs = graph.nodes.sparkSession.createDataFrame([(r, seed + r) for r in range(reps)], "run int, seed long")
    nodes = pin(graph.nodes.crossJoin(F.broadcast(runs)).withColumn("vertex", mark(F.col("id"), tree.k, F.col("seed"))), "nodes")
    x = {v: nodes.where(F.col("vertex") == v).select("run", "id", F.lit(1.0).alias("x")) for v in range(tree.k + 1)}
    n = tree.k + 1
    for level in tree.levels:
        children = [c for v in level for c in tree.children[v]]
        if children:  # all children of a level in one product, a key for each run and child
            held = [x[c].select("id", (F.col("run") * n + c).cast("long").alias("key"), "x") for c in children]
            sums = pin(noisy_graph.multiply(bits, reduce(DataFrame.unionByName, held), w0, w1, blocks))
        for v in level:
            for c in tree.children[v]:
                sent = sums.where(F.col("key") % n == c).select(F.floor(F.col("key") / n).cast("int").alias("run"), "id", "y")
                x[v] = x[v].join(sent, ["run", "id"], "left").select("run", "id", (F.col("x") * F.coalesce("y", F.lit(0.0))).alias("x"))
            x[v] = pin(x[v])
    per_run = runs.select("run").join(x[tree.root].groupBy("run").agg(F.sum("x").alias("s")), "run", "left")
    return per_run.agg((F.avg(F.coalesce("s", F.lit(0.0))) * float(tree.factor)).alias("estimate"))


def noisy_max_degree(graph: Graph, runs: DataFrame) -> DataFrame:
    """``run``, ``top``: the maximum of the degrees with noise for a tenth of the budget, at least 1."""
    d = graph.degrees().crossJoin(F.broadcast(runs))
    noisy = F.col("degree").cast("double") + laplace(F.lit(20.0) / F.col("eps"), F.col("seed"), F.lit("x"), F.col("id"))
    return d.groupBy("run").agg(F.greatest(F.lit(1.0), F.max(noisy)).alias("top"))


def walk_clipped(graph: Graph, runs: DataFrame, k: int, factor: str = "sqrt") -> DataFrame:
    """``run``, ``estimate``, ``top``, ``rounds``: walks whose counts are clipped to powers of a threshold.

    The threshold is the noisy maximum degree or its root (``sqrt``); noise is set by the clip, not by the counts.
    """
    if factor not in ("sqrt", "degree"):
        raise ValueError(f"unknown factor {factor!r}")
    top = {r["run"]: r["top"] for r in noisy_max_degree(graph, runs).collect()}
    rows = runs.select("run", "seed", "eps").collect()
    parts = [_clipped(graph, [(r["run"], r["seed"], r["eps"], top[r["run"]]) for r in rows[i : i + TOGETHER] if r["run"] in top], k, factor) for i in range(0, len(rows), TOGETHER)]
    return reduce(DataFrame.unionByName, parts)


def _clipped(graph: Graph, runs: list[tuple[int, int, float, float]], k: int, factor: str) -> DataFrame:
    """A column for each run, so that an arc is joined once for all of them; the first sum is the degree."""
    x = graph.degrees().select("id", *[F.col("degree").cast("double").alias(f"y{run}") for run, *_ in runs]) if k else graph.nodes
    schema = "run int, estimate double, top double, rounds int"
    if not runs or not k:
        n = float(graph.nodes.count())
        return graph.nodes.sparkSession.createDataFrame([(run, n, top, 1) for run, _, _, top in runs], schema)
    for level in range(1, k + 1):
        if level > 1:
            sent = graph.arcs.join(x.withColumnRenamed("id", "src"), "src")
            x = graph.nodes.join(sent.groupBy(F.col("dst").alias("id")).agg(*[F.sum(f"x{run}").alias(f"y{run}") for run, *_ in runs]), "id", "left")
        released = []
        for run, seed, eps, top in runs:
            tau = math.sqrt(top) if factor == "sqrt" else top
            scale = F.lit(2.0 * k / 0.9) / F.lit(eps) * F.pow(F.lit(tau), F.lit(float(level - 1)))
            noisy = F.coalesce(F.col(f"y{run}"), F.lit(0.0)) + laplace(scale, F.lit(seed), F.lit(f"c{level}"), F.col("id"))
            released.append(F.greatest(F.lit(0.0), F.least(noisy, F.pow(F.lit(tau), F.lit(float(level))))).alias(f"x{run}"))
        x = pin(x.select("id", *released))
    sums = x.agg(*[F.sum(f"x{run}").alias(f"x{run}") for run, *_ in runs])
    each = F.array(*[F.struct(F.lit(run).cast("int").alias("run"), F.col(f"x{run}").alias("estimate"), F.lit(top).alias("top"), F.lit(k + 1).alias("rounds")) for run, _, _, top in runs])
    return sums.select(F.explode(each).alias("r")).select("r.*")


def star_capped(graph: Graph, runs: DataFrame, k: int) -> DataFrame:
    """``run``, ``estimate`` (ordered), ``top``, ``rounds``: stars of degrees capped at the noisy maximum, Laplace noise for the cap."""
    top = noisy_max_degree(graph, runs).withColumn("top", F.ceil("top").cast("long"))
    d = graph.degrees().crossJoin(F.broadcast(runs.join(top, "run")))
    scale = F.lit(2.0 / 0.9) * choose(F.col("top") - 1, k - 1) / F.col("eps")
    value = choose(F.least(F.col("degree"), F.col("top")), k) + laplace(scale, F.col("seed"), F.lit("k"), F.col("id"))
    return d.groupBy("run", "top").agg((F.sum(value) * float(math.factorial(k))).alias("estimate")).select("run", "estimate", "top", F.lit(2).alias("rounds"))


def star_sensitivity(k: int, cap: int) -> int:
    """What one edge can change of the ordered star count on degrees clipped to ``cap``: both of its ends move by one."""
    return 2 * k * math.prod(range(cap - k + 1, cap))


def central_star(graph: Graph, runs: DataFrame, k: int, cap: int) -> DataFrame:
    """``run``, ``estimate``: a trusted curator's noisy star count on degrees clipped to a public cap."""
    d = F.least(F.col("degree"), F.lit(cap)).cast("decimal(38,0)")
    value = d
    for i in range(1, k):
        value = (value * (d - i)).cast("decimal(38,0)")
    exact = graph.degrees().agg(F.coalesce(F.sum(value).cast("decimal(38,0)"), F.lit(0).cast("decimal(38,0)")).alias("ordered"))
    noisy = laplace_mechanism(F.col("ordered"), star_sensitivity(k, cap), F.col("eps"), F.col("seed"), F.lit("central"))
    return runs.crossJoin(F.broadcast(exact)).select("run", noisy.alias("estimate"))
