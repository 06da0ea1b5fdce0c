"""The experiments as they are run: ten runs a cell, errors and bytes side by side, for trees, walks, stars and baselines."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import ROOTED, RootedPattern, path_tree
from ..operators import audit, baselines, bounds, cost, exact, many, star, tree, walk
from ..operators.kernel import make_runs
from ..plans import protocol as proto
from ..sources.views import Graph
from . import sql
from .methods import _ERR, _STATS, EPS_SWEEP, W0, W1, add, capped_sql, clipped_sql, comm_sql, digits, estimate, on, rr_walk_sql, trimmed_sql, tree_query, walk_query

TREES: dict[str, RootedPattern] = {f"pt{k}": path_tree(k) for k in (4, 5, 6)} | {p: t for p, t in ROOTED.items() if not p.startswith(("path", "star"))}


def truth_of(v: str, t: RootedPattern) -> str:
    """A query for the ordered count."""
    return f"SELECT CAST(ordered AS HUGEINT) AS t FROM ({sql.placements(v, t.pattern())})"


def bytes_of(t: RootedPattern) -> str:
    """CTEs ``ch`` and ``cm`` (run, bytes) after those of ``tree_estimates``."""
    return comm_channels(t) + ",\ncm AS (SELECT run, CAST(sum(messages) * 8 AS BIGINT) AS bytes FROM ch GROUP BY run)"


def comm_channels(t: RootedPattern) -> str:
    whole = comm_sql("copurchase", t)
    return ",\nch AS (" + whole.partition(",\nch AS (")[2].rpartition("\nSELECT run, channel")[0]


# Trees: error and bytes by epsilon.
def tree_protocol(v: str, t: RootedPattern, eps: float | list[float] = 1.0) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    def make(g: Graph) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, eps, reps=proto.REPS)
        got = many.tree_totals(g, r, t)
        error = proto.protocol(r, got.estimate, exact.tree_exact(g, t.pattern()))
        sent = proto.mean_bytes(r, got.sent)
        return error.join(sent, "eps").select("eps", digits("rel_err"), digits("comm_mean"))

    o = sql.graph(v) + ",\n" + sql.runs(eps, 42, proto.REPS) + sql.tree_estimates(t) + bytes_of(t)
    o += f",\ntr AS ({truth_of(v, t)}),\nerr AS (SELECT eps, {_ERR} AS e FROM est JOIN runs USING (run) CROSS JOIN tr),\nte AS ({trimmed_sql('eps')}),\nmb AS (SELECT eps, {sql.digits('avg(bytes)')} AS comm_mean FROM cm JOIN runs USING (run) GROUP BY eps)\nSELECT eps, rel_err, comm_mean FROM te JOIN mb USING (eps)"
    return on(v, make, True), o


for p, v in [(p, "trade_sparse") for p in ("pt4", "pt5", "pt6", "fork", "d22", "spider2111", "d212", "spider2211")] + [("pt4", "copurchase"), ("fork", "copurchase"), ("d22", "geo_forest")]:
    add(f"protocol_{p}_{v}", *tree_protocol(v, TREES[p]))
for p, v in (("fork", "trade_sparse"), ("pt5", "trade_sparse"), ("d22", "trade_sparse")):
    add(f"eps_sweep20_{p}_{v}", *tree_protocol(v, TREES[p], EPS_SWEEP))
for v in ("copurchase", "trade_sparse", "geo_forest"):
    for first, second in (("fork", "fork_alt"), ("d22", "d22_alt")):
        if (v, first) == ("copurchase", "d22"):
            continue
        parts = {p: tree_protocol(v, TREES[p]) for p in (first, second)}

        def _both(spark: SparkSession, d: str, parts: dict = parts) -> DataFrame:
            a, b = (make(spark, d).select(F.lit(p).alias("tree"), F.lit(TREES[p].rounds).alias("rounds"), "rel_err", "comm_mean") for p, (make, _) in parts.items())
            return a.unionByName(b)

        add(f"rootings_{first}_{v}", _both, "\nUNION ALL\n".join(f"SELECT '{p}' AS tree, {TREES[p].rounds} AS rounds, rel_err, comm_mean FROM ({o})" for p, (_, o) in parts.items()))


# Walks and stars beside their baselines: error, bytes, and how many times the baseline's are.
def _bytes_literal(method: str, k: int) -> tuple[Callable, str]:
    """The byte formula on columns n and m, and in SQL."""
    spoken = {
        "walk": (lambda n, m: cost.walk_bytes(n, m, k), f"8e0 * ({max(0, k - 2)} * (2 * m + 2 * n) + n)"), "clipped_walk": (lambda n, m: cost.clipped_walk_bytes(n, k), f"8e0 * {k} * n * n"),
        "star": (lambda n, m: cost.star_bytes(n), "8e0 * n"), "capped_star": (lambda n, m: cost.capped_star_bytes(n), "24e0 * n"), "noisy_graph": (lambda n, m: cost.noisy_graph_bytes(n), "n * (n - 1) / 2"),
    }
    return spoken[method]


def _size(g: Graph) -> DataFrame:
    return g.stats().select(F.col("n_nodes").cast("double").alias("n"), F.col("n_edges").cast("double").alias("m"))


def _walk_truth(k: int) -> str:
    return ",\nw1 AS (SELECT id, CAST(d AS HUGEINT) AS x FROM deg)" + "".join(f",\nw{i} AS (SELECT dst AS id, sum(x) AS x FROM arcs JOIN w{i - 1} ON id = src GROUP BY dst)" for i in range(2, k + 1)) + f",\ntr AS (SELECT sum(x) AS t FROM w{k})"


def versus(v: str, kind: str, k: int) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    ours, other = ("walk", "clipped_walk") if kind == "wk" else ("star", "capped_star")
    f_ours, s_ours = _bytes_literal(ours, k)
    f_other, s_other = _bytes_literal(other, k)

    def make(g: Graph) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, reps=proto.REPS)
        if kind == "wk":
            true, a, b = walk.walk_exact(g, k), many.walk3_dp(g, r) if k == 3 else walk.walk_dp(g, r, k), baselines.walk_clipped(g, r, k)
        else:
            true, a, b = exact.star_exact(g, k), star.star_dp(g, r, k), baselines.star_capped(g, r, k)
        both = proto.protocol(r, a, true).select("eps", F.col("rel_err").alias("ours")).join(proto.protocol(r, b, true).select("eps", F.col("rel_err").alias("other")), "eps").crossJoin(F.broadcast(_size(g)))
        n, m = F.col("n"), F.col("m")
        return both.select(digits("ours"), digits("other"), F.format_string("%.3e", F.col("other") / F.col("ours")).alias("error_gain"), digits(f_ours(n, m), "bytes_ours"), digits(f_other(n, m), "bytes_other"), digits(f_other(n, m) / f_ours(n, m), "comm_gain"))

    head = sql.graph(v) + ",\n" + sql.runs(1.0, 42, proto.REPS)
    if kind == "wk":
        mine = head + sql.walk_estimates(k, "") + "\nSELECT run, CAST(estimate AS DOUBLE) AS estimate FROM est"
        theirs = clipped_sql(v, k, proto.REPS, raw=True)
        true = _walk_truth(k)
    else:
        mine = head + sql.star_estimates(k) + "\nSELECT run, CAST(estimate AS DOUBLE) AS estimate FROM est"
        theirs, true = capped_sql(v, k, proto.REPS, raw=True), f",\ntr AS (SELECT sum({sql.falling('CAST(d AS HUGEINT)', k)}) AS t FROM deg)"
    mean = lambda x: f"(SELECT avg(e) FROM (SELECT {_ERR} AS e, row_number() OVER (ORDER BY {_ERR}) AS r FROM ({x}) CROSS JOIN tr) WHERE r > 2 AND r <= 8)"
    o = sql.graph(v) + true + _STATS + f",\nb AS (SELECT {mean(mine)} AS ours, {mean(theirs)} AS other)\nSELECT {sql.digits('ours')} AS ours, {sql.digits('other')} AS other, printf('%.3e', other / ours) AS error_gain, {sql.digits(s_ours)} AS bytes_ours, {sql.digits(s_other)} AS bytes_other, {sql.digits(f'({s_other}) / ({s_ours})')} AS comm_gain FROM b CROSS JOIN st"
    return on(v, make, True), o


for v, kind, k in (("trade", "wk", 3), ("handoff", "wk", 3), ("handoff", "wk", 4), ("handoff", "wk", 5), ("handoff", "wk", 6), ("trade", "star", 3), ("trade", "star", 4), ("trade", "star", 5), ("handoff", "star", 3)):
    add(f"improve_{kind}{k}_{v}", *versus(v, kind, k))
for v, k in (("copurchase", 6), ("handoff", 5), ("handoff", 6)):
    add(f"wk_dp_opt{k}_{v}", *walk_query(v, k, "rounds_k_minus_1"))
for v, k in (("handoff", 5), ("handoff", 6)):
    add(f"clip_wk{k}_{v}", on(v, lambda g, k=k: baselines.walk_clipped(g, make_runs(g.nodes.sparkSession), k).select("run", digits("estimate"), digits("top"), "rounds"), True), clipped_sql(v, k))
    add(f"rr_walk_{k}_{v}", on(v, lambda g, k=k: baselines.rr_walk(g, k, 1.0).select(digits("estimate"))), rr_walk_sql(v, k))


# Marked counts without noise.
def marked_only(v: str, t: RootedPattern) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    o = sql.graph(v) + ",\n" + sql.runs() + sql.tree_estimates(t) + "\nSELECT run, CAST(marked_estimate AS VARCHAR) AS estimate FROM est"
    return on(v, lambda g: tree.tree_marked(g, make_runs(g.nodes.sparkSession), t).select("run", F.col("estimate").cast("string").alias("estimate")), True), o


for k, v in ((2, "trade"), (3, "trade"), (4, "copurchase"), (5, "copurchase"), (6, "copurchase")):
    add(f"pt_marked{k}_{v}", *marked_only(v, path_tree(k)))
for p in ("fork", "d22", "d212", "spider2111", "spider2211"):
    add(f"tree_marked_{p}_copurchase", *marked_only("copurchase", ROOTED[p]))
for p in ("spider3111", "d22_leg"):
    add(f"tree_dp_{p}_trade_sparse", *tree_query("trade_sparse", ROOTED[p]))


# Labelled patterns: a vertex that only nodes of one kind may hold.
def labelled(v: str, t: RootedPattern, kinds: tuple[int | None, ...]) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    o = sql.graph(v) + ",\n" + sql.runs() + sql.tree_estimates(t, kinds=kinds) + f"\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, CAST(marked_estimate AS VARCHAR) AS marked_estimate, {t.rounds} AS rounds FROM est"
    return on(v, lambda g: estimate(tree.tree_dp(g, make_runs(g.nodes.sparkSession), t, kinds=kinds), "marked_estimate"), True), o


# The kinds of nodes in ids (1 part, 2 supplier, 3 customer).
add("tree_dp_labelled_pt2_trade", *labelled("trade", path_tree(2), (3, 1, 3)))
add("tree_dp_labelled_fork_trade", *labelled("trade", ROOTED["fork"], (1, 3, 3, None, 1)))


# Errors of the marks, of the noise and of both, by run; and by the number of averaged runs.
for p, v in (("pt4", "copurchase"), ("pt4", "trade_sparse"), ("pt5", "trade_sparse"), ("fork", "copurchase"), ("fork", "trade_sparse"), ("d22", "trade_sparse"), ("d22", "geo_forest")):
    t = TREES[p]
    share = lambda a, b: sql.digits(f"100.0e0 * abs(CAST({a} AS DOUBLE) - CAST({b} AS DOUBLE)) / abs(CAST(t AS DOUBLE))")
    o = sql.graph(v) + ",\n" + sql.runs(1.0, 42, 10) + sql.tree_estimates(t) + f",\ntr AS ({truth_of(v, t)})\nSELECT run, eps, {share('marked_estimate', 't')} AS sampling_err, {share('estimate', 'marked_estimate')} AS dp_err, {share('estimate', 't')} AS total_err FROM est JOIN runs USING (run) CROSS JOIN tr"

    def _split(g: Graph, t: RootedPattern = t) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, reps=10)
        return proto.decompose(r, tree.tree_dp(g, r, t), exact.tree_exact(g, t.pattern())).select("run", "eps", *[digits(c) for c in ("sampling_err", "dp_err", "total_err")])

    add(f"decompose_{p}_{v}", on(v, _split, True), o)

_NREP, _NREP_EPS = list(range(1, 11)), 16.0
for p, v in (("pt4", "trade_sparse"), ("pt5", "trade_sparse"), ("fork", "trade_sparse"), ("d22", "trade_sparse")):
    t = TREES[p]
    rows = ", ".join(f"({i}, {42 + 1000 * trial + 100 * n + r}, CAST({_NREP_EPS / n!r} AS DOUBLE), {n}, {trial})" for i, (n, trial, r) in enumerate((n, trial, r) for n in _NREP for trial in range(proto.REPS) for r in range(n)))
    av = "SELECT n_rep, trial, CAST(sum(estimate) AS DOUBLE) / n_rep AS a, CAST(sum(marked_estimate) AS DOUBLE) / n_rep AS m, CAST(max(t) AS DOUBLE) AS t FROM est JOIN runs USING (run) CROSS JOIN tr GROUP BY n_rep, trial"
    long = " UNION ALL ".join(f"SELECT n_rep, '{name}' AS kind, 100.0e0 * abs({a} - {b}) / abs(t) AS e FROM av" for name, a, b in (("total_err", "a", "t"), ("sampling_err", "m", "t"), ("dp_err", "a", "m")))
    o = sql.graph(v) + f",\nruns AS (SELECT * FROM (VALUES {rows}) AS t(run, seed, eps, n_rep, trial))" + sql.tree_estimates(t) + f""",
tr AS ({truth_of(v, t)}), av AS ({av}), err AS ({long}),
te AS (SELECT n_rep, kind, avg(e) AS e FROM (SELECT *, row_number() OVER (PARTITION BY n_rep, kind ORDER BY e) AS r FROM err) WHERE r > 2 AND r <= {proto.REPS - 2} GROUP BY n_rep, kind),
wide AS (SELECT n_rep, max(e) FILTER (kind = 'total_err') AS total_err, max(e) FILTER (kind = 'sampling_err') AS sampling_err, max(e) FILTER (kind = 'dp_err') AS dp_err FROM te GROUP BY n_rep)
SELECT n_rep, {sql.digits('total_err')} AS total_err, {sql.digits('sampling_err')} AS sampling_err, {sql.digits('dp_err')} AS dp_err, {sql.digits('(SELECT total_err FROM wide WHERE n_rep = 1) / total_err')} AS gain, total_err = (SELECT min(total_err) FROM wide) AS best FROM wide"""

    def _sweep(g: Graph, t: RootedPattern = t) -> DataFrame:
        got = proto.sweep_nrep_split(g, proto.tree_mechanism(t), exact.tree_exact(g, t.pattern()), _NREP, _NREP_EPS)
        return got.select("n_rep", *[digits(c) for c in ("total_err", "sampling_err", "dp_err", "gain")], "best")

    add(f"nrep10_{p}_{v}", on(v, _sweep, True), o)


# Communication of every method and variant on one graph; work of nodes and analyzer; tail bounds.
def _methods(k: int) -> list[tuple[str, Callable, str]]:
    fork = ROOTED["fork"]
    silent = lambda kk, i: f"8e0 * (2 * m + n + {i - 1} * 2 * m / {(kk + 1) ** 2}e0 + {2 * i - 1} * n / {kk + 1}e0)"
    zeros = lambda i: f"8e0 * (2 * m + n + {i - 1} * 2 * m + {2 * i - 1} * n)"
    return [
        ("walk_all_rounds", lambda n, m: cost.walk_bytes(n, m, k, "rounds_k"), f"8e0 * ({k - 1} * n * n + n)"),
        ("walk_broadcast", lambda n, m: cost.walk_bytes(n, m, k, routing="broadcast"), f"8e0 * ({k - 1} * n * n + n)"),
        ("walk_neighbours", *_bytes_literal("walk", k)), ("path_silent", lambda n, m: cost.path_bytes(n, m, k), silent(k, k - 1)),
        ("path_zeros", lambda n, m: cost.tree_bytes(n, m, k, k - 1, "zero"), zeros(k - 1)),
        ("fork_silent", lambda n, m: cost.tree_bytes(n, m, 4, len(fork.internal)), silent(4, len(fork.internal))),
        ("fork_zeros", lambda n, m: cost.tree_bytes(n, m, 4, len(fork.internal), "zero"), zeros(len(fork.internal))),
        *((name, *_bytes_literal(name, k)) for name in ("star", "capped_star", "noisy_graph", "clipped_walk")),
    ]


for v in ("copurchase", "trade", "supply_sparse", "handoff"):
    def _table(g: Graph) -> DataFrame:
        rows = F.array(*[F.struct(F.lit(name).alias("method"), f(F.col("n"), F.col("m")).cast("double").alias("bytes")) for name, f, _ in _methods(4)])
        return _size(g).select(F.explode(rows).alias("x")).select("x.method", digits("x.bytes", "bytes"))

    add(f"comm_methods_{v}", on(v, _table), sql.graph(v) + _STATS + "\n" + " UNION ALL ".join(f"SELECT '{name}' AS method, {sql.digits(s)} AS bytes FROM st" for name, _, s in _methods(4)))
    places = {"analyzer": ("max(d)", "count(*)"), "node": ("max(d) + count(*)", "count(*)")}
    add(f"ops_wk4_{v}", on(v, lambda g: cost.walk_operations(g, 4)), sql.graph(v) + "\n" + " UNION ALL ".join(f"SELECT '{p}' AS max_at, CAST(3 * ({a}) AS BIGINT) AS node_ops, CAST({3 if p == 'analyzer' else 1} * {b} AS BIGINT) AS analyzer_ops FROM deg" for p, (a, b) in places.items()))


def _tails(spark: SparkSession, d: str) -> DataFrame:
    rows = [("laplace_sum", bounds.laplace_sum_bound([1.0, 2.0, 3.0], 0.1)), ("chernoff", bounds.chernoff_upper(50.0, 0.4)), ("chebyshev", bounds.chebyshev(3.0))]
    return spark.createDataFrame(rows, "bound string, value double").select("bound", digits("value"))


add("tail_bounds", _tails, f"SELECT 'laplace_sum' AS bound, {sql.digits('sqrt(8e0 * (1e0 + 4e0 + 9e0) * ln(20e0))')} AS value UNION ALL SELECT 'chernoff', {sql.digits('exp(-0.16e0 * 50e0 / 3e0)')} UNION ALL SELECT 'chebyshev', {sql.digits('1e0 / 9e0')}")

# A trusted curator on degrees clipped to a public cap, and what an edge can make of it.
CAP = 64
_sensitivity = baselines.star_sensitivity(3, CAP)
add("central_laplace_star3_trade", on("trade", lambda g: baselines.central_star(g, make_runs(g.nodes.sparkSession), 3, CAP).select("run", digits("estimate"))), sql.graph("trade") + ",\n" + sql.runs() + f"\nSELECT run, {sql.digits(f'CAST((SELECT sum({sql.falling(f"CAST(least(d, {CAP}) AS HUGEINT)", 3)}) FROM deg) AS DOUBLE) + ' + sql.laplace(f'{float(_sensitivity)!r}e0 / eps', 'seed', chr(39) + 'central' + chr(39)))} AS estimate FROM runs")
_step = lambda c: f"({sql.falling(f'least({c}, {CAP})', 3)} - {sql.falling(f'least({c} - 1, {CAP})', 3)})"
add("privacy_loss_central_star3_trade", on("trade", lambda g: audit.central_star_loss(g, make_runs(g.nodes.sparkSession), 3, CAP).select("run", F.round("max_loss", 9).alias("max_loss"), (F.col("max_loss") <= F.col("eps")).alias("within")), True), sql.graph("trade") + ",\n" + sql.runs() + f"\nSELECT run, round(max(({_step('a.d')} + {_step('b.d')}) * eps / {float(_sensitivity)!r}e0), 9) AS max_loss, max(({_step('a.d')} + {_step('b.d')}) * eps / {float(_sensitivity)!r}e0) <= max(eps) AS within FROM arcs JOIN deg a ON a.id = src JOIN deg b ON b.id = dst CROSS JOIN runs WHERE src < dst GROUP BY run")


# The noisy graph's tree count by marks, in SQL.
def rr_tree_sql(v: str, t: RootedPattern, reps: int) -> str:
    out = sql.graph(v) + sql.noisy_pairs(1.0) + f",\nruns AS (SELECT * FROM (VALUES {', '.join(f'({r}, {42 + r})' for r in range(reps))}) AS t(run, seed)),\nmk AS MATERIALIZED (SELECT run, id, {sql.mark('id', t.k)} AS vertex FROM nodes, runs)"
    for x in t.leaves:
        out += f",\nx_{x} AS (SELECT run, id, 1.0e0 AS x FROM mk WHERE vertex = {x})"
    for x in [x for level in t.levels for x in level]:
        joins, terms = "", []
        for c in t.children[x]:
            out += f",\ns_{x}_{c} AS (SELECT run, a AS id, sum(CASE WHEN noisy = 1 THEN {W1!r}e0 ELSE {W0!r}e0 END * x) AS y FROM bp JOIN x_{c} ON id = b GROUP BY run, a)"
            joins += f" LEFT JOIN s_{x}_{c} ON s_{x}_{c}.run = mk.run AND s_{x}_{c}.id = mk.id"
            terms.append(f"coalesce(s_{x}_{c}.y, 0.0e0)")
        out += f",\nx_{x} AS MATERIALIZED (SELECT mk.run, mk.id, {' * '.join(terms)} AS x FROM mk{joins} WHERE mk.vertex = {x})"
    return out + f"\nSELECT {sql.digits(f'avg(coalesce(s, 0.0e0)) * {t.factor}e0')} AS estimate FROM runs LEFT JOIN (SELECT run, sum(x) AS s FROM x_{t.root} GROUP BY run) USING (run)"


for p, v in (("fork", "handoff"), ("d22", "nation_region")):
    add(f"rr_tree_marked_{p}_{v}", on(v, lambda g, p=p: baselines.rr_tree_marked(g, ROOTED[p], 1.0, reps=5).select(digits("estimate"))), rr_tree_sql(v, ROOTED[p], 5))
