"""Methods, variants, baselines, measures and experiment workloads on the graph views, each with its DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import ROOTED, Pattern, RootedPattern, path_tree
from ..operators import audit, baselines, bounds, cost, exact, many, star, tree, walk
from ..operators.kernel import make_runs
from ..plans import protocol as proto
from ..shipping import ship
from ..sources.views import VIEWS, Graph, view
from . import sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

EPS_SWEEP = [round(0.2 * i, 1) for i in range(1, 21)]
GRAPHS = ("copurchase", "trade", "trade_sparse", "supply_sparse", "handoff", "geo_forest")


def add(name: str, make: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return make(spark, sf_dir)

    run.__name__ = name
    QUERIES[name] = run
    if oracle:
        ORACLES[name] = oracle


def on(v: str, f: Callable[[Graph], DataFrame], pinned: bool = False) -> Query:
    return lambda spark, d: f(view(spark, d, v).pinned() if pinned else view(spark, d, v))


def text(*names: str) -> list[Column]:
    return [F.col(n).cast("string").alias(n) for n in names]


def digits(c: str | Column, name: str | None = None) -> Column:
    col = F.col(c) if isinstance(c, str) else c
    return F.format_string("%.6e", col.cast("double")).alias(name or c)


def both_counts(df: DataFrame, automorphisms: int) -> DataFrame:
    return df.select(F.col("ordered").cast("string").alias("ordered"), F.floor(F.col("ordered") / automorphisms).cast("decimal(38,0)").cast("string").alias("unordered"))


# Graphs and their statistics.
for v in VIEWS:
    add(f"graph_stats_{v}", on(v, lambda g: g.stats()), sql.graph(v) + "\nSELECT count(*) AS n_nodes, CAST(sum(d) // 2 AS BIGINT) AS n_edges, max(d) AS max_degree, round(sum(d) / count(*), 6) AS avg_degree, count(*) FILTER (d = 0) AS isolated FROM deg")
    add(f"build_arcs_{v}", on(v, lambda g: g.arcs), sql.graph(v) + "\nSELECT src, dst FROM arcs")
    add(f"build_nodes_{v}", on(v, lambda g: g.nodes), sql.graph(v) + "\nSELECT id FROM nodes")
for v in GRAPHS:
    add(f"degree_hist_{v}", on(v, lambda g: g.degrees().groupBy("degree").agg(F.count("*").alias("n"))), sql.graph(v) + "\nSELECT d AS degree, count(*) AS n FROM deg GROUP BY d")

# Exact counts.
for v, ks in {"copurchase": (2, 3, 4, 5, 6), "trade": (2, 3, 4), "handoff": (2, 3, 4), "geo_forest": (4,), "supply_sparse": (4, 5), "trade_sparse": (4,)}.items():
    for k in ks:
        add(f"exact_wk{k}_{v}", on(v, lambda g, k=k: both_counts(walk.walk_exact(g, k), 2)), sql.walk_exact(v, k))
for v, ks in {"copurchase": (2, 3, 4), "trade_sparse": (2, 3, 4), "handoff": (2, 3), "geo_forest": (2, 3, 4), "supply_sparse": (2, 3), "turns": (4,), "doc_facets": (2, 3)}.items():
    for k in ks:
        add(f"exact_pt{k}_{v}", on(v, lambda g, k=k: both_counts(exact.path_exact(g, k), 2)), sql.placements(v, Pattern.path(k)))
for p, v in (("fork", "copurchase"), ("fork", "trade_sparse"), ("d22", "trade_sparse"), ("spider2111", "trade_sparse"), ("d212", "trade_sparse"), ("spider2211", "trade_sparse")):
    add(f"exact_tree_{p}_{v}", on(v, lambda g, p=p: both_counts(exact.tree_exact(g, ROOTED[p].pattern()), ROOTED[p].pattern().automorphisms)), sql.placements(v, ROOTED[p].pattern()))
for p, v in (("fork", "copurchase"), ("d22", "trade_sparse")):
    add(f"exact_quotients_{p}_{v}", on(v, lambda g, p=p: both_counts(exact.tree_exact_by_quotients(g, ROOTED[p].pattern()), ROOTED[p].pattern().automorphisms), True), sql.placements(v, ROOTED[p].pattern()))
for v in ("copurchase", "trade", "supply_sparse", "handoff", "nation_region"):
    for k in (3, 4, 5):
        add(f"exact_star{k}_{v}", on(v, lambda g, k=k: both_counts(exact.star_exact(g, k), Pattern.star(k).automorphisms)), sql.star_exact(v, k))
_TRIANGLES = ",\ntri AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM arcs x JOIN arcs y ON y.src = x.dst JOIN arcs z ON z.src = y.dst AND z.dst = x.src)"
for v in ("copurchase", "trade", "handoff"):
    ends = ",\ne AS (SELECT u.d AS du, w.d AS dv FROM arcs JOIN deg u ON u.id = src JOIN deg w ON w.id = dst)" + _TRIANGLES
    add(f"closed_path3_{v}", on(v, lambda g: both_counts(exact.closed_form(g, "path3"), 2), True), sql.graph(v) + ends + ",\nr AS (SELECT (SELECT sum((du - 1) * (dv - 1)) FROM e) - (SELECT count(*) FROM tri) AS n)\nSELECT CAST(n AS VARCHAR) AS ordered, CAST(n // 2 AS VARCHAR) AS unordered FROM r")
    add(f"closed_fork_{v}", on(v, lambda g: both_counts(exact.closed_form(g, "fork"), 2), True), sql.graph(v) + ends + ",\nr AS (SELECT (SELECT sum((du - 1) * (du - 2) * (dv - 1)) FROM e) - 2 * coalesce((SELECT sum(d - 2) FROM tri JOIN deg ON deg.id = a), 0) AS n)\nSELECT CAST(CAST(n AS HUGEINT) AS VARCHAR) AS ordered, CAST(CAST(n AS HUGEINT) // 2 AS VARCHAR) AS unordered FROM r")
    add(f"triangles_{v}", on(v, lambda g: exact.triangles(g).agg(F.count("*").alias("triangles")), True), sql.graph(v) + _TRIANGLES + "\nSELECT count(*) // 6 AS triangles FROM tri")


# Private walks.
def estimate(df: DataFrame, *more: str) -> DataFrame:
    return df.select("run", *text("estimate", *more), "rounds")


def walk_query(v: str, k: int, variant: str, runs: dict | None = None) -> tuple[Query, str]:
    o = sql.graph(v) + ",\n" + sql.runs(**(runs or {})) + sql.walk_estimates(k, variant)
    rounds = k if variant == "rounds_k" else max(1, k - 1)
    return on(v, lambda g: estimate(walk.walk_dp(g, make_runs(g.nodes.sparkSession, **(runs or {})), k, variant)), True), o + f"\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, {rounds} AS rounds FROM est"


for v, ks in {"copurchase": (2, 3, 4, 5), "trade": (2, 3, 4), "trade_sparse": (3,), "supply_sparse": (3,), "handoff": (2, 3, 4), "geo_forest": (3,)}.items():
    for k in ks:
        add(f"wk_dp_opt{k}_{v}", *walk_query(v, k, "rounds_k_minus_1"))
for v, k in (("copurchase", 2), ("copurchase", 3), ("trade", 3), ("handoff", 3)):
    add(f"wk_dp_rounds{k}_{v}", *walk_query(v, k, "rounds_k"))
for v in ("copurchase", "trade", "handoff"):
    add(f"edge_count_dp_{v}", *walk_query(v, 1, "rounds_k_minus_1"))
for v in ("copurchase", "handoff"):
    trace = sql.graph(v) + ",\n" + sql.runs() + sql.walk_levels(4, 3) + "\n" + " UNION ALL ".join(f"SELECT run, {r} AS round, CAST(max(abs(x)) AS VARCHAR) AS max_abs, CAST(sum(x) AS VARCHAR) AS sum_x, count(*) AS active FROM x{r} GROUP BY run" for r in (1, 2, 3))
    add(f"wk_round_trace4_{v}", on(v, lambda g: walk.walk_trace(g, make_runs(g.nodes.sparkSession), 4).select("run", "round", *text("max_abs", "sum_x"), "active"), True), trace)


# Marked paths and trees.
def tree_query(v: str, t: RootedPattern, runs: dict | None = None, rounds: int | None = None, path: bool = False) -> tuple[Query, str]:
    def make(g: Graph) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, **(runs or {}))
        return estimate(tree.path_dp(g, r, t.k) if path else tree.tree_dp(g, r, t), "marked_estimate")

    o = sql.graph(v) + ",\n" + sql.runs(**(runs or {})) + sql.tree_estimates(t)
    return on(v, make, True), o + f"\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, CAST(marked_estimate AS VARCHAR) AS marked_estimate, {t.k if path else t.rounds} AS rounds FROM est"


for v, ks in {"copurchase": (2, 3, 4, 5, 6), "trade": (2, 3), "trade_sparse": (3, 4), "handoff": (2, 3, 4), "supply_sparse": (3,), "geo_forest": (3,)}.items():
    for k in ks:
        add(f"pt_dp{k}_{v}", *tree_query(v, path_tree(k), path=True))
for p, t in ROOTED.items():
    add(f"tree_dp_{p}_copurchase", *tree_query("copurchase", t))
for p, v in (("fork", "trade"), ("fork", "handoff"), ("fork", "supply_sparse"), ("d22", "trade_sparse"), ("fork_alt", "handoff"), ("d22_alt", "supply_sparse"), ("spider2211", "geo_forest"), ("d212", "handoff")):
    add(f"tree_dp_{p}_{v}", *tree_query(v, ROOTED[p]))
for k, v in ((2, "copurchase"), (4, "copurchase"), (3, "handoff")):
    t = path_tree(k)
    marks = sql.graph(v) + ",\n" + sql.runs(reps=2) + sql.tree_estimates(t) + "\nSELECT run, 'node' AS kind, -1 AS child, CAST(vertex AS INT) AS vertex, count(*) AS n FROM mk GROUP BY run, vertex UNION ALL SELECT run, 'arc', CAST(child AS INT), CAST(vertex AS INT), count(*) FROM ka GROUP BY run, child, vertex"
    add(f"marks_{k}_{v}", on(v, lambda g, t=t: tree.mark_stats(g, make_runs(g.nodes.sparkSession, reps=2), t)), marks)
t = ROOTED["d212"]
add("tree_trace_d212_copurchase", on("copurchase", lambda g: tree.tree_trace(g, make_runs(g.nodes.sparkSession), ROOTED["d212"]).select("run", "vertex", "active", *text("max_abs", "sum_x")), True), sql.graph("copurchase") + ",\n" + sql.runs() + sql.tree_estimates(t) + "\n" + " UNION ALL ".join(f"SELECT run, {v} AS vertex, count(*) AS active, CAST(max(abs(x)) AS VARCHAR) AS max_abs, CAST(sum(x) AS VARCHAR) AS sum_x FROM x_{v} GROUP BY run" for v in t.internal))
add("prune_arcs_by_mark", on("trade", lambda g: tree.kept_arcs(g, make_runs(g.nodes.sparkSession), path_tree(4)).groupBy("child", "vertex").agg(F.count("*").alias("n"))), sql.graph("trade") + ",\n" + sql.runs() + sql.tree_estimates(path_tree(4)) + "\nSELECT CAST(child AS INT) AS child, CAST(vertex AS INT) AS vertex, count(*) AS n FROM ka GROUP BY child, vertex")

# Stars.
for v, ks in {"copurchase": (3, 4, 5), "trade": (3, 4, 5), "supply_sparse": (4,), "handoff": (3,), "nation_region": (3,)}.items():
    for k in ks:
        add(f"star_dp{k}_{v}", on(v, lambda g, k=k: estimate(star.star_dp(g, make_runs(g.nodes.sparkSession), k))), sql.graph(v) + ",\n" + sql.runs() + sql.star_estimates(k) + "\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, 1 AS rounds FROM est")


def _polynomial(x: str, k: int, derivative: int = 0) -> str:
    c = star.coefficients(k)
    for _ in range(derivative):
        c = [i * a for i, a in enumerate(c)][1:]
    out = "0.0e0"
    for a in reversed(c):
        out = f"({out} * {x} + {float(a)}e0)"
    return out


for v, k in (("copurchase", 3), ("trade", 4)):
    d = f"(CAST(d AS DOUBLE) + {sql.laplace('2.0e0 / eps', 'seed', chr(39) + 's' + chr(39), 'id')})"
    o = sql.graph(v) + ",\n" + sql.runs() + f",\nnd AS (SELECT run, eps, {d} AS d FROM deg, runs)\nSELECT run, {sql.digits(f'sum({_polynomial('d', k)} - (2.0e0 / eps) * (2.0e0 / eps) * {_polynomial('d', k, 2)})')} AS estimate FROM nd GROUP BY run"
    add(f"star_dp_debiased{k}_{v}", on(v, lambda g, k=k: star.star_dp(g, make_runs(g.nodes.sparkSession), k, debias=True).select("run", digits("estimate"))), o)

# Baselines.
for v in ("nation_region", "handoff"):
    add(f"rr_bits_{v}", on(v, lambda g: baselines.pair_stats(g, 1.0)), sql.graph(v) + sql.noisy_pairs(1.0) + "\nSELECT count(*) AS n_pairs, CAST(sum(noisy) AS BIGINT) AS n_ones, CAST(sum(CAST(bit <> noisy AS INT)) AS BIGINT) AS n_flipped FROM np")
W0, W1 = baselines.weights(1.0)
_value = f"count(*) * pow({W1!r}e0, ones) * pow({W0!r}e0, {{m}} - ones)"
add("rr_enum_pt2_nation_region", on("nation_region", lambda g: baselines.rr_enumerate(g, Pattern.path(2), 1.0).select(digits("estimate"))), sql.graph("nation_region") + sql.noisy_pairs(1.0) + f",\ng AS (SELECT {_value.format(m=2)} AS t FROM (SELECT x.noisy + y.noisy AS ones FROM bp x JOIN bp y ON x.b = y.a AND y.b <> x.a) GROUP BY ones)\nSELECT {sql.digits('sum(t)')} AS estimate FROM g")
add("rr_enum_pt2_handoff", on("handoff", lambda g: baselines.rr_enumerate(g, Pattern.path(2), 1.0).select(digits("estimate"))), sql.graph("handoff") + sql.noisy_pairs(1.0) + f",\ng AS (SELECT {_value.format(m=2)} AS t FROM (SELECT x.noisy + y.noisy AS ones FROM bp x JOIN bp y ON x.b = y.a AND y.b <> x.a) GROUP BY ones)\nSELECT {sql.digits('sum(t)')} AS estimate FROM g")
add("rr_enum_pt3_nation_region", on("nation_region", lambda g: baselines.rr_enumerate(g, Pattern.path(3), 1.0).select(digits("estimate"))), sql.graph("nation_region") + sql.noisy_pairs(1.0) + f",\ng AS (SELECT {_value.format(m=3)} AS t FROM (SELECT x.noisy + y.noisy + z.noisy AS ones FROM bp x JOIN bp y ON x.b = y.a AND y.b <> x.a JOIN bp z ON y.b = z.a AND z.b <> x.a AND z.b <> x.b) GROUP BY ones)\nSELECT {sql.digits('sum(t)')} AS estimate FROM g")
add("rr_enum_wk2_nation_region", on("nation_region", lambda g: baselines.rr_enumerate(g, Pattern.path(2), 1.0, walk=True).select(digits("estimate"))), sql.graph("nation_region") + sql.noisy_pairs(1.0) + f",\ng AS (SELECT {_value.format(m=2)} AS t FROM (SELECT x.noisy + y.noisy AS ones FROM bp x JOIN bp y ON x.b = y.a) GROUP BY ones)\nSELECT {sql.digits('sum(t)')} AS estimate FROM g")
add("rr_enum_wk2_distinct_nation_region", on("nation_region", lambda g: baselines.rr_enumerate(g, Pattern.path(2), 1.0, walk=True, repeat="distinct").select(digits("estimate"))), sql.graph("nation_region") + sql.noisy_pairs(1.0) + f",\ns AS (SELECT CASE WHEN y.b = x.a THEN 1 ELSE 2 END AS m, CASE WHEN y.b = x.a THEN x.noisy ELSE x.noisy + y.noisy END AS ones FROM bp x JOIN bp y ON x.b = y.a),\ng AS (SELECT {_value.format(m='m')} AS t FROM s GROUP BY m, ones)\nSELECT {sql.digits('sum(t)')} AS estimate FROM g")


def rr_walk_sql(v: str, k: int) -> str:
    out = sql.graph(v) + sql.noisy_pairs(1.0) + ",\nx0 AS (SELECT id, 1.0e0 AS x FROM nodes)"
    for i in range(1, k + 1):
        out += f",\nx{i} AS MATERIALIZED (SELECT a AS id, sum(CASE WHEN noisy = 1 THEN {W1!r}e0 ELSE {W0!r}e0 END * x) AS x FROM bp JOIN x{i - 1} ON id = b GROUP BY a)"
    return out + f"\nSELECT {sql.digits('sum(x)')} AS estimate FROM x{k}"


for v, k in (("nation_region", 4), ("handoff", 2), ("handoff", 3), ("handoff", 4)):
    add(f"rr_walk_{k}_{v}", on(v, lambda g, k=k: baselines.rr_walk(g, k, 1.0).select(digits("estimate"))), rr_walk_sql(v, k))
add("rr_walk_dense_3_handoff", on("handoff", lambda g: baselines.rr_walk(g, 3, 1.0, sparse=False).select(digits("estimate"))), rr_walk_sql("handoff", 3))
for v, k in (("nation_region", 3), ("handoff", 3), ("handoff", 4)):
    value = " + ".join(f"{sql.choose('ones', j)} * {sql.choose('(n - ones)', k - j)} * {(W1**j * W0 ** (k - j))!r}e0" for j in range(k + 1))
    add(f"rr_star_{k}_{v}", on(v, lambda g, k=k: baselines.rr_star(g, k, 1.0).select(digits("estimate"))), sql.graph(v) + sql.noisy_pairs(1.0) + f",\nr AS (SELECT a, sum(noisy) AS ones, count(*) AS n FROM bp GROUP BY a)\nSELECT {sql.digits(f'sum(({value}) * {[1, 1, 2, 6, 24, 120][k]}e0)')} AS estimate FROM r")

_TOP = f",\ntop AS MATERIALIZED (SELECT run, greatest(1.0e0, max(CAST(d AS DOUBLE) + {sql.laplace('20.0e0 / eps', 'seed', chr(39) + 'x' + chr(39), 'id')})) AS top FROM deg, runs GROUP BY run)"


def clipped_sql(v: str, k: int, reps: int = 1, raw: bool = False) -> str:
    out = sql.graph(v) + ",\n" + sql.runs(reps=reps) + _TOP + ",\nx0 AS (SELECT run, id, 1.0e0 AS x FROM nodes, runs)"
    for i in range(1, k + 1):
        noise = sql.laplace(f"{2.0 * k / 0.9!r}e0 / r.eps * pow(sqrt(top), {i - 1})", "r.seed", f"'c{i}'", "n.id")
        out += f""",
s{i} AS (SELECT x.run, dst AS id, sum(greatest(0.0e0, least(x.x, pow(sqrt(top), {i - 1})))) AS y FROM arcs JOIN x{i - 1} x ON x.id = src JOIN top ON top.run = x.run GROUP BY x.run, dst),
x{i} AS MATERIALIZED (SELECT r.run, n.id, greatest(0.0e0, least(coalesce(y, 0.0e0) + {noise}, pow(sqrt(top), {i}))) AS x FROM nodes n CROSS JOIN runs r JOIN top USING (run) LEFT JOIN s{i} s ON s.run = r.run AND s.id = n.id)"""
    if raw:
        return out + f"\nSELECT run, sum(x) AS estimate FROM x{k} GROUP BY run"
    return out + f"\nSELECT x.run, {sql.digits('sum(x)')} AS estimate, {sql.digits('max(top)')} AS top, {k + 1} AS rounds FROM x{k} x JOIN top ON top.run = x.run GROUP BY x.run"


for v, ks in {"copurchase": (2, 4), "trade": (2, 3, 4), "handoff": (2, 3, 4)}.items():
    for k in ks:
        add(f"clip_wk{k}_{v}", on(v, lambda g, k=k: baselines.walk_clipped(g, make_runs(g.nodes.sparkSession), k).select("run", digits("estimate"), digits("top"), "rounds"), True), clipped_sql(v, k))


def capped_sql(v: str, k: int, reps: int = 1, raw: bool = False) -> str:
    noise = sql.laplace(f"{2.0 / 0.9!r}e0 * {sql.choose('(t - 1)', k - 1)} / eps", "seed", "'k'", "id")
    value = f"sum({sql.choose('least(d, t)', k)} + {noise}) * {[1, 1, 2, 6, 24, 120][k]}e0"
    out = sql.graph(v) + ",\n" + sql.runs(reps=reps) + _TOP + ",\nc AS (SELECT run, CAST(ceil(top) AS BIGINT) AS t FROM top)"
    return out + f"\nSELECT run, {value if raw else sql.digits(value)} AS estimate, max(t) AS top, 2 AS rounds FROM deg, runs JOIN c USING (run) GROUP BY run"


for v, ks in {"copurchase": (3,), "trade": (3, 4, 5), "handoff": (3, 4)}.items():
    for k in ks:
        add(f"cap_star{k}_{v}", on(v, lambda g, k=k: baselines.star_capped(g, make_runs(g.nodes.sparkSession), k).select("run", digits("estimate"), "top", "rounds")), capped_sql(v, k))

# Measures: bounds, theory, communication, operations, privacy loss.
_STATS = ",\nst AS (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(sum(d) / 2 AS DOUBLE) AS m, CAST(max(d) AS DOUBLE) AS d FROM deg)"


def bounds_sql(v: str, k: int, eps: float = 1.0, beta: float = 0.1) -> str:
    gamma = f"({2.0 * k / eps!r}e0 * sqrt(8.0e0 * ln({2.0 * k!r}e0 * n / {beta!r}e0)))"
    sampling = lambda b: f"({k + 1} * sqrt(n / {b!r}e0) * pow(d + {k + 1}e0, {k}e0))"

    def noise(events: float, b: float) -> str:
        g = f"({(k + 1.0) / eps!r}e0 * sqrt(8.0e0 * ln({events!r}e0 * n / {b!r}e0)))"
        dd = f"greatest(d, ceil({g} * {g}))"
        return f"({k * (k + 1.0)!r}e0 * {g} * sqrt(n) * pow({dd} + {g} * sqrt({dd}) + {g}, {k - 1}e0))"

    cols = {"walk": f"{k} * {gamma} * sqrt(n) * pow(d + {gamma}, {k - 1}e0)", "sampling": sampling(beta), "path_noise": noise(6.0, beta), "tree_noise": noise(6.0 * k, beta), "path_total": f"{sampling(beta / 2)} + {noise(12.0, beta)}", "tree_total": f"{sampling(beta / 2)} + {noise(12.0 * k, beta)}", "cap": f"n * pow(d, {k}e0)"}
    return sql.graph(v) + _STATS + "\nSELECT " + ", ".join(f"{sql.digits(c)} AS {n}" for n, c in cols.items()) + " FROM st"


for v, k in (("copurchase", 4), ("trade", 3), ("handoff", 5)):
    add(f"bounds_{k}_{v}", on(v, lambda g, k=k: (lambda b: b.select(*[digits(c) for c in b.columns]))(bounds.bounds_table(g, k))), bounds_sql(v, k))
for v in ("copurchase", "trade", "handoff"):
    rows = [("walk", "rounds", "sqrt(n) * pow(d, 2e0)", "m + n", "n * d"), ("walk", "clipped", "CAST(NULL AS DOUBLE)", "n * n", "n * d")]
    for task in ("path", "tree"):
        rows += [(task, "marks", "sqrt(n) * pow(d, 3e0)", "m + n", "n * d"), (task, "noisy_graph", "pow(n, 3e0)", "n * n", "pow(n, 4e0)")]
    o = sql.graph(v) + _STATS + "\n" + " UNION ALL ".join(f"SELECT '{a}' AS task, '{b}' AS method, {sql.digits('n * pow(d, 3e0)')} AS count_cap, CASE WHEN {e} IS NULL THEN NULL ELSE {sql.digits(e)} END AS error, {sql.digits(c)} AS communication, {sql.digits(t)} AS time FROM st" for a, b, e, c, t in rows)
    add(f"theory_{v}", on(v, lambda g: bounds.theory_table(g, 3).select("task", "method", digits("count_cap"), F.when(F.col("error").isNotNull(), F.format_string("%.6e", "error")).alias("error"), digits("communication"), digits("time"))), o)


def comm_sql(v: str, t: RootedPattern) -> str:
    inner = [x for x in t.internal if x != t.root]
    per = " + ".join(f"CASE WHEN vertex = {x} THEN {sum(c in inner for c in t.children[x])} ELSE 0 END" for x in t.internal)
    any_inner = f"child IN ({', '.join(map(str, inner))})" if inner else "FALSE"
    o = sql.graph(v) + ",\n" + sql.runs() + sql.tree_estimates(t)
    o += f""",
ch AS (SELECT r.run, 'marks' AS channel, (SELECT count(*) FROM arcs) + (SELECT count(*) FROM nodes) AS messages FROM runs r
 UNION ALL SELECT r.run, 'node_to_node', (SELECT count(*) FROM ka WHERE ka.run = r.run AND {any_inner}) FROM runs r
 UNION ALL SELECT r.run, 'node_to_analyzer', (SELECT count(*) FROM mk WHERE mk.run = r.run AND vertex IN ({', '.join(map(str, t.internal))})) FROM runs r
 UNION ALL SELECT r.run, 'analyzer_to_node', (SELECT CAST(sum({per}) AS BIGINT) FROM mk WHERE mk.run = r.run) FROM runs r)
SELECT run, channel, messages, messages * 8 AS bytes FROM ch"""
    return o


for p, t, v in (("pt4", path_tree(4), "trade"), ("pt5", path_tree(5), "copurchase"), ("fork", ROOTED["fork"], "trade"), ("fork_alt", ROOTED["fork_alt"], "trade"), ("d22", ROOTED["d22"], "handoff"), ("d212", ROOTED["d212"], "copurchase")):
    add(f"comm_{p}_{v}", on(v, lambda g, t=t: cost.tree_measured(g, make_runs(g.nodes.sparkSession), t), True), comm_sql(v, t))
    add(f"ops_{p}_{v}", on(v, lambda g, t=t: cost.operations(g, make_runs(g.nodes.sparkSession), t), True), sql.graph(v) + ",\n" + sql.runs() + sql.tree_estimates(t) + f"\nSELECT r.run, coalesce((SELECT max(c) FROM (SELECT count(*) AS c FROM ka WHERE ka.run = r.run GROUP BY dst)), 0) AS max_node_ops, (SELECT count(*) FROM mk WHERE mk.run = r.run AND vertex IN ({', '.join(map(str, t.internal))})) AS analyzer_ops FROM runs r")
for k in (4, 5, 6):
    o = sql.graph("trade") + f",\nc AS (SELECT 'node_to_node' AS channel, (SELECT count(*) FROM arcs) * {k - 2} AS messages UNION ALL SELECT 'node_to_analyzer', (SELECT count(*) FROM nodes) * {k - 1} UNION ALL SELECT 'analyzer_to_node', (SELECT count(*) FROM nodes) * {k - 2})\nSELECT channel, messages, messages * 8 AS bytes FROM c"
    add(f"comm_wk{k}_trade", on("trade", lambda g, k=k: cost.walk_measured(g, k)), o)
for v, k in (("copurchase", 4), ("handoff", 3)):
    o = sql.graph(v) + ",\n" + sql.runs() + sql.walk_levels(k, k - 1)
    terms = " + ".join([f"4 * r.eps / {2.0 * k!r}e0"] + [f"r.eps / {2.0 * k!r}e0 * (abs(a{i}.x) / p{i}.peak + abs(b{i}.x) / p{i}.peak)" for i in range(1, k - 1)])
    joins = " ".join(f"JOIN x{i} a{i} ON a{i}.id = src AND a{i}.run = r.run JOIN x{i} b{i} ON b{i}.id = dst AND b{i}.run = r.run JOIN (SELECT run, CAST(max(abs(x)) AS DOUBLE) AS peak FROM x{i} GROUP BY run) p{i} ON p{i}.run = r.run" for i in range(1, k - 1))
    add(f"privacy_loss_wk{k}_{v}", on(v, lambda g, k=k: audit.walk_loss(g, make_runs(g.nodes.sparkSession), k).select("run", F.round("max_loss", 6).alias("max_loss"), (F.col("max_loss") <= 1.0 + 1e-9).alias("within")), True), o + f"\nSELECT r.run, round(max({terms}), 6) AS max_loss, max({terms}) <= 1.0 + 1e-9 AS within FROM arcs CROSS JOIN runs r {joins} WHERE src < dst GROUP BY r.run")
for p, v in (("fork", "trade"), ("d212", "copurchase")):
    t = ROOTED[p]
    inner = [x for x in t.internal if x != t.root]
    loss = " UNION ALL ".join([f"SELECT ka.run, src, dst, r.eps AS loss FROM ka JOIN runs r USING (run) WHERE child IN ({', '.join(map(str, t.leaves))})"] + [f"SELECT ka.run, src, dst, r.eps * abs(x) / (SELECT CAST(max(abs(x)) AS DOUBLE) FROM x_{c} z WHERE z.run = ka.run) FROM ka JOIN runs r USING (run) JOIN x_{c} y ON y.run = ka.run AND y.id = src WHERE child = {c}" for c in inner])
    o = sql.graph(v) + ",\n" + sql.runs() + sql.tree_estimates(t) + f",\nl AS ({loss}),\ne AS (SELECT run, least(src, dst) AS a, greatest(src, dst) AS b, sum(loss) AS loss, count(*) AS sums FROM l GROUP BY ALL)\nSELECT run, round(max(loss), 6) AS max_loss, max(sums) AS max_sums FROM e GROUP BY run"
    add(f"privacy_loss_{p}_{v}", on(v, lambda g, t=t: audit.tree_loss(g, make_runs(g.nodes.sparkSession), t).select("run", F.round("max_loss", 6).alias("max_loss"), "max_sums"), True), o)
add("privacy_loss_star_trade", on("trade", lambda g: audit.star_loss(g, make_runs(g.nodes.sparkSession))), sql.graph("trade") + ",\n" + sql.runs() + "\nSELECT run, CASE WHEN (SELECT count(*) FROM arcs) > 0 THEN eps ELSE 0 END AS max_loss FROM runs")

# Workloads: ten runs and trimmed means, error splits, sweeps of epsilon and of the number of averaged runs, rootings.
_ERR = "100.0e0 * abs(CAST(estimate AS DOUBLE) - CAST(t AS DOUBLE)) / abs(CAST(t AS DOUBLE))"


def trimmed_sql(by: str) -> str:
    return f"SELECT {by}, {sql.digits('avg(e)')} AS rel_err FROM (SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY e) AS r, count(*) OVER (PARTITION BY {by}) AS c FROM err) WHERE r > 2 AND r <= c - 2 GROUP BY {by}"


def truth_sql(v: str, kind: str, k: int) -> str:
    if kind == "wk":
        return "(" + sql.walk_exact(v, k).replace(sql.graph(v), "WITH w0 AS (SELECT 1)").replace("CAST(coalesce(sum(x), 0) // 2 AS VARCHAR) AS unordered", "0 AS u") + ")"
    if kind == "star":
        return f"(SELECT sum({sql.falling('CAST(d AS HUGEINT)', k)}) FROM deg)"
    if kind == "pt" and k == 2:
        return "(SELECT sum(d * (d - 1)) FROM deg)"
    raise ValueError(kind)


def protocol_query(v: str, kind: str, k: int, eps: float | list[float] = 1.0) -> tuple[Query, str]:
    def make(g: Graph) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, eps, reps=proto.REPS)
        est = {"wk": lambda: many.walk3_dp(g, r) if k == 3 else walk.walk_dp(g, r, k), "star": lambda: star.star_dp(g, r, k), "pt": lambda: tree.path_dp(g, r, k)}[kind]()
        true = {"wk": lambda: walk.walk_exact(g, k), "star": lambda: exact.star_exact(g, k), "pt": lambda: exact.closed_form(g, f"path{k}")}[kind]()
        return proto.protocol(r, est, true).select("eps", digits("rel_err"))

    ests = {"wk": lambda: sql.walk_estimates(k, ""), "star": lambda: sql.star_estimates(k), "pt": lambda: sql.tree_estimates(path_tree(k))}[kind]()
    true = truth_sql(v, kind, k)
    if kind == "wk":
        steps = ",\nw1 AS (SELECT id, CAST(d AS HUGEINT) AS x FROM deg)" + "".join(f",\nw{i} AS (SELECT dst AS id, sum(x) AS x FROM arcs JOIN w{i - 1} ON id = src GROUP BY dst)" for i in range(2, k + 1))
        ests, true = ests + steps, f"(SELECT sum(x) FROM w{k})"
    o = sql.graph(v) + ",\n" + sql.runs(eps, 42, proto.REPS) + ests + f",\ntr AS (SELECT {true} AS t),\nerr AS (SELECT eps, {_ERR} AS e FROM est JOIN runs USING (run) CROSS JOIN tr)\n" + trimmed_sql("eps")
    return on(v, make, True), o


for v, kind, k in (("trade", "wk", 2), ("trade", "wk", 3), ("trade", "wk", 4), ("trade", "star", 3), ("trade", "star", 4), ("trade", "star", 5), ("trade", "pt", 2), ("handoff", "wk", 3), ("handoff", "pt", 2), ("copurchase", "wk", 2), ("copurchase", "star", 3)):
    add(f"protocol_{kind}{k}_{v}", *protocol_query(v, kind, k))
for v, kind, k in (("handoff", "wk", 3), ("handoff", "pt", 2), ("handoff", "star", 4), ("trade", "wk", 3)):
    add(f"eps_sweep_{kind}{k}_{v}", *protocol_query(v, kind, k, EPS_SWEEP))


def sweep_tree(v: str, t: RootedPattern, true: Callable[[Graph], DataFrame], true_sql: str) -> tuple[Query, str]:
    def make(g: Graph) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, [1.0, 4.0, 16.0, 64.0], reps=proto.REPS)
        return proto.protocol(r, tree.tree_dp(g, r, t), true(g)).select("eps", digits("rel_err"))

    o = sql.graph(v) + ",\n" + sql.runs([1.0, 4.0, 16.0, 64.0], 42, proto.REPS) + sql.tree_estimates(t) + f",\ntr AS ({true_sql}),\nerr AS (SELECT eps, {_ERR} AS e FROM est JOIN runs USING (run) CROSS JOIN tr)\n" + trimmed_sql("eps")
    return on(v, make, True), o


_FORK = "SELECT sum((u.d - 1) * (u.d - 2) * (w.d - 1)) - 2 * coalesce((SELECT sum(d - 2) FROM arcs x JOIN arcs y ON y.src = x.dst JOIN arcs z ON z.src = y.dst AND z.dst = x.src JOIN deg ON deg.id = x.src), 0) AS t FROM arcs JOIN deg u ON u.id = src JOIN deg w ON w.id = dst"
for v in ("handoff", "copurchase"):
    add(f"eps_sweep_fork_{v}", *sweep_tree(v, ROOTED["fork"], lambda g: exact.closed_form(g, "fork"), _FORK))
    add(f"rooting_fork_alt_{v}", *sweep_tree(v, ROOTED["fork_alt"], lambda g: exact.closed_form(g, "fork"), _FORK))

for v, k in (("trade", 2), ("handoff", 2), ("copurchase", 2)):
    share = lambda a, b: sql.digits(f"100.0e0 * abs(CAST({a} AS DOUBLE) - CAST({b} AS DOUBLE)) / abs(CAST(t AS DOUBLE))")
    o = sql.graph(v) + ",\n" + sql.runs(1.0, 42, 10) + sql.tree_estimates(path_tree(k)) + f",\ntr AS (SELECT {truth_sql(v, 'pt', k)} AS t)\nSELECT run, eps, {share('marked_estimate', 't')} AS sampling_err, {share('estimate', 'marked_estimate')} AS dp_err, {share('estimate', 't')} AS total_err FROM est JOIN runs USING (run) CROSS JOIN tr"

    def _decompose(g: Graph, k: int = k) -> DataFrame:
        r = make_runs(g.nodes.sparkSession, reps=10)
        return proto.decompose(r, tree.path_dp(g, r, k), exact.closed_form(g, f"path{k}")).select("run", "eps", *[digits(c) for c in ("sampling_err", "dp_err", "total_err")])

    add(f"decompose_pt{k}_{v}", on(v, _decompose, True), o)


def nrep_runs(values: list[int], eps: float, trials: int, seed: int = 42) -> str:
    rows = ", ".join(f"({i}, {seed + 1000 * t + 100 * n + r}, CAST({eps / n!r} AS DOUBLE), {n}, {t})" for i, (n, t, r) in enumerate((n, t, r) for n in values for t in range(trials) for r in range(n)))
    return f"runs AS (SELECT * FROM (VALUES {rows}) AS t(run, seed, eps, n_rep, trial))"


for v, t, true, name in (("handoff", path_tree(2), truth_sql("handoff", "pt", 2), "pt2"), ("trade", path_tree(2), truth_sql("trade", "pt", 2), "pt2"), ("handoff", ROOTED["fork"], f"({_FORK})", "fork")):
    values, eps, trials = [1, 2, 4, 6, 8, 10], 16.0, 6
    o = sql.graph(v) + ",\n" + nrep_runs(values, eps, trials) + sql.tree_estimates(t) + f",\ntr AS (SELECT {true} AS t),\nav AS (SELECT n_rep, trial, CAST(sum(estimate) AS DOUBLE) / n_rep AS estimate FROM est JOIN runs USING (run) GROUP BY n_rep, trial),\nerr AS (SELECT n_rep, {_ERR} AS e FROM av CROSS JOIN tr)\n" + trimmed_sql("n_rep")
    add(f"nrep_{name}_{v}", on(v, lambda g, t=t, name=name: proto.sweep_nrep(g, proto.tree_mechanism(t), exact.closed_form(g, "fork" if name == "fork" else "path2"), [1, 2, 4, 6, 8, 10], 16.0, trials=6).select("n_rep", digits("rel_err")), True), o)
    av = sql.graph(v) + ",\n" + nrep_runs([4], 1.0, 1) + sql.tree_estimates(t) + f"\nSELECT n_rep, trial, {sql.digits('CAST(sum(estimate) AS DOUBLE) / n_rep')} AS estimate FROM est JOIN runs USING (run) GROUP BY n_rep, trial"
    add(f"avg_dp_{name}_{v}", on(v, lambda g, t=t: proto.averaged(g, proto.tree_mechanism(t), 4).select("n_rep", "trial", digits("estimate")), True), av)
