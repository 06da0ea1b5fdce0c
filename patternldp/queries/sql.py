"""DuckDB SQL of the graph views and mechanisms, written apart from the Spark programs to check them."""

from __future__ import annotations

import math

from ..functions.pattern import Pattern, RootedPattern

TWO_52 = "4503599627370496e0"

_NODES = {
    "part": "SELECT p_partkey * 8 + 1 AS id FROM part",
    "supplier": "SELECT s_suppkey * 8 + 2 AS id FROM supplier",
    "customer": "SELECT c_custkey * 8 + 3 AS id FROM customer",
    "nation": "SELECT CAST(n_nationkey AS BIGINT) * 8 + 4 AS id FROM nation",
    "region": "SELECT CAST(r_regionkey AS BIGINT) * 8 + 5 AS id FROM region",
}


def text_id(kind: str, column: str) -> str:
    return f"CAST('0x' || substr(md5('{kind}:' || {column}), 1, 13) AS BIGINT)"


def _union(*parts: str) -> str:
    return " UNION ALL ".join(parts)


def _supply(least: int) -> tuple[str, str]:
    return _union(_NODES["part"], _NODES["supplier"]), f"SELECT l_partkey * 8 + 1 AS a, l_suppkey * 8 + 2 AS b FROM lineitem WHERE l_quantity >= {least}"


def _trade(least: int) -> tuple[str, str]:
    return _union(_NODES["customer"], _NODES["part"]), f"SELECT o_custkey * 8 + 3 AS a, l_partkey * 8 + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= {least}"


_LINKS = f"SELECT page_id * 8 AS a, {text_id('href', 't')} * 8 + 1 AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS t FROM pages)"

#: Nodes and pairs of each view.
VIEW_SQL: dict[str, tuple[str, str]] = {
    "copurchase": (_NODES["part"], "SELECT x.l_partkey * 8 + 1 AS a, y.l_partkey * 8 + 1 AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_quantity >= 40 AND y.l_quantity >= 40"),
    "trade": _trade(0), "trade_sparse": _trade(48), "supply": _supply(0), "supply_sparse": _supply(48),
    "handoff": ("SELECT DISTINCT user_id * 8 + 6 AS id FROM events", "SELECT user_id * 8 + 6 AS a, lead(user_id) OVER (ORDER BY ts, event_id) * 8 + 6 AS b FROM events WHERE event_type = 'purchase'"),
    "geo_forest": (_union(_NODES["region"], _NODES["nation"], _NODES["customer"], _NODES["supplier"]), "SELECT CAST(n_nationkey AS BIGINT) * 8 + 4 AS a, CAST(n_regionkey AS BIGINT) * 8 + 5 AS b FROM nation UNION ALL SELECT c_custkey * 8 + 3, CAST(c_nationkey AS BIGINT) * 8 + 4 FROM customer UNION ALL SELECT s_suppkey * 8 + 2, CAST(s_nationkey AS BIGINT) * 8 + 4 FROM supplier"),
    "nation_region": (_union(_NODES["region"], _NODES["nation"]), "SELECT CAST(n_nationkey AS BIGINT) * 8 + 4 AS a, CAST(n_regionkey AS BIGINT) * 8 + 5 AS b FROM nation"),
    "near_vectors": ("SELECT vec_id AS id FROM embeddings", "SELECT a, b FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) DESC, y.vec_id) AS r FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE r <= 3"),
    "page_links": (f"SELECT page_id * 8 AS id FROM pages UNION ALL SELECT DISTINCT b FROM ({_LINKS})", _LINKS),
    "doc_facets": (f"SELECT DISTINCT {text_id('source', 'source')} AS id FROM documents UNION SELECT DISTINCT {text_id('lang', 'lang')} FROM documents", f"SELECT {text_id('source', 'source')} AS a, {text_id('lang', 'lang')} AS b FROM documents"),
    "turns": ("SELECT conv_id * 1048576 + turn AS id FROM conversations", "SELECT x.conv_id * 1048576 + x.turn AS a, y.conv_id * 1048576 + y.turn AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1"),
}


def graph(view: str) -> str:
    """The head of a query: ``nodes``, ``arcs``, ``deg``."""
    nodes, pairs = VIEW_SQL[view]
    return f"""WITH nodes AS MATERIALIZED ({nodes}),
pairs AS ({pairs}),
arcs AS MATERIALIZED (SELECT DISTINCT a AS src, b AS dst FROM (SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs) WHERE a <> b),
deg AS MATERIALIZED (SELECT n.id, count(a.src) AS d FROM nodes n LEFT JOIN arcs a ON a.dst = n.id GROUP BY n.id)"""


def runs(eps: float | list[float] = 1.0, seed: int = 42, reps: int = 1) -> str:
    values = eps if isinstance(eps, list) else [eps]
    rows = ", ".join(f"({i * reps + r}, {seed + r}, CAST({e!r} AS DOUBLE))" for i, e in enumerate(values) for r in range(reps))
    return f"runs AS (SELECT * FROM (VALUES {rows}) AS t(run, seed, eps))"


def uniform(*parts: str) -> str:
    text = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"((CAST('0x' || substr(md5({text}), 1, 13) AS BIGINT) + 0.5e0) / {TWO_52})"


def laplace(scale: str, *parts: str) -> str:
    u = f"({uniform(*parts)} - 0.5e0)"
    return f"(-({scale}) * sign({u}) * ln(1.0e0 - 2.0e0 * abs({u})))"


def lattice(scale: str, *parts: str) -> str:
    return f"CAST(round({laplace(scale, *parts)}) AS HUGEINT)"


def mark(node: str, k: int, seed: str = "seed") -> str:
    return f"(CAST('0x' || substr(md5(CAST({seed} AS VARCHAR) || ':mark:' || CAST({node} AS VARCHAR)), 1, 13) AS BIGINT) % {k + 1})"


def walk_exact(view: str, k: int) -> str:
    out = graph(view) + ",\nw1 AS (SELECT id, CAST(d AS HUGEINT) AS x FROM deg)"
    for i in range(2, k + 1):
        out += f",\nw{i} AS (SELECT dst AS id, sum(x) AS x FROM arcs JOIN w{i - 1} ON id = src GROUP BY dst)"
    return out + f"\nSELECT CAST(coalesce(sum(x), 0) AS VARCHAR) AS ordered, CAST(coalesce(sum(x), 0) // 2 AS VARCHAR) AS unordered FROM w{k}"


def placements(view: str, pattern: Pattern) -> str:
    """Count of injective placements by joins."""
    seen, joins, where, todo = [0], ["nodes v0"], [], list(pattern.edges)
    at = {0: "v0.id"}
    while todo:
        a, b = next(e for e in todo if (e[0] in seen) != (e[1] in seen))
        todo.remove((a, b))
        old, new = (a, b) if a in seen else (b, a)
        joins.append(f"JOIN arcs e{new} ON e{new}.src = {at[old]}")
        at[new] = f"e{new}.dst"
        where += [f"{at[v]} <> {at[new]}" for v in seen if v != old]
        seen.append(new)
    cond = f" WHERE {' AND '.join(where)}" if where else ""
    return graph(view) + f",\nc AS (SELECT count(*) AS n FROM {' '.join(joins)}{cond})\nSELECT CAST(n AS VARCHAR) AS ordered, CAST(n // {pattern.automorphisms} AS VARCHAR) AS unordered FROM c"


def falling(x: str, k: int) -> str:
    return " * ".join([x] + [f"({x} - {i})" for i in range(1, k)])


def star_exact(view: str, k: int) -> str:
    return graph(view) + f"\nSELECT CAST(sum({falling('CAST(d AS HUGEINT)', k)}) AS VARCHAR) AS ordered, CAST(sum({falling('CAST(d AS HUGEINT)', k)}) // {math.factorial(k)} AS VARCHAR) AS unordered FROM deg"


def walk_levels(k: int, last: int) -> str:
    out = ""
    for r in range(1, last + 1):
        if r == 1:
            out += f",\nx1 AS MATERIALIZED (SELECT run, seed, eps, id, CAST(d AS HUGEINT) + {lattice(f'CAST({2.0 * k} AS DOUBLE) / eps * 1.0e0', 'seed', '1', 'id')} AS x FROM deg, runs)"
            continue
        p = r - 1
        out += f""",
m{r} AS (SELECT run, CAST(max(abs(x)) AS DOUBLE) AS peak FROM x{p} GROUP BY run),
s{r} AS (SELECT run, dst AS id, sum(x) AS s FROM arcs JOIN x{p} ON id = src GROUP BY run, dst),
x{r} AS MATERIALIZED (SELECT r.run, r.seed, r.eps, n.id, coalesce(s, 0) + {lattice(f'CAST({2.0 * k} AS DOUBLE) / r.eps * peak', 'r.seed', str(r), 'n.id')} AS x
  FROM nodes n CROSS JOIN runs r JOIN m{r} USING (run) LEFT JOIN s{r} ON s{r}.run = r.run AND s{r}.id = n.id)"""
    return out


def walk_estimates(k: int, variant: str) -> str:
    """CTE ``est`` (run, estimate)."""
    if variant == "rounds_k":
        return walk_levels(k, k) + f",\nest AS (SELECT run, sum(x) AS estimate FROM x{k} GROUP BY run)"
    noisy = f"(CAST(deg.d AS HUGEINT) + {lattice(f'CAST({2.0 * k} AS DOUBLE) / eps', 'seed', '99', 'deg.id')})"
    if k == 1:
        return f",\nest AS (SELECT run, sum({noisy}) AS estimate FROM deg, runs GROUP BY run)"
    return walk_levels(k, k - 1) + f",\nest AS (SELECT run, sum(x * {noisy}) AS estimate FROM x{k - 1} JOIN deg USING (id) GROUP BY run)"


def tree_estimates(tree: RootedPattern, kinds: tuple[int | None, ...] | None = None) -> str:
    """CTEs ``x_v`` of each internal vertex and ``est`` (run, estimate, marked_estimate); ``kinds``: what may hold a vertex."""
    k = tree.k
    named = [f"({mark('id', k)} = {v} AND id % 8 <> {kind})" for v, kind in enumerate(kinds or ()) if kind is not None]
    allowed = f" WHERE NOT ({' OR '.join(named)})" if named else ""
    out = f",\nmk AS MATERIALIZED (SELECT run, seed, eps, id, {mark('id', k)} AS vertex FROM nodes, runs{allowed})"
    out += f",\nka AS MATERIALIZED (SELECT a.run, src, dst, a.vertex AS child, b.vertex FROM arcs JOIN mk a ON a.id = src JOIN mk b ON b.id = dst AND a.run = b.run WHERE {' OR '.join(f'(a.vertex = {c} AND b.vertex = {p})' for c, p in tree.edges)})"
    for v in [v for level in tree.levels for v in level]:
        joins, xs, ys = "", [], []
        for c in tree.children[v]:
            if c in tree.leaves:
                out += f",\ns_{v}_{c} AS (SELECT run, dst AS id, CAST(count(*) AS HUGEINT) AS sx, CAST(count(*) AS HUGEINT) AS sy FROM ka WHERE child = {c} GROUP BY run, dst)"
                peak = "1.0e0"
            else:
                out += f",\ns_{v}_{c} AS (SELECT ka.run, dst AS id, sum(x) AS sx, sum(y) AS sy FROM ka JOIN x_{c} ON x_{c}.run = ka.run AND x_{c}.id = src WHERE child = {c} GROUP BY ka.run, dst)"
                out += f",\np_{c} AS (SELECT run, CAST(max(abs(x)) AS DOUBLE) AS peak FROM x_{c} GROUP BY run)"
                joins += f" LEFT JOIN p_{c} ON p_{c}.run = mk.run"
                peak = f"coalesce(p_{c}.peak, 0.0e0)"
            joins += f" LEFT JOIN s_{v}_{c} ON s_{v}_{c}.run = mk.run AND s_{v}_{c}.id = mk.id"
            noise = lattice(f"{peak} / mk.eps", "mk.seed", f"'t{c}'", "mk.id")
            xs.append(f"(coalesce(s_{v}_{c}.sx, 0) + {noise})")
            ys.append(f"coalesce(s_{v}_{c}.sy, 0)")
        out += f",\nx_{v} AS MATERIALIZED (SELECT mk.run, mk.id, CAST({' * '.join(xs) or '1'} AS HUGEINT) AS x, CAST({' * '.join(ys) or '1'} AS HUGEINT) AS y FROM mk{joins} WHERE mk.vertex = {v})"
    return out + f",\nest AS (SELECT r.run, coalesce(sum(x), 0) * {tree.factor} AS estimate, coalesce(sum(y), 0) * {tree.factor} AS marked_estimate FROM runs r LEFT JOIN x_{tree.root} t ON t.run = r.run GROUP BY r.run)"


def star_estimates(k: int) -> str:
    d = f"(CAST(d AS HUGEINT) + {lattice('2.0e0 / eps', 'seed', chr(39) + 's' + chr(39), 'id')})"
    return f",\nnd AS (SELECT run, {d} AS d FROM deg, runs),\nest AS (SELECT run, sum({falling('d', k)}) AS estimate FROM nd GROUP BY run)"


def noisy_pairs(eps: float, seed: int = 42) -> str:
    p = math.exp(eps) / (1 + math.exp(eps))
    u = uniform(str(seed), "'r'", "x.id", "y.id")
    return f""",
np AS MATERIALIZED (SELECT x.id AS a, y.id AS b, CAST(src IS NOT NULL AS INT) AS bit,
  CASE WHEN {u} < {p!r}e0 THEN CAST(src IS NOT NULL AS INT) ELSE 1 - CAST(src IS NOT NULL AS INT) END AS noisy
  FROM nodes x JOIN nodes y ON x.id > y.id LEFT JOIN arcs ON src = x.id AND dst = y.id),
bp AS MATERIALIZED (SELECT a, b, noisy FROM np UNION ALL SELECT b, a, noisy FROM np)"""


def choose(n: str, k: int) -> str:
    body = " * ".join([f"((CAST({n} AS DOUBLE) - {i}) / {i + 1}e0)" for i in range(k)]) or "1.0e0"
    return f"(CASE WHEN {n} < {k} THEN 0.0e0 ELSE {body} END)"


def digits(x: str) -> str:
    """Seven significant digits as text, as Spark's format gives them."""
    return f"printf('%.6e', CAST({x} AS DOUBLE))"
