"""The relational operators around the methods: scans, filters, joins, aggregates, windows, sets, functions.

Each entry is a DataFrame program and the DuckDB SQL that checks it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.noise import laplace, uniform
from ..operators.kernel import make_runs
from ..plans.protocol import trimmed_mean
from ..shipping import ship
from ..sources.scratch import fresh_path
from ..sources.views import encode, table, text_id, view
from . import sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, make: Query, oracle: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return make(spark, sf_dir)

    run.__name__ = name
    QUERIES[name] = run
    if oracle:
        ORACLES[name] = oracle


def on(*tables: str) -> Callable[[Callable[..., DataFrame]], Query]:
    """A query on the given tables."""
    return lambda f: lambda spark, d: f(*[table(spark, d, t) for t in tables])


# Scans and round trips through other formats.
_COLUMNS = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_name, n_regionkey", "customer": "c_custkey, c_nationkey, c_mktsegment", "supplier": "s_suppkey, s_nationkey",
    "part": "p_partkey, p_brand, p_type, p_size", "orders": "o_orderkey, o_custkey, o_orderstatus", "lineitem": "l_orderkey, l_partkey, l_suppkey, l_quantity",
    "events": "event_id, user_id, event_type", "documents": "doc_id, lang, source", "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role",
}
for t, cols in _COLUMNS.items():
    add(f"scan_{t}", on(t)(lambda df, cols=cols: df.select(*cols.split(", "))), f"SELECT {cols} FROM {t}")
add("scan_embeddings", on("embeddings")(lambda e: e.select("vec_id", "label", F.size("embedding").cast("long").alias("n"))), "SELECT vec_id, label, CAST(len(embedding) AS BIGINT) AS n FROM embeddings")


def _counts(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for t in (*_COLUMNS, "embeddings"):
        one = table(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


add("scan_schema_all", _counts, " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in (*_COLUMNS, "embeddings")))


def _round_trip(fmt: str) -> Query:
    def make(spark: SparkSession, d: str) -> DataFrame:
        arcs = view(spark, d, "copurchase").arcs
        path = fresh_path(spark, fmt)
        arcs.write.format(fmt).option("header", "true").save(path)
        return spark.read.format(fmt).schema("src long, dst long").option("header", "true").load(path)

    return make


_ARCS = sql.graph("copurchase") + "\nSELECT src, dst FROM arcs"
for fmt in ("csv", "json", "orc"):
    add(f"scan_{fmt}_roundtrip", _round_trip(fmt), _ARCS)


def _edge_source(spark: SparkSession, d: str) -> DataFrame:
    from ..sources.edgelist import register

    register(spark)
    path = fresh_path(spark, "edges")
    view(spark, d, "copurchase").arcs.where("src < dst").select(F.concat_ws("\t", "src", "dst").alias("value")).write.text(path)
    return spark.read.format("edgelist").load(path)


add("scan_graphview_source", _edge_source, _ARCS)


# Sinks.
def _bucketed(spark: SparkSession, d: str) -> DataFrame:
    path = fresh_path(spark, "partitioned")
    view(spark, d, "copurchase").arcs.withColumn("bucket", F.pmod(F.col("dst"), F.lit(8)).cast("int")).repartition("bucket").sortWithinPartitions("dst").write.partitionBy("bucket").parquet(path)
    return spark.read.parquet(path).groupBy("bucket").agg(F.count("*").alias("n"))


add("sink_arcs_bucketed", _bucketed, sql.graph("copurchase") + "\nSELECT CAST(dst % 8 AS INT) AS bucket, count(*) AS n FROM arcs GROUP BY 1")


def _append(spark: SparkSession, d: str) -> DataFrame:
    path = fresh_path(spark, "transcript")
    deg = view(spark, d, "copurchase").degrees()
    for r in (1, 2):
        deg.select(F.lit(r).alias("round"), F.sum("degree").over(Window.partitionBy("id")).alias("x")).write.mode("append").parquet(path)
    return spark.read.parquet(path).groupBy("round").agg(F.count("*").alias("messages"), F.sum("x").alias("total"))


add("sink_transcript_append", _append, sql.graph("copurchase") + "\nSELECT r AS round, count(*) AS messages, CAST(sum(d) AS BIGINT) AS total FROM deg, (VALUES (1), (2)) AS t(r) GROUP BY r")


def _by_rep(spark: SparkSession, d: str) -> DataFrame:
    path = fresh_path(spark, "reps")
    view(spark, d, "handoff").nodes.crossJoin(F.broadcast(make_runs(spark, reps=3))).write.partitionBy("run").parquet(path)
    return spark.read.parquet(path).where("run = 1").select("id", "seed")


add("sink_partitioned_rep", _by_rep, sql.graph("handoff") + "\nSELECT id, CAST(43 AS BIGINT) AS seed FROM nodes")

# Filters and projections.
add("filter_quantity_range", on("lineitem")(lambda x: x.where("l_quantity between 40 and 45").select("l_orderkey", "l_partkey", "l_quantity")), "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 40 AND 45")
add("filter_in_types", on("events")(lambda x: x.where(F.col("event_type").isin("purchase", "signup")).select("event_id", "event_type")), "SELECT event_id, event_type FROM events WHERE event_type IN ('purchase', 'signup')")
add("filter_like_brand", on("part")(lambda x: x.where(F.col("p_brand").like("Brand#1%")).select("p_partkey", "p_brand")), "SELECT p_partkey, p_brand FROM part WHERE p_brand LIKE 'Brand#1%'")
add("filter_regex_part", on("part")(lambda x: x.where(F.col("p_type").rlike("^[A-M].*[SL]$")).select("p_partkey", "p_type")), "SELECT p_partkey, p_type FROM part WHERE regexp_matches(p_type, '^[A-M].*[SL]$')")
add("filter_null_safe", on("orders")(lambda x: x.where(~F.col("o_orderstatus").eqNullSafe("F")).select("o_orderkey")), "SELECT o_orderkey FROM orders WHERE o_orderstatus IS DISTINCT FROM 'F'")
add("filter_case_bucket", on("customer")(lambda x: x.select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("bucket"))), "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS bucket FROM customer")
add("filter_label_quality", on("documents", "labels")(lambda x, l: x.join(l.where("quality = 1"), "doc_id", "left_semi").select("doc_id", "source")), "SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")

# Graph building.
add("build_selfloop_drop", on("customer")(lambda c: c.select(F.col("c_nationkey").alias("a"), F.pmod("c_custkey", F.lit(25)).cast("int").alias("b")).where("a <> b").distinct()), "SELECT DISTINCT c_nationkey AS a, CAST(c_custkey % 25 AS INT) AS b FROM customer WHERE c_nationkey <> c_custkey % 25")


def _induced(spark: SparkSession, d: str) -> DataFrame:
    ids = table(spark, d, "customer").where("c_mktsegment = 'BUILDING'").select(encode("c_custkey", 3).alias("id")).union(table(spark, d, "part").select(encode("p_partkey", 1)))
    return view(spark, d, "trade").induced(ids).arcs


add("build_induced_subgraph", _induced, sql.graph("trade") + ",\nk AS (SELECT c_custkey * 8 + 3 AS id FROM customer WHERE c_mktsegment = 'BUILDING' UNION ALL SELECT p_partkey * 8 + 1 FROM part)\nSELECT src, dst FROM arcs WHERE src IN (SELECT id FROM k) AND dst IN (SELECT id FROM k)")


def _edge_diff(spark: SparkSession, d: str) -> DataFrame:
    g = view(spark, d, "copurchase")
    first = g.arcs.where("src < dst").orderBy("src", "dst").limit(1).select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return g.arcs.exceptAll(g.without_edges(first).arcs)


add("build_edge_diff", _edge_diff, sql.graph("copurchase") + ",\nf AS (SELECT src, dst FROM arcs WHERE src < dst ORDER BY src, dst LIMIT 1)\nSELECT src, dst FROM f UNION ALL SELECT dst, src FROM f")

# Joins.
add("join_inner_order_line", on("orders", "lineitem")(lambda o, x: x.join(o, x.l_orderkey == o.o_orderkey).groupBy("o_custkey").agg(F.count("*").alias("n"))), "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey")
add("join_left_isolated", lambda s, d: view(s, d, "copurchase").degrees().where("degree = 0").select("id"), sql.graph("copurchase") + "\nSELECT id FROM deg WHERE d = 0")
add("join_right_supplier", on("lineitem", "supplier")(lambda x, s: x.where("l_quantity >= 49").join(s, x.l_suppkey == s.s_suppkey, "right").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("n"))), "SELECT s_suppkey, count(l_orderkey) AS n FROM (SELECT * FROM lineitem WHERE l_quantity >= 49) RIGHT JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_suppkey")
_OUT = lambda x, c: x.groupBy(F.col(c).alias("k")).agg(F.count("*").alias("n"))
add("join_full_degree", on("lineitem")(lambda x: _OUT(x.where("l_quantity < 3"), "l_partkey").withColumnRenamed("n", "low").join(_OUT(x.where("l_quantity > 48"), "l_partkey").withColumnRenamed("n", "high"), "k", "full").fillna(0)), "SELECT k, coalesce(low, 0) AS low, coalesce(high, 0) AS high FROM (SELECT l_partkey AS k, count(*) AS low FROM lineitem WHERE l_quantity < 3 GROUP BY 1) FULL JOIN (SELECT l_partkey AS k, count(*) AS high FROM lineitem WHERE l_quantity > 48 GROUP BY 1) USING (k)")
add("join_semi_buyers", on("customer", "orders")(lambda c, o: c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
add("join_anti_never_bought", on("part", "lineitem")(lambda p, x: p.join(x.where("l_quantity >= 49"), p.p_partkey == x.l_partkey, "left_anti").select("p_partkey")), "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 49)")
add("join_broadcast_region", on("nation", "region")(lambda n, r: n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_name", "r_name")), "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
for hint in ("shuffle_hash", "merge"):
    add(f"join_hint_{hint}", on("orders", "customer")(lambda o, c, hint=hint: o.join(c.hint(hint), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"))), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
add("join_theta_pairs", lambda s, d: (lambda n: n.select(F.col("id").alias("a")).join(n.select(F.col("id").alias("b")), F.col("a") > F.col("b")))(view(s, d, "nation_region").nodes), sql.graph("nation_region") + "\nSELECT x.id AS a, y.id AS b FROM nodes x JOIN nodes y ON x.id > y.id")


def _range_join(p: DataFrame) -> DataFrame:
    """Pairs of prices within 2, by bins of that width: each part meets its own bin and the next."""
    a = p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x"), F.floor(F.col("p_retailprice") / 2).alias("bin"))
    b = p.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("y"), F.explode(F.array(F.floor(F.col("p_retailprice") / 2), F.floor(F.col("p_retailprice") / 2) - 1, F.floor(F.col("p_retailprice") / 2) + 1)).alias("bin"))
    return a.join(b, "bin").where("a < b and abs(x - y) <= 2").select("a", "b")


add("join_range_price_band", on("part")(_range_join), "SELECT x.p_partkey AS a, y.p_partkey AS b FROM part x JOIN part y ON x.p_partkey < y.p_partkey AND abs(x.p_retailprice - y.p_retailprice) <= 2")


def _asof(e: DataFrame) -> DataFrame:
    """Each purchase with the user's latest view before or at its time."""
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = e.where(F.col("event_type").isin("view", "purchase")).withColumn("seen", F.last(F.when(F.col("event_type") == "view", F.col("ts")), True).over(w))
    return both.where("event_type = 'purchase' and seen is not null").select("event_id", F.col("seen").cast("string").alias("seen"))


add("join_asof_event_order", on("events")(lambda e: _asof(e).select("event_id", F.date_format(F.col("seen").cast("timestamp_ntz"), "yyyy-MM-dd HH:mm:ss").alias("seen"))), "SELECT p.event_id, strftime(max(v.ts), '%Y-%m-%d %H:%M:%S') AS seen FROM events p JOIN events v ON v.user_id = p.user_id AND v.ts <= p.ts AND v.event_type = 'view' WHERE p.event_type = 'purchase' GROUP BY p.event_id")


def _interval(e: DataFrame) -> DataFrame:
    """Pairs of one user's events within an hour, by hour bins."""
    h = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(3_600_000_000))
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), h.alias("bin"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), F.explode(F.array(h, h - 1, h + 1)).alias("bin"))
    return a.join(b, ["user_id", "bin"]).where("a < b").where(F.abs(F.unix_micros(F.col("ta").cast("timestamp")) - F.unix_micros(F.col("tb").cast("timestamp"))) <= 3_600_000_000).select("a", "b")


add("join_interval_events", on("events")(_interval), "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_id < y.event_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 3600000000")
add("join_self_two_hop", lambda s, d: (lambda a: a.alias("x").join(a.alias("y"), F.col("x.dst") == F.col("y.src")).where("x.src <> y.dst").agg(F.count("*").alias("n")))(view(s, d, "copurchase").arcs), sql.graph("copurchase") + "\nSELECT count(*) AS n FROM arcs x JOIN arcs y ON x.dst = y.src WHERE x.src <> y.dst")
add("join_cross_small", on("region", "nation")(lambda r, n: r.crossJoin(n).select("r_name", "n_name")), "SELECT r_name, n_name FROM region, nation")
add("join_nullsafe", on("events")(lambda e: (lambda x: x.alias("a").join(x.alias("b"), F.col("a.k").eqNullSafe(F.col("b.k"))).agg(F.count("*").alias("n")))(e.groupBy(F.when(F.col("event_type") != "error", F.col("event_type")).alias("k")).count())), "WITH x AS (SELECT CASE WHEN event_type <> 'error' THEN event_type END AS k, count(*) AS c FROM events GROUP BY 1) SELECT count(*) AS n FROM x a JOIN x b ON a.k IS NOT DISTINCT FROM b.k")


def _lateral(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "nation").createOrReplaceTempView("lateral_nation")
    table(spark, d, "customer").createOrReplaceTempView("lateral_customer")
    return spark.sql("SELECT n_name, c_custkey FROM lateral_nation, LATERAL (SELECT c_custkey FROM lateral_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")


add("join_lateral_top", _lateral, "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE r <= 2")

# Aggregates.
add("agg_degree", lambda s, d: view(s, d, "trade").degrees(), sql.graph("trade") + "\nSELECT id, d AS degree FROM deg")
add("agg_global", on("lineitem")(lambda x: x.agg(F.count("*").alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.sum("l_quantity").cast("long").alias("total"))), "SELECT count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, CAST(sum(l_quantity) AS BIGINT) AS total FROM lineitem")
add("agg_distinct_users", on("events")(lambda e: e.groupBy("event_type").agg(F.count_distinct("user_id").alias("n"))), "SELECT event_type, count(DISTINCT user_id) AS n FROM events GROUP BY event_type")
add("agg_approx_distinct", on("events")(lambda e: e.agg(F.approx_count_distinct("user_id").alias("a"), F.count_distinct("user_id").alias("n")).select((F.abs(F.col("a") - F.col("n")) <= 0.15 * F.col("n")).alias("close"))), "SELECT TRUE AS close")
add("agg_percentile_degree", lambda s, d: view(s, d, "trade").degrees().agg(F.percentile("degree", 0.5).alias("p50"), F.percentile("degree", 0.9).alias("p90")), sql.graph("trade") + "\nSELECT quantile_cont(d, 0.5) AS p50, quantile_cont(d, 0.9) AS p90 FROM deg")
add("agg_filter_clause", on("events")(lambda e: e.groupBy("user_id").agg(F.count_if(F.col("event_type") == "purchase").alias("buys"), F.count("*").alias("n"))), "SELECT user_id, count(*) FILTER (event_type = 'purchase') AS buys, count(*) AS n FROM events GROUP BY user_id")
add("agg_having_hubs", lambda s, d: view(s, d, "supply").degrees().where("degree >= 100"), sql.graph("supply") + "\nSELECT id, d AS degree FROM deg WHERE d >= 100")
_GEO = on("customer", "nation")(lambda c, n: c.join(n, c.c_nationkey == n.n_nationkey).rollup("n_regionkey", "n_name").agg(F.count("*").alias("n")).fillna(-1, ["n_regionkey"]))
add("agg_rollup_geo", _GEO, "SELECT coalesce(n_regionkey, -1) AS n_regionkey, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_name)")
add("agg_cube_flags", on("lineitem")(lambda x: x.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
add("agg_grouping_sets", on("lineitem")(lambda x: x.groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("long").alias("q"))), "SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
add("agg_pivot_child_sums", on("lineitem")(lambda x: x.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count("l_orderkey")).fillna(0)), "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
add("agg_collect_neighbours", lambda s, d: view(s, d, "nation_region").arcs.groupBy("dst").agg(F.concat_ws(",", F.array_sort(F.collect_set("src"))).alias("near")), sql.graph("nation_region") + "\nSELECT dst, string_agg(CAST(src AS VARCHAR), ',' ORDER BY src) AS near FROM arcs GROUP BY dst")
add("agg_decimal_sum", on("lineitem")(lambda x: x.agg(F.sum((F.col("l_quantity") * 100).cast("decimal(38,0)")).cast("string").alias("total"))), "SELECT CAST(CAST(sum(l_quantity * 100) AS HUGEINT) AS VARCHAR) AS total FROM lineitem")
add("agg_bool", on("orders")(lambda o: o.groupBy("o_orderstatus").agg(F.bool_or(F.col("o_totalprice") > 400000).alias("any"), F.bool_and(F.col("o_totalprice") > 0).alias("every"))), "SELECT o_orderstatus, bool_or(o_totalprice > 400000) AS any, bool_and(o_totalprice > 0) AS every FROM orders GROUP BY o_orderstatus")
add("agg_minmax_by", lambda s, d: view(s, d, "handoff").degrees().agg(F.min_by("id", F.struct("degree", "id")).alias("lowest"), F.max_by("id", F.struct("degree", "id")).alias("highest")), sql.graph("handoff") + "\nSELECT (SELECT id FROM deg ORDER BY d, id LIMIT 1) AS lowest, (SELECT id FROM deg ORDER BY d DESC, id DESC LIMIT 1) AS highest")
add("agg_stddev_degree", lambda s, d: view(s, d, "trade").degrees().agg(F.round(F.stddev_pop("degree"), 6).alias("sd"), F.round(F.var_samp("degree"), 6).alias("v")), sql.graph("trade") + "\nSELECT round(stddev_pop(d), 6) AS sd, round(var_samp(d), 6) AS v FROM deg")
add("agg_mode_type", on("events")(lambda e: e.groupBy("event_type").count().orderBy(F.desc("count"), "event_type").limit(1)), "SELECT event_type, count(*) AS count FROM events GROUP BY event_type ORDER BY count DESC, event_type LIMIT 1")

# Windows, order, sets.
_DEG = sql.graph("trade")
_T = lambda f: lambda s, d: f(view(s, d, "trade").degrees())
def _by():
    return Window.partitionBy(F.pmod("id", F.lit(8))).orderBy(F.desc("degree"), "id")


_BYS = "OVER (PARTITION BY id % 8 ORDER BY d DESC, id)"
add("win_rank_hubs", _T(lambda x: x.select("id", F.rank().over(Window.partitionBy(F.pmod("id", F.lit(8))).orderBy(F.desc("degree"))).alias("r"))), _DEG + "\nSELECT id, CAST(rank() OVER (PARTITION BY id % 8 ORDER BY d DESC) AS INT) AS r FROM deg")
add("win_dense_rank", _T(lambda x: x.select("id", F.dense_rank().over(Window.partitionBy(F.pmod("id", F.lit(8))).orderBy(F.desc("degree"))).alias("r"))), _DEG + "\nSELECT id, CAST(dense_rank() OVER (PARTITION BY id % 8 ORDER BY d DESC) AS INT) AS r FROM deg")
add("win_ntile_degree", _T(lambda x: x.select("id", F.ntile(4).over(_by()).alias("q"))), _DEG + f"\nSELECT id, CAST(ntile(4) {_BYS} AS INT) AS q FROM deg")
add("win_percent_rank", _T(lambda x: x.select("id", F.round(F.percent_rank().over(_by()), 9).alias("p"), F.round(F.cume_dist().over(_by()), 9).alias("c"))), _DEG + f"\nSELECT id, round(percent_rank() {_BYS}, 9) AS p, round(cume_dist() {_BYS}, 9) AS c FROM deg")
def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_US = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"
add("win_lag_lead_handoff", on("events")(lambda e: e.select("event_id", F.lag("event_id").over(_user()).alias("before"), F.lead("event_id").over(_user()).alias("after")).fillna(-1)), f"SELECT event_id, coalesce(lag(event_id) {_US}, -1) AS before, coalesce(lead(event_id) {_US}, -1) AS after FROM events")
add("win_first_last", on("events")(lambda e: e.select("event_id", F.first("event_type").over(_user()).alias("first"), F.last("event_type").over(_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"))), f"SELECT event_id, first_value(event_type) {_US} AS first, last_value(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events")
add("win_running_sum", on("events")(lambda e: e.select("event_id", F.count("*").over(_user().rowsBetween(Window.unboundedPreceding, 0)).alias("n"))), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM events")
add("win_rows_frame", on("events")(lambda e: e.select("event_id", F.min("event_id").over(_user().rowsBetween(-2, 2)).alias("m"))), "SELECT event_id, min(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS m FROM events")
def _days():
    return Window.partitionBy("user_id").orderBy("day").rangeBetween(-2, 0)


add("win_range_frame_days", on("events")(lambda e: e.withColumn("day", F.datediff(F.to_date("ts"), F.lit("2024-01-01"))).select("event_id", F.count("*").over(_days()).alias("n"))), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM events")
add("win_row_number_trim", on("lineitem")(lambda x: trimmed_mean(x.select("l_returnflag", F.col("l_quantity").alias("q")), "q", ["l_returnflag"], 100).select("l_returnflag", F.round("trimmed", 9).alias("trimmed"))), "SELECT l_returnflag, round(avg(q), 9) AS trimmed FROM (SELECT l_returnflag, l_quantity AS q, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS r, count(*) OVER (PARTITION BY l_returnflag) AS n FROM lineitem) WHERE r > 100 AND r <= n - 100 GROUP BY l_returnflag")
add("topk_hubs", lambda s, d: view(s, d, "supply").degrees().orderBy(F.desc("degree"), "id").limit(10), sql.graph("supply") + "\nSELECT id, d AS degree FROM deg ORDER BY d DESC, id LIMIT 10")
add("topk_per_kind", _T(lambda x: x.withColumn("r", F.row_number().over(_by())).where("r <= 3").select("id", "degree", "r")), _DEG + f"\nSELECT id, d AS degree, CAST(r AS INT) AS r FROM (SELECT *, row_number() {_BYS} AS r FROM deg) WHERE r <= 3")
add("sort_multi_nulls", on("events")(lambda e: e.groupBy(F.when(F.col("event_type") != "view", F.col("event_type")).alias("k")).agg(F.count("*").alias("n")).orderBy(F.col("k").asc_nulls_last(), F.desc("n"))), "SELECT CASE WHEN event_type <> 'view' THEN event_type END AS k, count(*) AS n FROM events GROUP BY 1 ORDER BY 1 NULLS LAST, 2 DESC")
add("limit_offset", on("part")(lambda p: p.select("p_partkey").orderBy("p_partkey").offset(5).limit(7)), "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 7 OFFSET 5")
_A = lambda f: lambda s, d: f(view(s, d, "supply").arcs, view(s, d, "supply_sparse").arcs)
_SPARSE = sql.graph("supply") + ",\nsp AS (SELECT l_partkey * 8 + 1 AS a, l_suppkey * 8 + 2 AS b FROM lineitem WHERE l_quantity >= 48),\nsa AS (SELECT DISTINCT * FROM (SELECT a AS src, b AS dst FROM sp UNION ALL SELECT b, a FROM sp))\n"
add("set_union_symmetrise", on("nation")(lambda n: (lambda a: a.union(a.select("b", "a")).distinct())(n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("b")))), "SELECT n_nationkey AS a, n_regionkey AS b FROM nation UNION SELECT n_regionkey, n_nationkey FROM nation")
add("set_union_all", on("region", "nation")(lambda r, n: r.select(F.col("r_name").alias("name")).unionByName(n.select(F.col("n_name").alias("name")))), "SELECT r_name AS name FROM region UNION ALL SELECT n_name FROM nation")
add("set_intersect_views", _A(lambda a, b: a.intersect(b)), _SPARSE + "SELECT src, dst FROM arcs INTERSECT SELECT src, dst FROM sa")
add("set_except_views", _A(lambda a, b: a.subtract(b)), _SPARSE + "SELECT src, dst FROM arcs EXCEPT SELECT src, dst FROM sa")
add("set_except_all", on("lineitem")(lambda x: x.select("l_linenumber").exceptAll(x.where("l_quantity > 25").select("l_linenumber"))), "SELECT l_linenumber FROM lineitem EXCEPT ALL SELECT l_linenumber FROM lineitem WHERE l_quantity > 25")

# Functions.
_ID = "p_partkey * 8 + 1"
add("fn_hash_uniform", on("part")(lambda p: p.select("p_partkey", uniform(F.lit(42), F.lit("f"), encode("p_partkey", 1)).alias("u"))), f"SELECT p_partkey, {sql.uniform('42', chr(39) + 'f' + chr(39), _ID)} AS u FROM part")
add("fn_math_noise", on("part")(lambda p: p.select("p_partkey", F.round(laplace(F.lit(2.0), F.lit(42), F.lit("f"), encode("p_partkey", 1)), 9).alias("x"), F.round(F.exp(F.sqrt(F.pow("p_size", F.lit(1.5))) / 50), 6).alias("y"))), f"SELECT p_partkey, round({sql.laplace('2.0e0', '42', chr(39) + 'f' + chr(39), _ID)}, 9) AS x, round(exp(sqrt(pow(p_size, 1.5e0)) / 50), 6) AS y FROM part")
add("fn_factorial_falling", on("region")(lambda r: r.select("r_regionkey", F.factorial(F.col("r_regionkey") + 3).alias("f"), ((F.col("r_regionkey") + 5) * (F.col("r_regionkey") + 4)).cast("long").alias("g"))), "SELECT r_regionkey, CAST(factorial(r_regionkey + 3) AS BIGINT) AS f, CAST((r_regionkey + 5) * (r_regionkey + 4) AS BIGINT) AS g FROM region")
add("fn_string_ids", on("documents")(lambda x: x.select("doc_id", text_id("source", F.col("source")).alias("sid"), F.lpad(F.upper("lang"), 4, "_").alias("l"))), f"SELECT doc_id, {sql.text_id('source', 'source')} AS sid, lpad(upper(lang), 4, '_') AS l FROM documents")
add("fn_regex_href", on("pages")(lambda p: p.select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).cast("long").alias("n"))), "SELECT page_id, CAST(len(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS BIGINT) AS n FROM pages")
add("fn_date_trunc_month", on("orders")(lambda o: o.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("m")).agg(F.count("*").alias("n"))), "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS m, count(*) AS n FROM orders GROUP BY 1")
add("fn_timestamp_diff", on("orders", "lineitem")(lambda o, x: x.join(o, x.l_orderkey == o.o_orderkey).groupBy("l_linenumber").agg(F.sum(F.datediff("l_shipdate", "o_orderdate")).alias("days"))), "SELECT l_linenumber, CAST(sum(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))) AS BIGINT) AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY l_linenumber")
add("fn_interval_add", on("orders")(lambda o: o.select("o_orderkey", F.date_format(F.col("o_orderdate") + F.expr("INTERVAL 1 MONTH") + F.expr("INTERVAL 3 DAYS"), "yyyy-MM-dd").alias("due"))), "SELECT o_orderkey, strftime(o_orderdate + INTERVAL 1 MONTH + INTERVAL 3 DAY, '%Y-%m-%d') AS due FROM orders")
add("fn_array_transform_aggregate", on("part")(lambda p: p.select("p_partkey", F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: F.col("p_size") - i), F.lit(1), lambda a, x: a * x).cast("long").alias("falling"))), "SELECT p_partkey, CAST(p_size * (p_size - 1) * (p_size - 2) * (p_size - 3) AS BIGINT) AS falling FROM part")
add("fn_array_sort_slice", on("part")(lambda p: p.groupBy("p_brand").agg(F.slice(F.array_sort(F.collect_list("p_size")), 1, 3).alias("a")).select("p_brand", F.concat_ws(",", F.transform("a", lambda x: x.cast("string"))).alias("low"))), "SELECT p_brand, array_to_string(list_sort(list(p_size))[1:3], ',') AS low FROM part GROUP BY p_brand")
add("fn_explode_reps", on("region")(lambda r: r.select("r_regionkey", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("rep"))), "SELECT r_regionkey, CAST(rep AS INT) AS rep FROM region, (SELECT unnest(range(0, 10)) AS rep)")
add("fn_sequence_eps", on("part")(lambda p: p.where("p_size > 0").select(F.explode(F.transform(F.sequence(F.lit(1), F.col("p_size")), lambda i: F.round(i * 0.2, 1))).alias("eps")).groupBy("eps").agg(F.count("*").alias("n"))), "SELECT round(i * 0.2, 1) AS eps, count(*) AS n FROM (SELECT unnest(range(1, p_size + 1))::DOUBLE AS i FROM part) GROUP BY 1")
add("fn_map_round_max", on("lineitem")(lambda x: x.groupBy("l_returnflag").agg(F.max("l_quantity").alias("m")).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("l_returnflag", "m")))).alias("mp")).select(F.element_at("mp", "A").alias("a"), F.element_at("mp", "N").alias("n"))), "SELECT max(l_quantity) FILTER (l_returnflag = 'A') AS a, max(l_quantity) FILTER (l_returnflag = 'N') AS n FROM lineitem")
add("fn_struct_pack", on("customer")(lambda c: c.groupBy("c_nationkey").agg(F.max(F.struct("c_acctbal", "c_custkey")).alias("m")).select("c_nationkey", F.col("m.c_custkey").alias("c_custkey"))), "SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey DESC) AS r FROM customer) WHERE r = 1")
add("fn_json_props", on("events")(lambda e: e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long").getField("k").alias("k2"))), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k2 FROM events")
add("fn_cosine_pairs", lambda s, d: view(s, d, "near_vectors").degrees().agg(F.sum("degree").alias("arcs")), sql.graph("near_vectors") + "\nSELECT CAST(sum(d) AS BIGINT) AS arcs FROM deg")
