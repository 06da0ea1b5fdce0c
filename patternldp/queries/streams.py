"""Streaming, Python-function and SQL-text queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import udfs
from ..functions.noise import uniform
from ..functions.pattern import Pattern
from ..operators.kernel import make_runs
from ..operators.star import star_dp
from ..shipping import ship
from ..sources.views import TURNS, Graph, encode, table, view
from ..sqlapi import dp_sql
from ..streaming import streams
from . import sql
from .methods import estimate

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


def _stamp(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


add("stream_edges_dedup", lambda s, d: streams.drained(streams.dedup_edges(streams.event_stream(s, d)), "dedup"), "SELECT DISTINCT user_id, event_type FROM events")
add("stream_degree", lambda s, d: streams.last_batch(streams.drained(streams.stateful_degree(streams.event_stream(s, d)), "degree", "update"), ["user_id"]), "SELECT user_id, count(*) AS degree FROM events GROUP BY user_id")
# Over all events: a closing row lets the watermark pass every window and session.
add("stream_tumbling_pairs", lambda s, d: streams.drained(streams.tumbling_counts(streams.event_stream(s, d, closing=True)), "tumbling").select(_stamp("start"), "event_type", "n"), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
add("stream_sliding_users", lambda s, d: streams.drained(streams.sliding_users(streams.event_stream(s, d, closing=True)), "sliding").select(_stamp("start"), "users", "n"), "SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS start, count(DISTINCT user_id) AS users, count(*) AS n FROM (SELECT user_id, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS w FROM events) GROUP BY w")
add("stream_session_users", lambda s, d: streams.drained(streams.user_sessions(streams.event_stream(s, d, closing=True)), "sessions").select("user_id", _stamp("start"), "n"), "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, count(*) FILTER (WHERE p IS NULL OR ts >= p + INTERVAL 6 HOUR) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events)) GROUP BY user_id, session")


def _late(spark: SparkSession, d: str) -> DataFrame:
    """Rows that arrive a day late and more are dropped by the watermark: all later events come first."""
    from ..sources.scratch import fresh_path

    folder = fresh_path(spark, "late-files")
    ev = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    ev.where("ts >= '2024-01-10'").write.mode("append").parquet(folder)
    first = spark.readStream.schema(ev.schema).parquet(folder)
    out, state = fresh_path(spark, "late"), fresh_path(spark, "late-state")

    def go() -> None:
        streams.tumbling_counts(first).writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()

    go()
    ev.where("ts < '2024-01-10'").write.mode("append").parquet(folder)
    go()
    early = F.col("start") < F.lit("2024-01-10").cast("timestamp")
    return spark.read.parquet(out).agg(F.count_if(early).alias("late_windows"), F.count_if(~early).alias("windows"))


add("stream_late_drop", _late, "SELECT CAST(0 AS BIGINT) AS late_windows, count(*) AS windows FROM (SELECT DISTINCT date_trunc('day', ts) AS start, event_type FROM events WHERE ts >= TIMESTAMP '2024-01-10') WHERE start + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")


def snapshots_sql(estimates: str) -> str:
    """A release on the edges up to each week."""
    return "\nUNION ALL\n".join(
        f"SELECT {w} AS batch, CAST(estimate AS VARCHAR) AS estimate FROM (WITH pairs AS (SELECT user_id * 8 + 6 AS a, CAST('0x' || substr(md5(event_type), 1, 8) AS BIGINT) * 8 + 7 AS b FROM events{'' if w == 4 else f" WHERE date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) // 7 <= {w}"}), arcs AS (SELECT DISTINCT a AS src, b AS dst FROM (SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs)), deg AS (SELECT dst AS id, count(*) AS d FROM arcs GROUP BY dst), nodes AS (SELECT id FROM deg), {sql.runs(1.0, 1000 + w)}{estimates} SELECT * FROM est)"
        for w in range(5)
    )


add("stream_star_window", lambda s, d: streams.star_snapshots(streams.event_stream(s, d)).select("batch", "estimate"), snapshots_sql(sql.star_estimates(3)))
add("stream_foreach_walk", lambda s, d: streams.walk_snapshots(streams.event_stream(s, d)).select("batch", "estimate"), snapshots_sql(sql.walk_estimates(3, "")))


def _star_by_window(spark: SparkSession, d: str) -> DataFrame:
    """A private star count of each week's (user, type) graph; weeks are disjoint in time, an edge may be in several."""
    ev = table(spark, d, "events").withColumn("week", F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01")) / 7).cast("int"))
    out = None
    for w in range(5):
        pairs = ev.where(F.col("week") == w).select(encode("user_id", 6).alias("a"), (F.conv(F.substring(F.md5("event_type"), 1, 8), 16, 10).cast("long") * 8 + 7).alias("b"))
        g = Graph.from_pairs(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), pairs)
        one = star_dp(g, make_runs(spark, seed=42 + w), 3).select(F.lit(w).alias("week"), F.col("estimate").cast("string").alias("estimate"))
        out = one if out is None else out.union(one)
    return out


_WEEK = "\nUNION ALL\n".join(
    f"SELECT {w} AS week, CAST(estimate AS VARCHAR) AS estimate FROM (WITH pairs AS (SELECT user_id * 8 + 6 AS a, CAST('0x' || substr(md5(event_type), 1, 8) AS BIGINT) * 8 + 7 AS b FROM events WHERE date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) // 7 = {w}), arcs AS (SELECT DISTINCT a AS src, b AS dst FROM (SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs)), deg AS (SELECT dst AS id, count(*) AS d FROM arcs GROUP BY dst), {sql.runs(1.0, 42 + w)}{sql.star_estimates(3)} SELECT * FROM est)"
    for w in range(5)
)
add("stream_star_weeks_batch", _star_by_window, _WEEK)

# Python functions.
add("udf_pandas_laplace", lambda s, d: table(s, d, "part").select("p_partkey", F.round(udfs.laplace_np(uniform(F.lit(42), F.lit("f"), encode("p_partkey", 1)), F.lit(2.0)), 9).alias("x")), f"SELECT p_partkey, round({sql.laplace('2.0e0', '42', chr(39) + 'f' + chr(39), 'p_partkey * 8 + 1')}, 9) AS x FROM part")
add("udf_grouped_exact_paths", lambda s, d: udfs.grouped_paths(view(s, d, "turns").arcs.withColumn("conv", F.floor(F.col("src") / TURNS)), "conv", 4).agg(F.sum("ordered").alias("ordered")), "SELECT CAST(2 * sum(greatest(n - 4, 0)) AS BIGINT) AS ordered FROM (SELECT count(*) AS n FROM conversations GROUP BY conv_id)")
add("udaf_trimmed_mean", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(udfs.trimmed(F.col("l_quantity"), 100), 9).alias("trimmed")), "SELECT l_returnflag, round(avg(q), 9) AS trimmed FROM (SELECT l_returnflag, l_quantity AS q, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS r, count(*) OVER (PARTITION BY l_returnflag) AS n FROM lineitem) WHERE r > 100 AND r <= n - 100 GROUP BY l_returnflag")


def _udtf(text: str) -> Query:
    def make(spark: SparkSession, d: str) -> DataFrame:
        udfs.register(spark)
        return spark.sql(text)

    return make


# Numbers of tree shapes on 1 to 7 vertices.
add("udtf_free_trees", _udtf("SELECT n, trees FROM free_trees(7)"), "SELECT CAST(n AS INT) AS n, CAST(t AS INT) AS trees FROM (VALUES (1, 1), (2, 1), (3, 1), (4, 2), (5, 3), (6, 6), (7, 11)) AS v(n, t)")
add("udtf_comm_model", _udtf("SELECT method, round(bytes, 3) AS bytes FROM comm_model(1000D, 5000D, 4)"), "SELECT * FROM (VALUES ('walk', round(8 * (2 * (2 * 5000e0 + 2 * 1000e0) + 1000e0), 3)), ('path', round(8 * (2 * 5000e0 + 1000e0 + 2 * 2 * 5000e0 / 25 + 5 * 1000e0 / 5), 3)), ('star', 8000e0), ('capped_star', 24000e0), ('noisy_graph', 499500e0), ('clipped_walk', 32000000e0)) AS v(method, bytes)")
add("sql_dp_tree_call", lambda s, d: dp_sql(s, d, "SELECT CAST(estimate AS STRING) AS estimate, rounds FROM dp_tree('copurchase', '0-1,1-2,1-3', 1.0)"), sql.graph("copurchase") + ",\n" + sql.runs() + sql.tree_estimates(Pattern.parse("0-1,1-2,1-3").best_rooting()) + "\nSELECT CAST(estimate AS VARCHAR) AS estimate, 2 AS rounds FROM est")
add("sql_dp_walk_call", lambda s, d: dp_sql(s, d, "SELECT CAST(estimate AS STRING) AS estimate FROM dp_walk('copurchase', 3, 1.0)"), sql.graph("copurchase") + ",\n" + sql.runs() + sql.walk_estimates(3, "") + "\nSELECT CAST(estimate AS VARCHAR) AS estimate FROM est")
add("sql_dp_star_call", lambda s, d: estimate(dp_sql(s, d, "SELECT * FROM dp_star('trade', 3, 1.0)")), sql.graph("trade") + ",\n" + sql.runs() + sql.star_estimates(3) + "\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, 1 AS rounds FROM est")
