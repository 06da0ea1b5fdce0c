"""Structured Streaming around the mechanisms.

A stream releases a result for every window, and an edge present in several windows pays for each: budgets of windows add up
in the ledger.  All streams here run with ``availableNow`` triggers, keep their state in checkpoints in the shared folder and
write to tables there.
"""

from __future__ import annotations

import shutil
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.kernel import make_runs
from ..operators.star import star_dp
from ..operators.walk import walk_dp
from ..sources.scratch import fresh_path
from ..sources.views import Graph

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
CLOSING = "30 days"
WEEKS, FILE_ROWS = 5, 5_000_000


def event_stream(spark: SparkSession, sf_dir: str, file_rows: int = FILE_ROWS, closing: bool = False) -> DataFrame:
    """The events as a stream, a week a micro-batch, in the order of time; ``ts`` as a timestamp.

    A trigger takes as many files as every week has, so a week is written and read by many tasks, about ``file_rows`` rows in
    each of the thinnest week's files, and still arrives at once.

    ``closing`` adds a last batch, one row of nulls ``CLOSING`` after the last event: it moves watermarks past all windows
    and sessions of events, while its own window stays open and is never written.
    """
    path = f"{sf_dir}/events.parquet"
    rows = spark.read.parquet(path)
    schema = rows.schema
    week = F.least(F.greatest(F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01")) / 7), F.lit(0)), F.lit(WEEKS - 1))
    sizes = {r["week"]: r["count"] for r in rows.groupBy(week.alias("week")).count().collect()}
    files = max(1, min(sizes.values(), default=0) // file_rows)
    folder = fresh_path(spark, "event-files")
    for w in sorted(sizes):  # one after the other, so that files are taken in the order of time
        rows.where(week == w).repartition(files).write.mode("append").parquet(folder)
    if closing or not sizes:
        last = rows.agg(F.max("ts").alias("ts")).where("ts IS NOT NULL")
        row = [(F.col("ts") + F.expr(f"INTERVAL {CLOSING}") if f.name == "ts" else F.lit(None)).cast(f.dataType).alias(f.name) for f in schema]
        last.select(*row).coalesce(1).write.mode("append").parquet(folder)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Run the stream over all that is there and return the table that it wrote."""
    spark = stream.sparkSession
    out, state = fresh_path(spark, label), fresh_path(spark, f"{label}-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    else:
        def keep(batch: DataFrame, i: int) -> None:
            batch.withColumn("_batch", F.lit(i)).write.mode("append").parquet(out)

        stream.writeStream.foreachBatch(keep).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


def last_batch(df: DataFrame, key: list[str]) -> DataFrame:
    """Of an update or complete stream's table, the latest row of each key."""
    cols = [c for c in df.columns if c not in (*key, "_batch")]
    return df.groupBy(*key).agg(F.max_by(F.struct(*cols), "_batch").alias("x")).select(*key, "x.*")


def dedup_edges(events: DataFrame, delay: str = "30 days") -> DataFrame:
    """Distinct (user, type) edges, once each within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def tumbling_counts(events: DataFrame, width: str = "1 day", delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding_users(events: DataFrame, width: str = "2 days", slide: str = "1 day", delay: str = "1 day") -> DataFrame:
    """``start``, ``users`` (distinct, exact) and ``n`` of each window; the state holds a row for each user of an open window."""
    each = events.withWatermark("ts", delay).groupBy(F.window("ts", width, slide).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return each.groupBy("w").agg(F.count("user_id").alias("users"), F.sum("n").alias("n")).select(F.col("w.start").alias("start"), "users", "n")


def user_sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def stateful_degree(events: DataFrame) -> DataFrame:
    """Per user, the number of events so far, kept in a state that grows with the users."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    return events.select("user_id").groupBy("user_id").applyInPandasWithState(step, "user_id long, degree long", "n long", "update", GroupStateTimeout.NoTimeout)


def snapshots(events: DataFrame, release: Callable[[Graph, DataFrame, int], DataFrame], eps: float, label: str) -> DataFrame:
    """Per micro-batch, the private release on the graph of all (user, type) edges seen so far.

    Each batch is a release of its own and costs ``eps``; seeds differ by batch.
    """
    spark = events.sparkSession
    out, seen, state = fresh_path(spark, label), fresh_path(spark, f"{label}-edges"), fresh_path(spark, f"{label}-state")

    def step(batch: DataFrame, i: int) -> None:
        batch.select((F.col("user_id") * 8 + 6).alias("a"), (F.conv(F.substring(F.md5("event_type"), 1, 8), 16, 10).cast("long") * 8 + 7).alias("b")).distinct().write.mode("append").parquet(seen)
        pairs = batch.sparkSession.read.schema("a long, b long").parquet(seen)
        graph = Graph.from_pairs(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), pairs).pinned()
        release(graph, make_runs(batch.sparkSession, eps, seed=1000 + i), i).withColumn("batch", F.lit(i)).write.mode("append").parquet(out)

    events.writeStream.foreachBatch(step).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


def star_snapshots(events: DataFrame, eps: float = 1.0) -> DataFrame:
    return snapshots(events, lambda g, r, i: star_dp(g, r, 3).select(F.col("estimate").cast("string").alias("estimate")), eps, "star-snapshots")


def walk_snapshots(events: DataFrame, eps: float = 1.0) -> DataFrame:
    return snapshots(events, lambda g, r, i: walk_dp(g, r, 3).select(F.col("estimate").cast("string").alias("estimate")), eps, "walk-snapshots")


def clear(path: str) -> None:
    """Remove a local folder of a finished stream, in tests."""
    shutil.rmtree(path.removeprefix("file://"), ignore_errors=True)
