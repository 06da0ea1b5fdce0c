"""The flagship: a private pattern count beside its truth, error, rounds and bytes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import ROOTED
from ..operators.cost import tree_measured
from ..operators.exact import closed_form
from ..operators.kernel import make_runs
from ..operators.tree import tree_dp
from ..plans.protocol import relative_error
from ..shipping import ship
from ..sources.views import view
from . import sql
from .methods import _FORK, comm_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def fork_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    g, tree = view(spark, sf_dir, "copurchase").pinned(), ROOTED["fork"]
    runs = make_runs(spark)
    sent = tree_measured(g, runs, tree).groupBy("run").agg(F.sum("bytes").alias("bytes"))
    out = tree_dp(g, runs, tree).join(sent, "run").crossJoin(F.broadcast(closed_form(g, "fork")))
    return out.select("run", F.col("estimate").cast("string").alias("estimate"), F.col("ordered").cast("string").alias("truth"), F.format_string("%.6e", relative_error(F.col("estimate"), F.col("ordered"))).alias("rel_err"), "rounds", "bytes")


QUERIES["flagship_fork_copurchase"] = fork_report
_BYTES = comm_sql("copurchase", ROOTED["fork"]).rpartition("\nSELECT run, channel")[0]
ORACLES["flagship_fork_copurchase"] = _BYTES + f",\ntr AS ({_FORK})\nSELECT run, CAST(estimate AS VARCHAR) AS estimate, CAST(CAST(t AS HUGEINT) AS VARCHAR) AS truth, {sql.digits('100.0e0 * abs(CAST(estimate AS DOUBLE) - CAST(t AS DOUBLE)) / abs(CAST(t AS DOUBLE))')} AS rel_err, {ROOTED['fork'].rounds} AS rounds, (SELECT CAST(sum(messages) * 8 AS BIGINT) FROM ch WHERE ch.run = est.run) AS bytes FROM est CROSS JOIN tr"
