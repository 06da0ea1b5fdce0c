"""Mechanisms in SQL text: ``SELECT ... FROM dp_tree('copurchase', '0-1,1-2,1-3', 1.0)``.

Table functions cannot start jobs, so calls are replaced by temporary views of the programs before Spark parses the text.
"""

from __future__ import annotations

import ast
import re

from pyspark.sql import DataFrame, SparkSession

from .functions.pattern import Pattern
from .operators.kernel import make_runs
from .operators.star import star_dp
from .operators.tree import path_dp, tree_dp
from .operators.walk import walk_dp
from .sources.views import view

_CALL = re.compile(r"\bdp_(walk|path|tree|star)\s*\(([^()]*)\)", re.I)


def parse_call(name: str, arguments: str) -> tuple[str, str, object, float, int]:
    """Kind, view, size or pattern, epsilon, seed."""
    args = ast.literal_eval(f"({arguments},)") if arguments.strip() else ()
    if not 3 <= len(args) <= 4 or not isinstance(args[0], str) or not isinstance(args[1], str if name == "tree" else int):
        raise ValueError(f"dp_{name} takes a view, a {'pattern' if name == 'tree' else 'number of edges'}, epsilon and perhaps a seed")
    return name, args[0], args[1], float(args[2]), int(args[3]) if len(args) > 3 else 42


def dp_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    def put(m: re.Match) -> str:
        kind, name, what, eps, seed = parse_call(m[1].lower(), m[2])
        g, runs = view(spark, sf_dir, name).pinned(), make_runs(spark, eps, seed)
        if kind == "tree":
            df = tree_dp(g, runs, Pattern.parse(what).best_rooting())
        else:
            df = {"walk": walk_dp, "path": path_dp, "star": star_dp}[kind](g, runs, what)
        target = f"_dp_{kind}_{abs(hash((name, what, eps, seed)))}"
        df.createOrReplaceTempView(target)
        return target

    return spark.sql(_CALL.sub(put, text))
