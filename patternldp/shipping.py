"""Makes this package importable in Python workers, wherever the session was started from."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> None:
    """Add the package's sources to the session once; workers on any machine fetch them from the driver."""
    context = spark.sparkContext
    if getattr(context, "_patternldp_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    fd, path = tempfile.mkstemp(prefix="patternldp-", suffix=".zip")
    with os.fdopen(fd, "wb") as out, zipfile.ZipFile(out, "w") as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.join("patternldp", os.path.relpath(full, root)))
    context.addPyFile(path)
    context._patternldp_shipped = True
