"""Row functions over Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .scratch import release_memory
from .wordbytes import chunks

Run = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def released(run: Run) -> Run:
    """``run`` for a worker that is kept for other stages: at a task's end what it freed goes back to the system."""
    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release_memory()

    return task


def map_texts(df: DataFrame, text: int, schema: T.StructType, make: Callable[[list[list]], dict[str, list]], limit: int = 1 << 20) -> DataFrame:
    """Apply ``make`` (columns in, columns out, any number of rows) to runs of rows of about ``limit`` characters.

    ``text`` is the position of the column that bounds a run.  The rows of one run are the only ones held.
    """
    target = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = [c.to_pylist() for c in batch.columns]
            for lo, hi in chunks(cols[text], limit):
                out = make([c[lo:hi] for c in cols])
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type) for f in target], schema=target)

    return df.mapInArrow(released(run), schema)
