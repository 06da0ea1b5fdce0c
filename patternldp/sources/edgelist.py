"""A Python data source for edge lists: text files of two ids a line become symmetric arcs.

The source plans one partition per file; each streams its file through ``pyarrow``'s file system of the path's scheme.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeListSource(DataSource):
    """``spark.read.format("edgelist").option("separator", ...).load(path)`` gives ``src``, ``dst``, both directions, without loops."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> EdgeListReader:
        return EdgeListReader(self.options["path"], self.options.get("separator", "\t"))


class EdgeListReader(DataSourceReader):
    def __init__(self, path: str, separator: str):
        self.path, self.separator = path, separator

    def partitions(self) -> list[InputPartition]:
        fs, at = pa.fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path.removeprefix('file:')}")
        found = fs.get_file_info(pa.fs.FileSelector(at, recursive=True))
        return [InputPartition(f.path) for f in found if f.type == pa.fs.FileType.File and not f.base_name.startswith(("_", "."))] or [InputPartition(None)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int]]:
        if partition.value is None:
            return
        fs, _ = pa.fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path.removeprefix('file:')}")
        with fs.open_input_stream(partition.value) as raw:
            rest = b""
            while chunk := raw.read(1 << 20):
                *lines, rest = (rest + chunk).split(b"\n")
                yield from self._arcs(lines)
            yield from self._arcs([rest])

    def _arcs(self, lines: list[bytes]) -> Iterator[tuple[int, int]]:
        for line in lines:
            if line and not line.startswith(b"#"):
                a, b = (int(x) for x in line.decode().split(self.separator)[:2])
                if a != b:
                    yield a, b
                    yield b, a


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeListSource)
