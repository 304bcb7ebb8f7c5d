"""White-space edge lists (u v length a line) as a Python data source with partitions by file range."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class EdgeListReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.path, self.size = options["path"], int(options.get("rangebytes", 8 << 20))

    def partitions(self) -> list[_Range]:
        import os

        n = os.path.getsize(self.path)
        return [_Range(self.path, a, min(a + self.size, n)) for a in range(0, n, self.size)] or [_Range(self.path, 0, 0)]

    def read(self, part: _Range):
        with open(part.path, "rb") as f:
            f.seek(part.start)
            if part.start:
                f.seek(part.start - 1)
                if f.read(1) != b"\n":
                    f.readline()  # the line belongs to the range before
            while f.tell() < part.end and (line := f.readline()):
                fields = line.split()
                if len(fields) >= 3 and not line.startswith(b"#"):
                    u, v, w = int(fields[-3]), int(fields[-2]), int(float(fields[-1]))
                    yield min(u, v), max(u, v), w


class EdgeList(DataSource):
    """spark.read.format("edge_list").load(path): for files that executors can open; other stores go through spark.read.text."""

    @classmethod
    def name(cls) -> str:
        return "edge_list"

    def schema(self) -> str:
        return "u long, v long, w long"

    def reader(self, schema) -> EdgeListReader:
        return EdgeListReader(self.options)


def register_edge_list(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeList)


def edges_from_text(spark: SparkSession, path: str):
    """The same by Spark's own reader, from any store that it knows."""
    from pyspark.sql import functions as F

    f = F.split(F.trim("value"), "\\s+")
    rows = spark.read.text(path).filter(~F.col("value").startswith("#") & (F.size(f) >= 3))
    u, v = F.element_at(f, -3).cast("long"), F.element_at(f, -2).cast("long")
    return rows.select(F.least(u, v).alias("u"), F.greatest(u, v).alias("v"), F.element_at(f, -1).cast("double").cast("long").alias("w"))
