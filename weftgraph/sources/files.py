"""Readers and writers of graph tables: Parquet, CSV, JSON lines, ORC, bucketed tables, and tiles as a source of their own."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

EDGE_SCHEMA = "eid long, src long, dst long, weight long, direction int"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE_SCHEMA) -> DataFrame:
    """Edges from files of a format, with a given schema so that nothing is inferred."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", by: list[str] = ()) -> None:
    writer = edges.write.mode("overwrite").format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*by) if by else writer).save(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int, key: str = "src") -> None:
    """A catalogued table whose joins on ``key`` need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


class _Rows(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class LatticeSource(DataSource):
    """``format("lattice")``: edges of a grid of nodes, generated where they are read.

    Options: width, rows, partitions. For tests of size without files.
    """

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return "eid long, src long, dst long, weight long"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _LatticeReader(self.options)


class _LatticeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.width, self.rows = int(options.get("width", 10)), int(options.get("rows", 10))
        self.parts = max(1, int(options.get("partitions", 4)))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.rows // self.parts)
        return [_Rows(i, min(i + step, self.rows)) for i in range(0, self.rows, step)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        w = self.width
        for y in range(partition.first, partition.last):
            for x in range(w):
                n = y * w + x
                if x + 1 < w:
                    yield (2 * n, n, n + 1, 1 + n % 7)
                if y + 1 < self.rows:
                    yield (2 * n + 1, n, n + w, 1 + n % 5)
