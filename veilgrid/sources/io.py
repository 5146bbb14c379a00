"""Sources and sinks for points, reports and histograms."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

POINT_SCHEMA = "user_id long, x double, y double, part string"
HIST_SCHEMA = "cx int, cy int, mass double"


def read_many(spark: SparkSession, paths: list[str]) -> DataFrame:
    """Several files as one table, with the file each row came from."""
    return spark.read.parquet(*paths).withColumn("file", F.col("_metadata.file_path"))


def write_points(df: DataFrame, path: str, form: str = "parquet", parts: str | None = None) -> None:
    """csv, json, orc or parquet; ``parts`` makes one folder per value, and only folders that are written are replaced."""
    writer = df.write.mode("overwrite").format(form)
    if form == "csv":
        writer = writer.option("header", True)
    if parts:
        writer = writer.option("partitionOverwriteMode", "dynamic").partitionBy(parts)
    writer.save(path)


def read_points(spark: SparkSession, path: str, form: str = "parquet", schema: str = POINT_SCHEMA) -> DataFrame:
    reader = spark.read.format(form).schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).load(path)


def save_bucketed(df: DataFrame, name: str, column: str, buckets: int = 16) -> None:
    """A table bucketed by a key: joins and sums on that key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).saveAsTable(name)


class _Span(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__(first)
        self.first, self.last = first, last


class PointSource(DataSource):
    """format('ldp_points'): generated points, options kind (normal, szipf), rows, partitions, seed. Each partition has its own stream of numbers."""

    @classmethod
    def name(cls) -> str:
        return "ldp_points"

    def schema(self) -> str:
        return "user_id long, x double, y double"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _PointReader(dict(self.options))


class _PointReader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.rows = options.get("kind", "normal"), int(options.get("rows", "1000"))
        self.parts, self.seed = int(options.get("partitions", "4")), int(options.get("seed", "1"))

    def partitions(self) -> list[InputPartition]:
        edges = [self.rows * k // self.parts for k in range(self.parts + 1)]
        return [_Span(a, b) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition: _Span) -> Iterator[tuple]:
        import numpy as np

        rng = np.random.default_rng([self.seed, partition.first])
        n = partition.last - partition.first
        if self.kind == "szipf":
            x, y = 2 ** rng.random(n) - 1, 2 ** rng.random(n) - 1
        else:
            x = rng.standard_normal(n)
            y = 0.5 * x + 0.75**0.5 * rng.standard_normal(n)
        yield from zip(range(partition.first, partition.last), x.tolist(), y.tolist(), strict=True)
