"""Point sources beside Parquet tables, and sinks."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from orthant.functions.shipping import ship


def points(spark: SparkSession, path: str, format: str, schema: str) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a given schema; a row that doesn't fit it fails."""
    reader = spark.read.schema(schema).format(format)
    if format in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    if format == "csv":
        reader = reader.option("header", True)
    return reader.load(path)


def stream_dir(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


class _Rows(InputPartition):
    def __init__(self, start: int, stop: int) -> None:
        self.start, self.stop = start, stop


class _ColumnReader(DataSourceReader):
    def __init__(self, options: dict, names: list[str]) -> None:
        self.names = names
        self.paths = [options[f"path_{n}"] for n in names]
        self.step = int(options.get("rows_per_partition", 1 << 20))

    def partitions(self) -> list[InputPartition]:
        import os

        n = min(os.path.getsize(p) // 8 for p in self.paths)
        return [_Rows(i, min(n, i + self.step)) for i in range(0, n, self.step)] or [_Rows(0, 0)]

    def read(self, partition: _Rows) -> Iterator[pa.RecordBatch]:
        import numpy as np

        size = partition.stop - partition.start
        columns = [np.fromfile(p, dtype="<f8", count=size, offset=8 * partition.start) for p in self.paths]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(partition.start, partition.stop)), *map(pa.array, columns)], ["pid", *self.names])


class ColumnArrays(DataSource):
    """One file per property, each a plain array of little-endian doubles, aligned by position.

    A partition is a range of rows of all files, so nothing is joined. Files must be visible to every executor.
    """

    @classmethod
    def name(cls) -> str:
        return "column_arrays"

    def schema(self) -> str:
        names = self.options["names"].split(",")
        return "pid long, " + ", ".join(f"{n} double" for n in names)

    def reader(self, schema) -> DataSourceReader:
        return _ColumnReader(dict(self.options), self.options["names"].split(","))


def column_arrays(spark: SparkSession, paths: dict[str, str], rows_per_partition: int = 1 << 20) -> DataFrame:
    ship(spark)
    spark.dataSource.register(ColumnArrays)
    reader = spark.read.format("column_arrays").option("names", ",".join(paths)).option("rows_per_partition", rows_per_partition)
    for n, p in paths.items():
        reader = reader.option(f"path_{n}", p)
    return reader.load()


def explode_coords(df: DataFrame, array: str = "coords", dims: int = 3) -> DataFrame:
    return df.select("*", *(F.get(F.col(array), F.lit(i)).alias(f"c{i}") for i in range(dims))).drop(array)


def pack_coords(df: DataFrame, dims: int) -> DataFrame:
    coords = [f"c{i}" for i in range(dims)]
    return df.withColumn("coords", F.array(*coords)).drop(*coords)


def write_neighbors(df: DataFrame, path: str, mode: str = "append") -> None:
    df.write.mode(mode).parquet(path)
