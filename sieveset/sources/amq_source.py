"""Saved filter sets as a data source: ``spark.read.format("amq")``; and readers of keys in other formats."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "filter_id string, kind string, shard int, shard_count int, n_keys long, fp_bits int, capacity long, bits_total long, seed long"


class _Rows(InputPartition):
    def __init__(self, rows: list[tuple]):
        self.rows = rows


class FilterReader(DataSourceReader):
    """One row of metadata per shard, dealt to ``numPartitions`` tasks. Cells stay in the files: FilterSet.load reads them."""

    def __init__(self, options):
        self.path, self.parts = options.get("path"), int(options.get("numPartitions", "1"))
        if not self.path:
            raise ValueError("format amq needs a path")

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs
        from pyarrow import dataset as ds

        system, path = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path.removeprefix("file:"))
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        rows = ds.dataset(path, filesystem=system, partitioning="hive").to_table(columns=names).to_pylist()
        rows = [tuple(str(r[n]) if n == "filter_id" else r[n] for n in names) for r in rows]
        return [_Rows(rows[i :: self.parts]) for i in range(min(self.parts, max(1, len(rows))))]

    def read(self, partition: _Rows) -> Iterator[tuple]:
        yield from partition.rows


class FilterSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "amq"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> FilterReader:
        return FilterReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FilterSource)


def read_keys(spark: SparkSession, path: str, column: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """The key column of a file in any of Spark's formats: parquet, orc, csv, json or text. Only that column is read where the format allows it."""
    reader = spark.read.options(**options)
    if schema:
        reader = reader.schema(schema)
    if kind == "text":
        return reader.text(path).withColumnRenamed("value", column)
    return reader.format(kind).load(path).select(column)


def write_keys(df: DataFrame, path: str, kind: str = "parquet", mode: str = "overwrite", **options) -> None:
    df.write.mode(mode).options(**options).format(kind).save(path)
