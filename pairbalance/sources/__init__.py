"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType


def read(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A Parquet table of a folder; filters and columns reach the scan."""
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_as(spark: SparkSession, path: str, fmt: str, schema: StructType | str, **options: str) -> DataFrame:
    """A csv, json, text, orc or parquet path with a stated schema; nothing is inferred."""
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def inline(spark: SparkSession, rows: list[tuple], schema: StructType | str) -> DataFrame:
    """A few rows from the driver."""
    return spark.createDataFrame(rows, schema)


def read_stream(spark: SparkSession, folder: str, schema: StructType, files_per_batch: int = 1) -> DataFrame:
    """New Parquet files of a folder as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def write(df: DataFrame, path: str, partition_by: list[str] | None = None, fmt: str = "parquet", mode: str = "errorifexists", table: str | None = None, bucket_by: tuple[int, list[str]] | None = None) -> None:
    """A path, split by columns if asked; or a table, bucketed and sorted by columns if asked."""
    writer = df.write.format(fmt).mode(mode)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if bucket_by:
        writer = writer.bucketBy(bucket_by[0], *bucket_by[1]).sortBy(*bucket_by[1])
    if table:
        writer.option("path", path).saveAsTable(table)
    else:
        writer.save(path)
