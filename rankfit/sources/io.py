"""Sources and sinks: pruned scans, files with explicit schemas, streams, and a store of summaries."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, functions as F


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_column(spark: SparkSession, path: str, col: str, keys: Sequence[str] = (), where: str | None = None) -> DataFrame:
    """A Parquet scan of one column and its keys; the filter reaches the scan."""
    rows = spark.read.parquet(path)
    return (rows.where(where) if where else rows).select(*keys, col)


def read_any(spark: SparkSession, fmt: str, path: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a schema that is given, never inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def stream_files(spark: SparkSession, folder: str, schema, max_files: int = 100, only: str = "*.parquet") -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).option("pathGlobFilter", only).option("recursiveFileLookup", True).parquet(folder)


def stream_rate(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """(timestamp, value) at a steady rate, for timing."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def save_summaries(summaries: DataFrame, path: str, by: Sequence[str] = ()) -> None:
    """Write summaries below `path`; of a partitioned store only the partitions that are written again change."""
    writer = summaries.write.mode("overwrite")
    if by:
        writer = writer.option("partitionOverwriteMode", "dynamic").partitionBy(*by)
    writer.parquet(path)


def load_summaries(spark: SparkSession, path: str, where: str | None = None) -> DataFrame:
    rows = spark.read.parquet(path)
    return rows.where(where) if where else rows


def range_ordered(df: DataFrame, col: str, parts: int) -> DataFrame:
    """Rows dealt by range of `col`, ordered inside each part."""
    return df.repartitionByRange(parts, col).sortWithinPartitions(col).withColumn("part", F.spark_partition_id())
