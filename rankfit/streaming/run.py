"""Bounded runs of summary streams."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, functions as F

from rankfit.config import AcsConfig
from rankfit.plans.build import map_summaries
from rankfit.session import new_table
from rankfit.sources.io import stream_files
from rankfit.streaming.summary_stream import summary_stream


def final_state(spark: SparkSession, folder: str, only: str, col: str, keys: Sequence[str], cfg: AcsConfig = AcsConfig()) -> DataFrame:
    """The summaries after all files `only` below a folder went through the stream."""
    schema = spark.read.parquet(f"{folder}/{only}").schema
    source = stream_files(spark, folder, schema, max_files=8, only=only)
    out, checkpoint = new_table(spark, "stream-out"), new_table(spark, "stream-checkpoint")

    def store(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/b={number}")

    stream = summary_stream(source, col, keys, cfg=cfg)
    stream.writeStream.outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(store).start().awaitTermination()
    rows = spark.read.parquet(out)
    latest = rows.groupBy(*keys).agg(F.max_by("summary", "batch").alias("summary"))
    return map_summaries(latest, lambda s: s)
