"""Answers from summaries that are already there: coarser groups, moving windows, stored days, latest snapshots."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from rankfit.operators import codec, kernel
from rankfit.plans.build import arrow_schema, finish_summaries, remerge
from rankfit.session import cut, ship
from rankfit.sources.io import load_summaries


def rollup_summaries(summaries: DataFrame, levels: Iterable[Sequence[str]], keys: Sequence[str]) -> DataFrame:
    """(level, keys or null, summary, details) for each list of keys in `levels`, from the finest summaries alone.

    The summaries are multiplied, not the rows below them.
    """
    wanted = [tuple(level) for level in levels]
    masks = F.explode(F.array(*[F.struct(F.lit(i).alias("level"), *[F.lit(k in level).alias(f"has_{k}") for k in keys]) for i, level in enumerate(wanted)])).alias("m")
    spread = summaries.select(*keys, "summary", masks)
    spread = spread.select(F.col("m.level").alias("level"), *[F.when(F.col(f"m.has_{k}"), F.col(k)).alias(k) for k in keys], "summary")
    return remerge(spread, ["level", *keys])


def rolling_summaries(summaries: DataFrame, time: str, before: int, keys: Sequence[str] = ()) -> DataFrame:
    """`summaries` (keys, time, summary) with each one merged with the `before` rows ahead of it; rows stay small.

    Rows are numbered without their summaries and dealt in runs that overlap by `before` rows. Inside a run a window is
    the end of one block of rows and the beginning of the next: three merges for each row, however long the window is.
    """
    ship(summaries.sparkSession)
    width = before + 1
    run = 8 * width
    plain = summaries.select(*keys, time, "summary").withColumn("_id", F.monotonically_increasing_id())
    stored = cut(plain)
    numbered = _numbered(stored.select(*keys, time, "_id"), [*keys, time, "_id"], keys)
    first = F.floor(F.col("_n") / run).cast("long")
    runs = numbered.select("_id", "_n", F.explode(F.array_distinct(F.array(first, F.floor((F.col("_n") + before) / run).cast("long")))).alias("_run"))
    dealt = stored.join(runs, "_id")
    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in stored.schema if f.name in (*keys, time)), "summary binary"])
    schema = arrow_schema(ddl)

    def roll(table: pa.Table) -> pa.Table:
        table = table.sort_by("_n")
        blobs, numbers = table.column("summary").to_pylist(), table.column("_n").to_pylist()
        own, merged = table.column("_run")[0].as_py(), {}
        tails: list[bytes] = []  # merges of the rows from each one of the last block to its end
        head: bytes | None = None
        for i, n in enumerate(numbers):
            at = i % width
            if not at:
                tails = list(accumulate(reversed(blobs[max(i - width, 0) : i]), lambda later, x: _merged([x, later])))[::-1]
                head = None
            head = _merged([head, blobs[i]]) if head else blobs[i]
            if n // run == own:
                rest = tails[at + 1 :][:1]
                merged[i] = _merged([*rest, head], True)
        kept = table.take(pa.array(list(merged), pa.int64())).drop_columns(["summary"])
        return kept.append_column("summary", pa.array(list(merged.values()), pa.binary())).select(schema.names).cast(schema)

    rolled = dealt.groupBy(*keys, "_run").applyInArrow(roll, ddl)
    return finish_summaries(rolled)


def _merged(blobs: list[bytes], finished: bool = False) -> bytes:
    state = kernel.merge_many([codec.decode(x) for x in blobs])
    return codec.encode(kernel.finish(state) if finished else state)


def _numbered(rows: DataFrame, order: Sequence[str], keys: Sequence[str]) -> DataFrame:
    """`rows` with `_n`, their number from 0 in `order` within `keys`, dealt by ranges."""
    parted = cut(rows.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    earlier = Window.partitionBy(*keys or [F.lit(0)]).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = parted.groupBy(*keys, "_part").agg(F.count("*").alias("_c")).select(*keys, "_part", F.coalesce(F.sum("_c").over(earlier), F.lit(0)).alias("_base"))
    inside = parted.withColumn("_in", F.row_number().over(Window.partitionBy(*keys, "_part").orderBy(*order)))
    same = inside["_part"] == counts["_part"]
    for k in keys:
        same &= inside[k].eqNullSafe(counts[k])
    return inside.join(counts, same).select(*[inside[c] for c in rows.columns], (F.col("_base") + F.col("_in") - 1).cast("long").alias("_n"))


def asof_summary(events: DataFrame, snapshots: DataFrame, time: str, keys: Sequence[str] = ()) -> DataFrame:
    """`events` with snapshot_time and summary of the latest snapshot (keys, snapshot_time, summary) not after them."""
    cols = events.columns
    left = events.select(*cols, F.lit(None).cast("timestamp_ntz").alias("snapshot_time"), F.lit(None).cast("binary").alias("summary"), F.col(time).alias("_t"), F.lit(1).alias("_side"))
    right = snapshots.select(*[F.col(c) if c in keys else F.lit(None).cast(events.schema[c].dataType).alias(c) for c in cols], F.col("snapshot_time").cast("timestamp_ntz"), "summary", F.col("snapshot_time").cast("timestamp_ntz").alias("_t"), F.lit(0).alias("_side"))
    ordered = Window.partitionBy(*keys).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    found = left.unionByName(right).withColumn("snapshot_time", F.last("snapshot_time", True).over(ordered)).withColumn("summary", F.last("summary", True).over(ordered))
    return found.where("_side = 1").select(*cols, "snapshot_time", "summary")


def from_catalog(spark: SparkSession, path: str, where: str, keys: Sequence[str] = ()) -> DataFrame:
    """Summaries of the stored partitions that `where` selects, merged; nothing below them is read."""
    return remerge(load_summaries(spark, path, where), keys)


def union_summaries(a: DataFrame, b: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Summaries of the union of both inputs' rows."""
    return remerge(a.select(*keys, "summary").unionByName(b.select(*keys, "summary")), keys)
