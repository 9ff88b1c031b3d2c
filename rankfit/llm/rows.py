"""What several operators need: rows by their id and text, samples by hash, and tasks that give memory back."""

from __future__ import annotations

import ctypes

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

FEW = 100_000


def released(run):
    """`run` over a task's batches, giving back what it held when it ends: idle workers stay for later tasks."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):
                pass  # another C library

    return task


def text_hash() -> Column:
    return F.xxhash64(F.col("text")).alias("text_hash")


def keep_rows(docs: DataFrame, kept: DataFrame) -> DataFrame:
    """Rows of `docs`, all columns, whose id and text are in `kept` (doc_id, text_hash, single).

    Where `single` is true only one of the rows that share both stays. `kept` has one row for each pair and is
    read more than once, so it should be a stored table.
    """
    wide = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r"), F.col("doc_id").cast("long").alias("id"), text_hash())
    names = kept.select(F.col("doc_id").alias("kept_id"), F.col("text_hash").alias("kept_hash"))
    same = F.col("id").eqNullSafe(F.col("kept_id")) & (F.col("text_hash") == F.col("kept_hash"))
    rows = wide.join(names, same, "left_semi")
    several = kept.where("single").select(F.col("doc_id").alias("kept_id"), F.col("text_hash").alias("kept_hash"))
    few = several.limit(FEW + 1).count()
    if not few:
        return rows.select("r.*")
    several = F.broadcast(several) if few <= FEW else several
    again = rows.join(several, same, "left_semi").groupBy("id", "text_hash").agg(F.min("r").alias("r"))
    return rows.join(several, same, "left_anti").select("r.*").unionByName(again.select("r.*"))


def hashed_sample(rows: DataFrame, bound: int, seed: int, *keys: str) -> DataFrame:
    """About `bound` different rows of a stored table by `keys`, all if it has fewer: those whose hash lies in the lowest share.

    Each task filters its rows alone, so nothing is sorted and no more than the sample leaves the tasks. The hash is that
    of the keys, so that neither the order nor the files of the table matter, and rows alike in them count once.
    """
    n = rows.agg(F.approx_count_distinct(F.xxhash64(*keys), 0.02)).first()[0]
    place = F.xxhash64(F.lit(seed), *keys).cast("double") / 2.0**64 + 0.5
    return rows.where(place <= min(1.0, bound / max(n, 1))).dropDuplicates(list(keys))
