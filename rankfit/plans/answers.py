"""Ranks, quantiles and what follows from them, asked of summary DataFrames."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F
from pyspark.sql.types import ArrayType, DoubleType

from rankfit.operators import codec
from rankfit.plans.build import _key_schema, arrow_schema
from rankfit.session import ship

BROADCAST_BYTES = 64 << 20


def _asked(kind: str):
    @F.pandas_udf(ArrayType(DoubleType()))
    def ask(summary, xs):
        import pandas as pd

        return pd.Series([None if s is None or x is None else getattr(codec.answers(bytes(s)), kind)(np.asarray(x)).astype(float) for s, x in zip(summary, xs, strict=True)])

    return ask


def ranks_of(summary: Column | str, xs: Column | str) -> Column:
    """Array of estimated ranks of an array of values."""
    return _asked("rank")(summary, xs)


def quantiles_of(summary: Column | str, qs: Column | str) -> Column:
    """Array of estimated quantiles of an array of fractions."""
    return _asked("quantile")(summary, qs)


def _small(summaries: DataFrame) -> bool:
    """Whether all summaries together stay below the size that may be sent to every task."""
    total = summaries.agg(F.sum(F.octet_length("summary"))).first()[0]
    return (total or 0) <= BROADCAST_BYTES


def _query(summaries: DataFrame, queries: DataFrame, keys: Sequence[str], x: str, out: str, kind: str) -> DataFrame:
    ship(queries.sparkSession)
    others = [c for c in queries.columns]
    ddl = ", ".join([*_key_schema(queries, others), f"{out} double", "est_n long"])
    schema = arrow_schema(ddl)
    few = summaries.select(*[F.col(f"`{k}`") for k in keys], "summary")

    def answered(batch: pa.RecordBatch, blobs: list) -> pa.RecordBatch:
        values = batch.column(x).to_numpy(zero_copy_only=False)
        found, sizes = np.full(len(values), np.nan), np.zeros(len(values), np.int64)
        rows_of: dict = {}
        for i, b in enumerate(blobs):
            rows_of.setdefault(b, []).append(i)
        for blob, rows in rows_of.items():
            if blob is not None:
                answers = codec.answers(blob)
                found[rows], sizes[rows] = getattr(answers, kind)(values[rows]), answers.s.n
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in others), pa.array(found, mask=np.isnan(found)), pa.array(sizes)], schema=schema)

    if _small(few):
        known = {tuple(r[k] for k in keys): bytes(r["summary"]) for r in few.collect()}  # its size is checked above
        shared = queries.sparkSession.sparkContext.broadcast(known)

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                own = list(zip(*(batch.column(k).to_pylist() for k in keys), strict=True)) if keys else [()] * batch.num_rows
                yield answered(batch, [shared.value.get(k) for k in own])

        return queries.mapInArrow(run, ddl)
    joined = queries.join(few, list(keys), "left") if keys else queries.crossJoin(few)

    def run_joined(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield answered(batch, batch.column("summary").to_pylist())

    return joined.mapInArrow(run_joined, ddl)


def query_ranks(summaries: DataFrame, queries: DataFrame, keys: Sequence[str] = (), x: str = "x") -> DataFrame:
    """Columns of `queries`, est_rank, est_cdf."""
    found = _query(summaries, queries, keys, x, "est_rank", "rank")
    return found.withColumn("est_cdf", F.col("est_rank") / F.col("est_n")).drop("est_n")


def query_quantiles(summaries: DataFrame, queries: DataFrame, keys: Sequence[str] = (), q: str = "q") -> DataFrame:
    """Columns of `queries`, value."""
    return _query(summaries, queries, keys, q, "value", "quantile").drop("est_n")


def range_fraction(summaries: DataFrame, low: float, high: float) -> DataFrame:
    """Columns of `summaries` with `fraction`: the share of items in (low, high]."""
    asked = summaries.withColumn("_r", ranks_of("summary", F.array(F.lit(float(low)), F.lit(float(high)))))
    return asked.withColumn("fraction", (F.col("_r")[1] - F.col("_r")[0]) / F.greatest(F.col("n"), F.lit(1))).drop("_r")


def quantile_map(summaries: DataFrame, qs: Sequence[float]) -> DataFrame:
    """Columns of `summaries` with `quantiles`: a map from fraction to value."""
    fractions = F.array(*[F.lit(float(q)) for q in qs])
    return summaries.withColumn("quantiles", F.map_from_arrays(fractions, quantiles_of("summary", fractions)))


def outliers(df: DataFrame, col: str, summaries: DataFrame, q: float, keys: Sequence[str] = ()) -> DataFrame:
    """Rows of `df` above their group's estimated quantile."""
    limits = summaries.select(*keys, quantiles_of("summary", F.array(F.lit(float(q))))[0].alias("_limit"))
    limits = F.broadcast(limits) if _small(summaries) else limits
    joined = df.join(limits, list(keys)) if keys else df.crossJoin(limits)
    return joined.where(F.col(col).cast("double") > F.col("_limit")).drop("_limit")


def rank_column(df: DataFrame, col: str, summaries: DataFrame, keys: Sequence[str] = (), tiles: int = 4) -> DataFrame:
    """`df` with est_percent_rank in 0..1 and est_tile in 1..tiles."""
    asked = df.withColumn("_x", F.col(col).cast("double"))
    found = query_ranks(summaries, asked, keys, "_x").drop("_x", "est_rank")
    tile = F.least(F.greatest(F.ceil(F.col("est_cdf") * tiles), F.lit(1)), F.lit(tiles)).cast("int")
    return found.withColumn("est_tile", tile).withColumnRenamed("est_cdf", "est_percent_rank")


def range_ids(df: DataFrame, col: str, summary: DataFrame, parts: int) -> DataFrame:
    """`df` with range_id in 0..parts-1 of about equal sizes, cut at estimated quantiles."""
    cuts = F.array(*[F.lit(i / parts) for i in range(1, parts)])
    bounds = summary.select(quantiles_of("summary", cuts).alias("_cuts"))
    at = F.size(F.filter("_cuts", lambda c: c < F.col(col).cast("double")))
    return df.crossJoin(F.broadcast(bounds)).withColumn("range_id", at).drop("_cuts")


def ks_distance(a: DataFrame, b: DataFrame, points: int = 512) -> DataFrame:
    """(ks double): the largest distance of two summaries' CDFs over both sides' quantiles."""
    grid = F.array(*[F.lit(i / points) for i in range(1, points + 1)])
    left = a.select(F.col("summary").alias("sa"), F.col("n").alias("na"), quantiles_of("summary", grid).alias("qa"))
    right = b.select(F.col("summary").alias("sb"), F.col("n").alias("nb"), quantiles_of("summary", grid).alias("qb"))
    both = left.crossJoin(F.broadcast(right)).withColumn("xs", F.concat("qa", "qb"))
    both = both.withColumn("ra", ranks_of("sa", "xs")).withColumn("rb", ranks_of("sb", "xs"))
    return both.select(F.array_max(F.zip_with("ra", "rb", lambda x, y: F.abs(x / F.col("na") - y / F.col("nb")))).alias("ks"))


def qq_table(a: DataFrame, b: DataFrame, qs: Sequence[float]) -> DataFrame:
    """(q, value_a, value_b)."""
    fractions = F.array(*[F.lit(float(q)) for q in qs])
    left, right = a.select(quantiles_of("summary", fractions).alias("va")), b.select(quantiles_of("summary", fractions).alias("vb"))
    rows = left.crossJoin(F.broadcast(right)).select(F.explode(F.arrays_zip(fractions.alias("q"), F.col("va"), F.col("vb"))).alias("z"))
    return rows.select(F.col("z.q").alias("q"), F.col("z.va").alias("value_a"), F.col("z.vb").alias("value_b"))


BUCKETS = "idx int, lo double, hi double, cnt double, cum_lo double, cum_hi double, slope_lo double, slope_hi double"


def explode_buckets(summaries: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """One row for each bucket, with the rank curve's slopes at both ends (times the bucket's length)."""
    ship(summaries.sparkSession)
    ddl = ", ".join([*_key_schema(summaries, keys), BUCKETS])
    schema = arrow_schema(ddl)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, raw in enumerate(batch.column("summary").to_pylist()):
                curve = codec.answers(raw).curve
                t, r = curve.t.astype(float), curve.r
                if not len(t):
                    continue
                slope = np.stack([np.concatenate(([0.0], getattr(curve, side, np.diff(r)))) for side in ("left", "right")])
                low, below = np.concatenate((t[:1], t[:-1])), np.concatenate(([0.0], r[:-1]))
                columns = [np.arange(1, len(t) + 1, dtype=np.int32), low, t, r - below, below, r, *slope]
                own = [pa.array([batch.column(k)[i].as_py()] * len(t), batch.column(k).type) for k in keys]
                yield pa.RecordBatch.from_arrays([*own, *map(pa.array, columns)], schema=schema)

    return summaries.select(*keys, "summary").mapInArrow(run, ddl)
