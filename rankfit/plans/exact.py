"""Exact ranks and order statistics, distributed: what estimates are held against."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window, functions as F

from rankfit.session import cut


def _offsets(df: DataFrame, size: Column, keys: Sequence[str]) -> DataFrame:
    """Per part (and keys): the sum of `size` over earlier parts."""
    sums = df.groupBy(*keys, "part").agg(F.sum(size).alias("_own"))
    earlier = Window.partitionBy(*keys).orderBy("part").rowsBetween(Window.unboundedPreceding, -1) if keys else Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return sums.select(*keys, "part", F.coalesce(F.sum("_own").over(earlier), F.lit(0)).alias("_base"))


def value_ranks(df: DataFrame, col: str, keys: Sequence[str] = ()) -> DataFrame:
    """(keys, v, cnt, cum): every distinct value with its count and exact rank, as a stored table.

    Values are counted before they move, dealt by range, summed inside each range and over ranges (one row for each).
    """
    kept = df.select(*keys, F.col(col).alias("v")).where(F.col("v").isNotNull())
    counts = kept.groupBy(*keys, "v").agg(F.count("*").alias("cnt"))
    dealt = cut(counts.repartitionByRange(*keys, "v").withColumn("part", F.spark_partition_id()))
    inside = F.sum("cnt").over(Window.partitionBy(*keys, "part").orderBy("v"))
    based = dealt.withColumn("_inside", inside).join(F.broadcast(_offsets(dealt, F.col("cnt"), keys)) if not keys else _offsets(dealt, F.col("cnt"), keys), [*keys, "part"])
    return cut(based.select(*keys, "v", "cnt", (F.col("_inside") + F.col("_base")).alias("cum")))


def numbered(df: DataFrame, order: str) -> DataFrame:
    """`df` with `number` from 1 in order of a column, and `total`."""
    dealt = cut(df.repartitionByRange(order).withColumn("part", F.spark_partition_id()))
    total = dealt.count()
    inside = F.row_number().over(Window.partitionBy("part").orderBy(order))
    based = dealt.withColumn("_inside", inside).join(F.broadcast(_offsets(dealt, F.lit(1), ())), "part")
    return based.withColumn("number", F.col("_inside") + F.col("_base")).withColumn("total", F.lit(total).cast("long")).drop("_inside", "_base", "part")


def exact_ranks(df: DataFrame, col: str, queries: DataFrame, keys: Sequence[str] = (), few: int = 4096) -> DataFrame:
    """Columns of `queries` (keys, x) and exact_rank: the number of values at or below x.

    Few queries are broadcast and counted in one scan; many are sorted into the values' ranges and take the rank of
    the last value at or below them.
    """
    if queries.limit(few + 1).count() <= few:
        q = queries.select(*[F.col(k).alias(f"_{k}") for k in keys], F.col("x").alias("_x")).distinct()
        match = F.col(col) <= F.col("_x")
        for k in keys:
            match &= F.col(k).eqNullSafe(F.col(f"_{k}"))
        rows = df.select(*keys, col).where(F.col(col).isNotNull())
        counted = rows.join(F.broadcast(q), match).groupBy(*[f"_{k}" for k in keys], "_x").agg(F.count("*").alias("exact_rank"))
        on = F.col("x") == F.col("_x")
        for k in keys:
            on &= F.col(k).eqNullSafe(F.col(f"_{k}"))
        out = queries.join(F.broadcast(counted), on, "left")
        return out.select(*queries.columns, F.coalesce("exact_rank", F.lit(0)).alias("exact_rank"))
    ranks = value_ranks(df, col, keys)
    both = ranks.select(*keys, F.col("v").alias("x"), "cum", F.lit(0).alias("asks")).unionByName(queries.select(*keys, F.col("x").cast(ranks.schema["v"].dataType), F.lit(None).cast("long").alias("cum"), F.lit(1).alias("asks")))
    dealt = cut(both.repartitionByRange(*keys, "x", "asks").withColumn("part", F.spark_partition_id()))
    tops = dealt.groupBy(*keys, "part").agg(F.max("cum").alias("_top"))
    earlier = Window.partitionBy(*keys).orderBy("part").rowsBetween(Window.unboundedPreceding, -1) if keys else Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    tops = tops.withColumn("_top", F.max("_top").over(earlier))
    inside = F.max("cum").over(Window.partitionBy(*keys, "part").orderBy("x", "asks").rowsBetween(Window.unboundedPreceding, 0))
    found = dealt.withColumn("_in", inside).where("asks = 1").join(tops, [*keys, "part"])
    return found.select(*keys, "x", F.coalesce(F.greatest("_in", "_top"), F.lit(0)).alias("exact_rank"))


def query_points(df: DataFrame, col: str, m: int) -> DataFrame:
    """(j, x, exact_rank, n): values at the places ceil(j n / m) of the sorted column."""
    ranks = value_ranks(df, col)
    total = ranks.agg(F.max("cum")).first()[0] or 0
    places = df.sparkSession.range(1, m + 1).select(F.col("id").cast("int").alias("j"), F.ceil(F.col("id") * F.lit(total) / F.lit(m)).cast("long").alias("p"))
    # A value answers a run of places: enumerate it instead of comparing every value with every place.
    low, high = F.floor((F.col("cum") - F.col("cnt")) * m / F.lit(max(total, 1))).cast("long") - 1, F.floor(F.col("cum") * m / F.lit(max(total, 1))).cast("long") + 1
    each = ranks.select("v", "cnt", "cum", F.explode(F.sequence(F.greatest(low, F.lit(1).cast("long")), F.greatest(high, F.lit(1).cast("long")))).alias("j"))
    found = each.join(F.broadcast(places) if m <= 200_000 else places, "j").where("p > cum - cnt and p <= cum")
    return found.select(F.col("j").cast("int").alias("j"), F.col("v").alias("x"), F.col("cum").alias("exact_rank"), F.lit(total).cast("long").alias("n"))


def exact_quantiles(df: DataFrame, col: str, qs: Sequence[float], keys: Sequence[str] = ()) -> DataFrame:
    """(keys, q, value): the smallest value whose rank reaches q n, without a group's rows meeting in one task."""
    ranks = value_ranks(df, col, keys)
    totals = ranks.groupBy(*keys).agg(F.max("cum").alias("n"))
    place = lambda q: F.greatest(F.lit(1).cast("long"), F.ceil(q * F.col("n")).cast("long"))
    # Each value keeps the fractions whose place lies in its run; no value meets all of them as rows.
    inside = lambda q: (place(q) > F.col("cum") - F.col("cnt")) & (place(q) <= F.col("cum"))
    asked = F.filter(F.array(*[F.lit(float(q)) for q in qs]), inside)
    if keys:
        same = F.lit(True)
        named = totals.select(*[F.col(k).alias(f"_{k}") for k in keys], "n")
        for k in keys:
            same &= F.col(k).eqNullSafe(F.col(f"_{k}"))
        joined = ranks.join(named, same)
    else:
        joined = ranks.crossJoin(F.broadcast(totals))  # one row
    return joined.select(*keys, "v", F.explode(asked).alias("q")).select(*keys, "q", F.col("v").alias("value"))


def profile(df: DataFrame, col: str) -> DataFrame:
    """(n, n_distinct, vmin, vmax, smallest_gap, aspect_ratio, max_count) of a column."""
    ranks = value_ranks(df, col)
    dealt = cut(ranks.repartitionByRange("v").withColumn("part", F.spark_partition_id()))
    # Neighbours: inside a part by lag, across parts by the largest value of the parts before.
    top = dealt.groupBy("part").agg(F.max("v").alias("_top"))
    top = top.withColumn("_top", F.max("_top").over(Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))  # a row for each task
    before = F.coalesce(F.lag("v").over(Window.partitionBy("part").orderBy("v")), F.col("_top"))
    gaps = dealt.join(F.broadcast(top), "part").withColumn("gap", F.col("v") - before)
    found = gaps.agg(F.sum("cnt").alias("n"), F.count("*").alias("n_distinct"), F.min("v").alias("vmin"), F.max("v").alias("vmax"), F.min("gap").alias("smallest_gap"), F.max("cnt").alias("max_count"))
    return found.select("n", "n_distinct", "vmin", "vmax", "smallest_gap", F.greatest(F.lit(2.0), (F.col("vmax") - F.col("vmin")) / F.col("smallest_gap")).alias("aspect_ratio"), "max_count")


def exact_frequent(df: DataFrame, col: str, k: int) -> DataFrame:
    """(v, cnt): values that occur more than n / k times."""
    counts = df.where(F.col(col).isNotNull()).groupBy(F.col(col).alias("v")).agg(F.count("*").alias("cnt"))
    n = df.agg(F.count(col).alias("n"))
    return counts.crossJoin(F.broadcast(n)).where(F.col("cnt") > F.col("n") / k).select("v", "cnt")
