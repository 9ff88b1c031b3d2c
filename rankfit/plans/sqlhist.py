"""The relational side: buckets and the rank curve as DataFrame expressions, with no Python in the plan."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window, functions as F

from rankfit.plans.exact import value_ranks


def equi_depth(df: DataFrame, col: str, k: int, keys: Sequence[str] = ()) -> DataFrame:
    """(keys, idx, t, cum): start thresholds at k places spread evenly over the sorted column, with exact ranks."""
    ranks = value_ranks(df, col, keys)
    totals = ranks.groupBy(*keys).agg(F.max("cum").alias("total"))
    places = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("i")
    wanted = totals.select(*keys, "total", places).withColumn("p", F.ceil(F.col("i") * (F.col("total") - 1) / F.lit(float(k - 1))).cast("long") + 1)
    joined = ranks.join(F.broadcast(wanted), list(keys)) if keys else ranks.crossJoin(F.broadcast(wanted))
    hit = joined.where("p > cum - cnt and p <= cum").select(*keys, F.col("v").alias("t"), F.col("cum").cast("double").alias("cum")).distinct()
    return hit.select(*keys, F.row_number().over(_by(keys, "t")).alias("idx"), "t", "cum")


def _by(keys: Sequence[str], order: str):
    return Window.partitionBy(*keys).orderBy(order) if keys else Window.orderBy(order)


def bucket_columns(nodes: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """`nodes` with b (count) and l (length; the first takes the second's)."""
    w = _by(keys, "t")
    length = F.col("t") - F.lag("t").over(w)
    return nodes.withColumn("b", F.col("cum") - F.coalesce(F.lag("cum").over(w), F.lit(0.0))).withColumn("l", F.coalesce(length, F.lead("t").over(w) - F.col("t")))


def one_sided(b, length, other_b, other_l) -> Column:
    return F.abs(b - other_b * (length / other_l)) * (length / (length + other_l))


def curvature(nodes: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys, idx, t, b, l, score): the larger one-sided second difference of the density times length squared."""
    w = _by(keys, "t")
    rows = bucket_columns(nodes, keys)
    left = one_sided(F.col("b"), F.col("l"), F.coalesce(F.lag("b").over(w), F.col("b")), F.coalesce(F.lag("l").over(w), F.col("l")))
    right = one_sided(F.col("b"), F.col("l"), F.coalesce(F.lead("b").over(w), F.lit(0.0)), F.coalesce(F.lead("l").over(w), F.col("l")))
    return rows.withColumn("score", F.greatest(left, right)).select(*keys, "idx", "t", "b", "l", "score")


def pair_scores(nodes: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys, idx, score): of the bucket that would join buckets idx and idx + 1, for all but the first and last."""
    w = _by(keys, "t")
    rows = bucket_columns(nodes, keys)
    jb, jl = F.col("b") + F.lead("b").over(w), F.col("l") + F.lead("l").over(w)
    left = one_sided(jb, jl, F.lag("b").over(w), F.lag("l").over(w))
    right = one_sided(jb, jl, F.coalesce(F.lead("b", 2).over(w), F.lit(0.0)), F.coalesce(F.lead("l", 2).over(w), F.lead("l").over(w)))
    scored = rows.withColumn("score", F.greatest(left, right)).withColumn("_last", F.lead("t").over(w))
    return scored.where("idx > 1 and _last is not null").select(*keys, "idx", "score")


def node_slopes(nodes: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """One row for each bucket with its nodes and monotone-cubic slopes at both."""
    w = _by(keys, "t")
    h1, h0 = F.lead("t").over(w) - F.col("t"), F.col("t") - F.lag("t").over(w)
    s1, s0 = (F.lead("cum").over(w) - F.col("cum")) / h1, (F.col("cum") - F.lag("cum").over(w)) / h0
    rows = nodes.withColumn("h1", h1).withColumn("h0", h0).withColumn("s1", s1).withColumn("s0", s0)
    w1, w2 = 2 * F.col("h1") + F.col("h0"), F.col("h1") + 2 * F.col("h0")
    inner = F.when((F.col("s0") > 0) & (F.col("s1") > 0), (w1 + w2) / (w1 / F.col("s0") + w2 / F.col("s1"))).otherwise(0.0)

    def end(h, s, other_h, other_s):
        d = ((2 * h + other_h) * s - h * other_s) / (h + other_h)
        return F.coalesce(F.least(F.greatest(d, F.lit(0.0)), 3 * s), s)

    first = end(F.col("h1"), F.col("s1"), F.lead("h1").over(w), F.lead("s1").over(w))
    last = end(F.col("h0"), F.col("s0"), F.lag("h0").over(w), F.lag("s0").over(w))
    rows = rows.withColumn("m", F.when(F.col("h0").isNull(), first).when(F.col("h1").isNull(), last).otherwise(inner))
    rows = rows.withColumn("hi", F.lead("t").over(w)).withColumn("cum_hi", F.lead("cum").over(w)).withColumn("m_hi", F.lead("m").over(w))
    return rows.where("hi is not null").select(*keys, F.col("t").alias("lo"), "hi", F.col("cum").alias("cum_lo"), "cum_hi", F.col("m").alias("m_lo"), "m_hi")


def rank_sql(buckets: DataFrame, queries: DataFrame, keys: Sequence[str] = (), interp: str = "pchip") -> DataFrame:
    """Columns of `queries` (keys, x) and est_rank, by a range join with the (broadcast) buckets of `node_slopes`."""
    match = (F.col("lo") < F.col("x")) & (F.col("x") <= F.col("hi"))
    kept = buckets.select(*[F.col(k).alias(f"_{k}") for k in keys], "lo", "hi", "cum_lo", "cum_hi", "m_lo", "m_hi")
    ends = buckets.groupBy(*[F.col(k).alias(f"_{k}") for k in keys]).agg(F.min("lo").alias("_min"), F.min_by("cum_lo", "lo").alias("_first"), F.max("hi").alias("_max"), F.max("cum_hi").alias("_total"))
    same = F.lit(True)
    for k in keys:
        same &= F.col(k).eqNullSafe(F.col(f"_{k}"))
    joined = queries.join(F.broadcast(kept), match & same, "left").drop(*[f"_{k}" for k in keys]).join(F.broadcast(ends), same, "left")
    u, h = (F.col("x") - F.col("lo")) / (F.col("hi") - F.col("lo")), F.col("hi") - F.col("lo")
    rise = F.col("cum_hi") - F.col("cum_lo")
    value = F.col("cum_lo") + rise * u if interp == "linear" else F.col("cum_lo") + rise * u * u * (3 - 2 * u) + h * u * (1 - u) * (F.col("m_lo") * (1 - u) - F.col("m_hi") * u)
    rank = F.when(F.col("x") < F.col("_min"), 0.0).when(F.col("x") == F.col("_min"), F.col("_first")).when(F.col("x") > F.col("_max"), F.col("_total")).otherwise(value)
    return joined.select(*queries.columns, rank.alias("est_rank"))


def recount(df: DataFrame, col: str, nodes: DataFrame) -> DataFrame:
    """`nodes` (t) with exact ranks from a second scan: bounds are broadcast, counts combine before they move."""
    bounds = nodes.agg(F.sort_array(F.collect_list("t")).alias("_t"))
    at = F.size(F.filter("_t", lambda t: t < F.col(col))) + 1
    counts = df.where(F.col(col).isNotNull()).crossJoin(F.broadcast(bounds)).groupBy(at.alias("idx")).agg(F.count("*").alias("cnt"))
    ordered = nodes.select("t", F.row_number().over(Window.orderBy("t")).alias("idx"))
    joined = ordered.join(F.broadcast(counts), "idx", "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)))
    return joined.select("idx", "t", F.sum("cnt").over(Window.orderBy("idx")).cast("double").alias("cum"))
