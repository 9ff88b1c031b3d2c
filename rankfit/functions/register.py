"""SQL names for summaries: scalar functions, aggregates and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, BinaryType, DoubleType, LongType

from rankfit.config import AcsConfig
from rankfit.operators import codec, kernel
from rankfit.session import ship


def _each(kind: str):
    def ask(summary: pd.Series, x: pd.Series) -> pd.Series:
        out = []
        for s, v in zip(summary, x, strict=True):
            out.append(None if s is None or v is None or v != v else float(getattr(codec.answers(bytes(s)), kind)([v])[0]))
        return pd.Series(out, dtype="float64")

    return ask


@pandas_udf(DoubleType())
def rank_est(summary: pd.Series, x: pd.Series) -> pd.Series:
    return _each("rank")(summary, x)


@pandas_udf(DoubleType())
def cdf_est(summary: pd.Series, x: pd.Series) -> pd.Series:
    return _each("rank")(summary, x) / summary.map(lambda s: max(1, codec.answers(bytes(s)).s.n) if s is not None else 1)


@pandas_udf(DoubleType())
def quantile_est(summary: pd.Series, q: pd.Series) -> pd.Series:
    return _each("quantile")(summary, q)


@pandas_udf(BinaryType())
def summary_merge(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([y if x is None else x if y is None else codec.encode(kernel.finish(kernel.merge(codec.decode(x), codec.decode(y)))) for x, y in zip(a, b, strict=True)])


@pandas_udf(BinaryType())
def summary_resize(summary: pd.Series, k: pd.Series) -> pd.Series:
    return pd.Series([None if s is None else codec.encode(kernel.finish(kernel.resize(codec.decode(s), int(size)), compress=False)) for s, size in zip(summary, k, strict=True)])


@pandas_udf(LongType())
def summary_n(summary: pd.Series) -> pd.Series:
    return summary.map(lambda s: None if s is None else codec.answers(bytes(s)).s.n)


@pandas_udf(LongType())
def summary_bytes(summary: pd.Series) -> pd.Series:
    return summary.map(lambda s: None if s is None else codec.size_bytes(codec.answers(bytes(s)).s))


@pandas_udf(ArrayType(DoubleType()))
def summary_ends(summary: pd.Series) -> pd.Series:
    def ends(raw):
        state = codec.answers(bytes(raw)).s
        return None if not state.n else [float(state.vmin), float(state.vmax)]

    return summary.map(lambda s: None if s is None else ends(s))


@pandas_udf(BinaryType())
def acs_build(v: pd.Series) -> bytes:
    """Aggregate of raw values; convenient, but without a partial step: large inputs go through `build_summary`."""
    return codec.encode(kernel.finish(kernel.update(kernel.State(AcsConfig()), v.dropna().to_numpy(float))))


@pandas_udf(BinaryType())
def acs_merge(summary: pd.Series) -> bytes:
    from rankfit.plans.build import balanced

    return codec.encode(kernel.finish(balanced([codec.decode(s) for s in summary if s is not None])))


@udtf(returnType="idx int, lo double, hi double, cnt double, cum double")
class AcsBuckets:
    def eval(self, summary: bytes) -> Iterator[tuple]:
        state = codec.decode(summary)
        below = 0.0
        for i, (t, r) in enumerate(zip(state.t.tolist(), state.r.tolist(), strict=True)):
            yield i + 1, float(state.t[max(i - 1, 0)]), float(t), r - below, r
            below = r


@udtf(returnType="q double, value double")
class AcsQuantiles:
    def eval(self, summary: bytes, qs: list) -> Iterator[tuple]:
        yield from zip([float(q) for q in qs], codec.answers(bytes(summary)).quantile(qs).astype(float).tolist(), strict=True)


SCALARS = {"rank_est": rank_est, "cdf_est": cdf_est, "quantile_est": quantile_est, "summary_merge": summary_merge, "summary_resize": summary_resize, "summary_n": summary_n, "summary_bytes": summary_bytes, "summary_ends": summary_ends, "acs_build": acs_build, "acs_merge": acs_merge}


def register_functions(spark: SparkSession) -> None:
    """Make all names known to spark.sql."""
    ship(spark)
    for name, function in SCALARS.items():
        spark.udf.register(name, function)
    spark.udtf.register("acs_buckets", AcsBuckets)
    spark.udtf.register("acs_quantiles", AcsQuantiles)
