"""Accuracy, size and time of summaries, and the experiments that compare them."""

from __future__ import annotations

import time
from collections.abc import Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from rankfit.config import AcsConfig
from rankfit.operators import codec, kernel
from rankfit.operators.baselines import BASELINES
from rankfit.plans.answers import query_ranks
from rankfit.plans.exact import query_points
from rankfit.session import ship


def rank_error(summaries: DataFrame, df: DataFrame, col: str, m: int = 1000) -> DataFrame:
    """(m, n, avg_err, max_err): rank errors over m evenly spaced data points, as shares of n."""
    points = query_points(df, col, m)
    asked = query_ranks(summaries, points.withColumn("x", F.col("x").cast("double")))
    err = F.abs(F.col("est_rank") - F.col("exact_rank")) / F.col("n")
    return asked.agg(F.count("*").alias("m"), F.max("n").alias("n"), F.avg(err).alias("avg_err"), F.max(err).alias("max_err"))


def quantile_error(q: np.ndarray, low_rank: np.ndarray, high_rank: np.ndarray, n: int) -> np.ndarray:
    """Distance of q n to the ranks (low, high] of the returned value, as a share of n."""
    return np.maximum(np.maximum(low_rank + 1 - np.ceil(q * n), np.ceil(q * n) - high_rank), 0) / n


def method(name: str, size: int):
    """(begin, add, join, answer) of a method by name; `acs` takes options after colons, as acs:filter=none."""
    if name.split(":")[0] == "acs":
        options = dict(o.split("=") for o in name.split(":")[1:])
        typed = {k: type(getattr(AcsConfig(), k))(v) if k != "min_split" else float(v) for k, v in options.items()}
        cfg = AcsConfig(k=size, **typed)
        return (lambda: kernel.State(cfg)), kernel.update, kernel.merge, lambda s: kernel.Answers(kernel.finish(s)), codec.encode, codec.decode
    kind = BASELINES[name]
    return (lambda: kind(size)), (lambda s, v: s.update(v)), (lambda a, b: a.merge(b)), (lambda s: s), (lambda s: s.encode()), kind.decode


def sized(name: str, n_bytes: int) -> int:
    """The size parameter that gives about `n_bytes`."""
    per = {"compactor": 12, "rank_bounds": 24, "moments": 16, "centroids": 9}.get(name, 16)
    return max({"moments": 3, "compactor": 8}.get(name, 6), n_bytes // per - (1 if name == "moments" else 0))


def bytes_of(answer) -> int:
    return codec.size_bytes(answer.s) if isinstance(answer, kernel.Answers) else answer.bytes


def compare(df: DataFrame, methods: Sequence[str], sizes: Sequence[int], chunks: int = 1, m: int = 1000) -> DataFrame:
    """(method, bytes_asked, bytes, n, avg_err, max_err, status, update_us, merge_us, below_n_over_k) over (seq, v).

    The last says how many times the average error is below n / k, with k of 16 bytes each.

    The stream setting is one reader in arrival order; with `chunks`, equal shares of it are summarised apart and
    merged in a balanced tree. Inputs of experiments, not of production: a chunk is read by one task.
    """
    from rankfit.sources.workloads import chunked

    ship(df.sparkSession)
    points = query_points(df, "v", m).select("x", "exact_rank", "n").toPandas().astype({"x": float})  # m rows
    parts = chunked(df, chunks).select("chunk", "seq", F.col("v").cast("double").alias("v"))
    names, asked = list(methods), list(sizes)
    schema = "method string, bytes_asked int, chunk int, blob binary, us double, items long"

    def build(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("seq").to_numpy(), kind="stable")
        v, rows = table.column("v").to_numpy()[order], []
        for name in names:
            for size in asked:
                begin, add, _, _, encode, _ = method(name, sized(name, size))
                began = time.perf_counter()
                state = add(begin(), v)
                if chunks > 1 and isinstance(state, kernel.State):
                    state = kernel.finish(state, compress=False)
                rows.append((name, size, int(table.column("chunk")[0].as_py()), encode(state), (time.perf_counter() - began) * 1e6, len(v)))
        kinds = (pa.string(), pa.int32(), pa.int32(), pa.binary(), pa.float64(), pa.int64())
        return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=[c.split()[0] for c in schema.split(", ")])

    out = "method string, bytes_asked int, bytes long, n long, avg_err double, max_err double, status string, update_us double, merge_us double, below_n_over_k double"
    xs, exact, n = points["x"].to_numpy(), points["exact_rank"].to_numpy(float), int(points["n"].iloc[0]) if len(points) else 0

    def measure(table: pd.DataFrame) -> pd.DataFrame:
        name, size = table["method"].iloc[0], int(table["bytes_asked"].iloc[0])
        _, _, join, answer, _, decode = method(name, sized(name, size))
        states = [decode(b) for b in table.sort_values("chunk")["blob"]]
        count, began = len(states), time.perf_counter()
        while len(states) > 1:
            states = [join(a, b) for a, b in zip(states[::2], states[1::2], strict=False)] + (states[-1:] if len(states) % 2 else [])
        merge_us = (time.perf_counter() - began) * 1e6 / max(1, count - 1)
        done = answer(states[0])
        err = np.abs(done.rank(xs) - exact) / max(n, 1)
        failed = getattr(done, "status", "ok") != "ok" or not np.isfinite(err).all()
        return pd.DataFrame([[name, size, bytes_of(done), n, None if failed else err.mean(), None if failed else err.max(), "failed" if failed else "ok", table["us"].sum() / table["items"].sum(), merge_us, None if failed or not err.any() else 16 / bytes_of(done) / err.mean()]], columns=[c.split()[0] for c in out.split(", ")])

    return parts.groupBy("chunk").applyInArrow(build, schema).groupBy("method", "bytes_asked").applyInPandas(measure, out)


def ratio(results: pd.DataFrame, ours: str, other: str, column: str = "avg_err") -> float:
    """How many times larger the other method's error is, at the size nearest to each of ours; the median."""
    a, b = results[results["method"] == ours], results[(results["method"] == other) & (results["status"] == "ok")]
    found = [b.iloc[(b["bytes"] - x["bytes"]).abs().argmin()][column] / max(x[column], 1e-12) for _, x in a.iterrows()] if len(b) else [np.nan]
    return float(np.median(found))


def query_us(answer, xs: np.ndarray) -> float:
    began = time.perf_counter()
    answer.rank(xs)
    return (time.perf_counter() - began) * 1e6 / max(1, len(xs))


def _timed(df: DataFrame, schema: str, measure) -> DataFrame:
    """Rows of `measure` (values in arrival order), by one task: a clock's input, not production."""
    ship(df.sparkSession)
    columns = [(c.split()[0], {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}[c.split()[1]]) for c in schema.split(", ")]

    def run(table: pa.Table) -> pa.Table:
        v = table.column("v").to_numpy()[np.argsort(table.column("seq").to_numpy(), kind="stable")]
        rows = list(measure(v))
        return pa.Table.from_arrays([pa.array([r[i] for r in rows], k) for i, (_, k) in enumerate(columns)], names=[c for c, _ in columns])

    return df.select("seq", F.col("v").cast("double").alias("v")).groupBy(F.lit(0).alias("all")).applyInArrow(run, schema)


def update_time(df: DataFrame, methods: Sequence[str], sizes: Sequence[int], shares: Sequence[float] = (0.125, 0.25, 0.5, 1.0)) -> DataFrame:
    """(method, bytes_asked, n, update_us): time of an update by method, by size and as the input grows."""

    def measure(v: np.ndarray):
        for name in methods:
            for size in sizes:
                begin, add, *_ = method(name, sized(name, size))
                for share in shares:
                    own = v[: max(1, int(share * len(v)))]
                    began = time.perf_counter()
                    add(begin(), own)
                    yield name, size, len(own), (time.perf_counter() - began) * 1e6 / len(own)

    return _timed(df, "method string, bytes_asked int, n long, update_us double", measure)


def query_time(df: DataFrame, methods: Sequence[str], sizes: Sequence[int], ms: Sequence[int] = (100, 1_000, 10_000, 100_000)) -> DataFrame:
    """(method, bytes_asked, m, query_us): time of a rank query by method, by size and by how many are asked at once."""

    def measure(v: np.ndarray):
        for name in methods:
            for size in sizes:
                begin, add, _, answer, *_ = method(name, sized(name, size))
                state = add(begin(), v)
                for m in ms:
                    xs = np.resize(v, m)
                    began = time.perf_counter()
                    answer(state).rank(xs)
                    yield name, size, m, (time.perf_counter() - began) * 1e6 / m

    return _timed(df, "method string, bytes_asked int, m long, query_us double", measure)


def diagnostics(summaries: DataFrame) -> DataFrame:
    """`summaries` with `events`: counts of splits, joins, doublings, rounds and epochs."""
    from pyspark.sql.types import LongType, MapType, StringType

    @F.pandas_udf(MapType(StringType(), LongType()))
    def events(summary: pd.Series) -> pd.Series:
        return summary.map(lambda s: {k: int(v) for k, v in codec.answers(bytes(s)).s.meta.items()})

    return summaries.withColumn("events", events("summary"))


def invariants(summaries: DataFrame) -> DataFrame:
    """`summaries` with `rules`: a map from each structural rule to whether it holds."""
    from pyspark.sql.types import BooleanType, MapType, StringType

    @F.pandas_udf(MapType(StringType(), BooleanType()))
    def rules(summary: pd.Series) -> pd.Series:
        return summary.map(lambda s: {k: bool(v) for k, v in kernel.invariants(codec.decode(bytes(s))).items()})

    return summaries.withColumn("rules", rules("summary"))
