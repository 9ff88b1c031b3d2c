"""Summaries of streams: a state for each key (and window), encoded, in the stream's state store."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankfit.config import AcsConfig
from rankfit.operators import codec, kernel
from rankfit.plans.build import _key_schema, axis_column
from rankfit.session import ship


def summary_stream(df: DataFrame, col: str, keys: Sequence[str], time: str | None = None, window: str | None = None, slide: str | None = None, watermark: str | None = None, cfg: AcsConfig = AcsConfig()) -> DataFrame:
    """(keys, window_start, summary, n, vmin, vmax) in update mode: a row for each key a micro-batch touched.

    Late rows are dropped before the state by the watermark; a window's state goes when the watermark passes its end.
    """
    ship(df.sparkSession)
    rows = df
    if watermark:
        rows = rows.withWatermark(time, watermark)
    plain = [F.col(k) for k in keys] + [axis_column(df, col, cfg.axis).alias("v")]
    by = list(keys)
    if window:
        rows = rows.select(*plain, F.col(time), F.window(time, window, slide).alias("w"))
        rows = rows.select(*keys, "v", time, F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"))
        by += ["window_start", "window_end"]
    else:
        rows = rows.select(*plain, *([time] if time and watermark else []))
    ddl = ", ".join([*_key_schema(rows, by), "summary binary", "n long", "vmin double", "vmax double"])
    timeout = GroupStateTimeout.EventTimeTimeout if window and watermark else GroupStateTimeout.NoTimeout

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        own = codec.decode(state.get[0]) if state.exists else kernel.State(cfg)
        for part in parts:
            v = part["v"]
            own.n_null += int(v.isna().sum())
            kernel.update(own, v.dropna().to_numpy())
        state.update((codec.encode(own),))
        if timeout == GroupStateTimeout.EventTimeTimeout:
            state.setTimeoutTimestamp(max(int(pd.Timestamp(key[-1]).timestamp() * 1000), state.getCurrentWatermarkMs() + 1))
        raw = codec.encode(kernel.finish(own))
        yield pd.DataFrame([[*key, raw, own.n, None if own.vmin is None else float(own.vmin), None if own.vmax is None else float(own.vmax)]], columns=[*by, "summary", "n", "vmin", "vmax"])

    return rows.groupBy(*by).applyInPandasWithState(step, ddl, "summary binary", "update", timeout)
