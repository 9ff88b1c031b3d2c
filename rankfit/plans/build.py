"""Building, merging and resizing summaries as DataFrames.

Raw rows never shuffle: each task summarises the rows it scans, a state for each group, and only the summaries (16
bytes for each bucket) meet, in a balanced tree of merges. A task whose groups outgrow `task_bytes` emits its largest
states as partials and begins them anew, which mergeability allows.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F, types as T

from rankfit.config import AcsConfig
from rankfit.operators import codec, kernel
from rankfit.session import ship

TASK_BYTES = 256 << 20
FANOUT = 64
DETAILS = "n long, n_null long, n_nan long, vmin double, vmax double, imin long, imax long, buckets int, items int, size_bytes long"
_detail_types = [pa.int64()] * 3 + [pa.float64()] * 2 + [pa.int64()] * 2 + [pa.int32()] * 2 + [pa.int64()]


def axis_column(df: DataFrame, col: str | Column, axis: str) -> Column:
    """A numeric, date or timestamp column on the summary's axis."""
    column = F.col(col) if isinstance(col, str) else col
    kind = df.select(column.alias("v")).schema["v"].dataType
    if isinstance(kind, T.TimestampType | T.TimestampNTZType):
        column = F.unix_micros(column.cast("timestamp"))
    elif isinstance(kind, T.DateType):
        column = F.unix_date(column)
    elif isinstance(kind, T.DecimalType) and axis == "i64":
        if kind.precision > 18:
            raise TypeError("a decimal of more than 18 digits has no integer axis")
        column = (column * F.lit(10**kind.scale)).cast("long")
    elif isinstance(kind, T.DayTimeIntervalType):
        column = F.expr(f"cast(extract(epoch from {col}) * 1000000 as long)") if isinstance(col, str) else column.cast("long")
    elif not isinstance(kind, T.NumericType):
        raise TypeError(f"no summary of {kind.simpleString()} values")
    elif axis == "i64" and isinstance(kind, T.FractionalType) and not isinstance(kind, T.DecimalType):
        raise TypeError("floating-point values have no integer axis")
    return column.cast("double" if axis == "f64" else "long")


def _key_schema(df: DataFrame, keys: Sequence[str]) -> list[str]:
    return [f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys]


def _groups(table: pa.Table, keys: Sequence[str]) -> Iterator[tuple[tuple, np.ndarray | None]]:
    """Each group of a table with its rows, or None for all of them."""
    if not keys:
        yield (), None
        return
    codes = np.zeros(table.num_rows, np.int64)
    for k in keys:
        encoded = pc.dictionary_encode(table.column(k).combine_chunks(), null_encoding="encode")
        codes = codes * (len(encoded.dictionary) + 1) + encoded.indices.to_numpy(zero_copy_only=False)
        codes = np.unique(codes, return_inverse=True)[1]
    order = np.argsort(codes, kind="stable")
    starts = np.flatnonzero(np.concatenate(([True], np.diff(codes[order]) > 0)))
    for rows in np.split(order, starts[1:]):
        yield tuple(table.column(k)[int(rows[0])].as_py() for k in keys), rows


def _rows(schema: pa.Schema, keys: list[tuple], *columns: list) -> pa.RecordBatch:
    parts = [pa.array(x, f.type) for x, f in zip([*(map(list, zip(*keys, strict=True)) if keys and keys[0] else []), *columns], schema, strict=True)]
    return pa.RecordBatch.from_arrays(parts, schema=schema)


def arrow_schema(ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(T._parse_datatype_string(ddl))


def _local_build(keys: tuple[str, ...], weighted: bool, cfg: AcsConfig, schema: pa.Schema, prior, task_bytes: int):
    def begun() -> kernel.State:
        return kernel.preset(cfg, prior) if prior is not None else kernel.State(cfg)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        states: dict[tuple, kernel.State] = {}
        held = 0

        def emit(some: list[tuple]) -> pa.RecordBatch:
            done = [states.pop(k) for k in some]
            for s in done:
                if s.buffered > s.k:
                    kernel.fold(s)
            return _rows(schema, some, [shard] * len(some), [codec.encode(s) for s in done])

        for batch in batches:
            table = pa.Table.from_batches([batch])
            values, weights = table.column("v").combine_chunks(), table.column("w").combine_chunks() if weighted else None
            for key, rows in _groups(table, keys) if table.num_rows else ():
                own = values if rows is None else values.take(pa.array(rows))
                w = None if weights is None else pc.fill_null(weights if rows is None else weights.take(pa.array(rows)), 0).to_numpy(zero_copy_only=False)
                state = states.get(key)
                if state is None:
                    state = states[key] = begun()
                before = state.buffered
                if own.null_count:
                    there = pc.is_valid(own)
                    state.n_null += own.null_count if w is None else int(w[~there.to_numpy(zero_copy_only=False)].sum())
                    w = None if w is None else w[there.to_numpy(zero_copy_only=False)]
                    own = own.drop_null()
                kernel.update(state, own.to_numpy(zero_copy_only=False).copy(), w)
                held += 16 * max(0, state.buffered - before) + (0 if before else 400)
            if held > task_bytes and len(states) > 1:
                largest = sorted(states, key=lambda k: -states[k].buffered)[: max(1, len(states) // 2)]
                yield emit(largest)
                held = sum(16 * s.buffered + 16 * s.k for s in states.values())
        every = list(states)
        for at in range(0, len(every), 1024):
            yield emit(every[at : at + 1024])

    return run


def partials(df: DataFrame, col: str | Column, keys: Sequence[str] = (), weight: str | Column | None = None, cfg: AcsConfig = AcsConfig(), prior=None, task_bytes: int = TASK_BYTES) -> DataFrame:
    """(keys, shard, summary) of each group of each task."""
    ship(df.sparkSession)
    w = [] if weight is None else [(F.col(weight) if isinstance(weight, str) else weight).cast("long").alias("w")]
    plain = df.select(*[F.col(f"`{k}`") for k in keys], axis_column(df, col, cfg.axis).alias("v"), *w)
    ddl = ", ".join([*_key_schema(df, keys), "shard long", "summary binary"])
    return plain.mapInArrow(_local_build(tuple(keys), weight is not None, cfg, arrow_schema(ddl), prior, task_bytes), ddl)


def balanced(states: list[kernel.State]) -> kernel.State:
    """One state of many: pairs of like size merge, round by round."""
    states = sorted(states, key=lambda s: s.n)
    while len(states) > 1:
        paired = [kernel.merge(a, b) for a, b in zip(states[::2], states[1::2], strict=False)]
        states = paired + (states[-1:] if len(states) % 2 else [])
    return states[0]


def _levels(df: DataFrame, fanout: int) -> int:
    """Levels of a merge tree for as many tasks as the plan's estimated size makes."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    shards = min(1 << 24, max(df.sparkSession.sparkContext.defaultParallelism, size >> 27))
    return max(1, int(np.ceil(np.log(shards) / np.log(fanout))))


def merge_summaries(df: DataFrame, keys: Sequence[str] = (), fanout: int = FANOUT, levels: int = 1) -> DataFrame:
    """(keys, shard, summary): one for each group, by a tree of `levels` shuffles of summaries."""
    ddl = ", ".join([*_key_schema(df, keys), "shard long", "summary binary"])
    schema = arrow_schema(ddl)

    def run(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("shard").to_numpy(), kind="stable").tolist()
        blobs = table.column("summary")
        merged = balanced([codec.decode(blobs[i].as_py()) for i in order])
        key = tuple(table.column(k)[0].as_py() for k in keys)
        return pa.Table.from_batches([_rows(schema, [key], [table.column("shard")[order[0]].as_py()], [codec.encode(merged)])])

    for level in reversed(range(levels)):
        group = [F.col(f"`{k}`") for k in keys]
        if level:
            df = df.withColumn("shard", F.pmod("shard", F.lit(fanout**level)))
            df = df.groupBy(*group, "shard").applyInArrow(run, ddl)
        elif keys:
            df = df.groupBy(*group).applyInArrow(run, ddl)
        else:
            df = df.groupBy(F.lit(0).alias("all")).applyInArrow(run, ddl)
    return df


def details(state: kernel.State) -> list:
    low, high = state.vmin, state.vmax
    whole = state.cfg.axis == "i64"
    return [state.n, state.n_null, state.n_nan, None if low is None else float(low), None if high is None else float(high), int(low) if whole and low is not None else None, int(high) if whole and high is not None else None, len(state.t), len(state.items.v), codec.size_bytes(state)]


def map_summaries(df: DataFrame, change) -> DataFrame:
    """`change` every summary in its own row; all other columns stay, the details follow."""
    ship(df.sparkSession)
    others = [c for c in df.columns if c not in ("summary", *[d.split()[0] for d in DETAILS.split(", ")])]
    ddl = ", ".join([*_key_schema(df, others), "summary binary", DETAILS])
    schema = arrow_schema(ddl)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            states = [change(codec.decode(x)) for x in batch.column("summary").to_pylist()]
            columns = [batch.column(c) for c in others] + [pa.array([codec.encode(s) for s in states], pa.binary())]
            found = list(zip(*map(details, states), strict=True)) if states else [[]] * len(_detail_types)
            yield pa.RecordBatch.from_arrays([*columns, *(pa.array(x, k) for x, k in zip(found, _detail_types, strict=True))], schema=schema)

    return df.select(*[F.col(f"`{c}`") for c in others], "summary").mapInArrow(run, ddl)


def finish_summaries(df: DataFrame) -> DataFrame:
    """Finished summaries with their details."""
    return map_summaries(df.drop("shard"), kernel.finish)


def resize_summaries(df: DataFrame, k: int) -> DataFrame:
    return map_summaries(df, lambda s: kernel.finish(kernel.resize(s, k), compress=False))


def build_summary(df: DataFrame, col: str | Column, keys: Sequence[str] = (), weight=None, cfg: AcsConfig = AcsConfig(), prior=None, fanout: int = FANOUT, levels: int | None = None, k_build: int | None = None) -> DataFrame:
    """(keys, summary, details) of each group. With `k_build`, partials are larger and shrink at the end."""
    built = partials(df, col, keys, weight, replace(cfg, k=k_build) if k_build else cfg, prior)
    merged = merge_summaries(built, keys, fanout, _levels(df, fanout) if levels is None else levels)
    if k_build:
        return map_summaries(merged.drop("shard"), lambda s: kernel.finish(kernel.resize(s, cfg.k)))
    return finish_summaries(merged)


#: Bytes of stored summaries that one task of a tree's first level may be expected to get.
REMERGE_BYTES = 16 << 20


def remerge(df: DataFrame, keys: Sequence[str] = (), levels: int | None = None, fanout: int = FANOUT) -> DataFrame:
    """Finished summaries of coarser groups from stored finer ones, by a tree as deep as the plan's estimated size asks for."""
    if levels is None:
        size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        levels = max(1, int(np.ceil(np.log(min(1 << 24, max(1, size // REMERGE_BYTES))) / np.log(fanout))))
    others = df.select(*[F.col(f"`{k}`") for k in keys], F.pmod(F.xxhash64("summary"), F.lit(1 << 30)).alias("shard"), "summary")
    return finish_summaries(merge_summaries(others, keys, fanout, levels))


def build_ladder(df: DataFrame, col: str, chunk: str, cfg: AcsConfig = AcsConfig()) -> DataFrame:
    """(rung int, summary, details): unequal partials, one for each `chunk`, merged only within size classes."""
    from rankfit.operators.ladder import Ladder

    parts = build_summary(df, col, [chunk], cfg=cfg, levels=1).select("summary")

    def run(table: pa.Table) -> pa.Table:
        ladder = Ladder(cfg)
        for raw in table.column("summary").to_pylist():
            ladder.add(codec.decode(raw))
        rungs = sorted(ladder.rungs.items())
        return pa.table({"rung": pa.array([k for k, _ in rungs], pa.int32()), "summary": pa.array([codec.encode(s) for _, s in rungs], pa.binary())})

    return map_summaries(parts.groupBy(F.lit(0).alias("all")).applyInArrow(run, "rung int, summary binary"), lambda s: s)
