"""Best-fit packing by minimum bin slack.

Documents are encoded, ended and cut into pieces of at most `capacity` tokens, the first of which may be shorter. A
full piece is a sequence of its own. The rest are packed by length alone, and there are fewer than `capacity`
lengths: so the packing is planned once over how many pieces each length has, a table whose size doesn't depend on
the corpus. Each bin takes the longest piece left; a bitset subset-sum over the lengths that remain finds the fullest
combination for the room beside it, and as many bins as the stock allows are filled alike before the next search.
Pieces then find their bin by their number among those of equal length: a running count inside each task plus the
counts of the tasks before it. No piece meets more than its own length's part of the plan.

Defined results: a null or empty text is the end token alone. Null ids and repeated rows are packed like any others.
Extra columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F

from rankfit.llm import byte_bpe
from rankfit.llm.rows import released
from rankfit.session import cut, ship

CAPACITY, SLICE = 1024, 2048


def fullest(stock: dict[int, int], room: int) -> dict[int, int]:
    """How many of each length fill `room` best; among equals, longer ones."""
    reach, items = [1], []
    mask = (1 << (room + 1)) - 1
    for length in sorted(x for x in stock if x <= room):
        left, step = min(stock[length], room // length), 1
        while left:
            n = min(step, left)
            items.append((length, n))
            reach.append((reach[-1] | reach[-1] << length * n) & mask)
            left, step = left - n, 2 * step
    at, taken = reach[-1].bit_length() - 1, {}
    for (length, n), before in zip(reversed(items), reversed(reach[:-1]), strict=True):
        if at >= length * n and before >> (at - length * n) & 1:
            taken[length] = taken.get(length, 0) + n
            at -= length * n
    return taken


def plan(stock: dict[int, int], capacity: int = CAPACITY) -> list[tuple[dict[int, int], int]]:
    """Bins as (how many of each length, how many bins alike)."""
    stock, out = {k: v for k, v in stock.items() if v > 0}, []
    while stock:
        longest = max(stock)
        stock[longest] -= 1
        content = fullest({k: v for k, v in stock.items() if v}, capacity - longest)
        stock[longest] += 1
        content[longest] = content.get(longest, 0) + 1
        alike = min(stock[k] // n for k, n in content.items())
        for k, n in content.items():
            stock[k] -= n * alike
            if not stock[k]:
                del stock[k]
        out.append((content, alike))
    return out


def places(bins: list[tuple[dict[int, int], int]]) -> tuple[dict[int, np.ndarray], int]:
    """For each length, rows of (first number, in each bin, first sequence, offset); the number of sequences."""
    rows: dict[int, list[tuple[int, int, int, int]]] = {}
    used: dict[int, int] = {}
    sequence = 0
    for content, alike in bins:
        offset = 0
        for length in sorted(content, reverse=True):
            rows.setdefault(length, []).append((used.get(length, 0), content[length], sequence, offset))
            used[length] = used.get(length, 0) + content[length] * alike
            offset += length * content[length]
        sequence += alike
    return {k: np.array(v, np.int64) for k, v in rows.items()}, sequence


_PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long, run int, number long"


def _cut_batches(capacity: int, with_ids: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get().partitionId()
        end = np.array([byte_bpe.END], "<u4").tobytes()
        seen = np.zeros(capacity + 1, np.int64)
        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
            for at in range(0, len(ids), SLICE):
                rows, parts = [], []
                for doc, raw in zip(ids[at : at + SLICE], byte_bpe.token_bytes_of(texts[at : at + SLICE]), strict=True):
                    raw += end
                    n = len(raw) // 4
                    bounds = [0, *range(n - capacity * ((n - 1) // capacity), n + 1, capacity)]
                    for piece, (a, b) in enumerate(zip(bounds, bounds[1:], strict=False)):
                        part = raw[4 * a : 4 * b]
                        rows.append((doc, piece, a, b - a, crc32(part), task, int(seen[b - a])))
                        seen[b - a] += 1
                        parts.append(part)
                if rows:
                    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
                    arrays = [pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)]
                    names = [x.split()[0] for x in _PIECE.split(", ")]
                    if with_ids:
                        arrays, names = [*arrays, pa.array(parts, pa.binary())], [*names, "ids"]
                    yield pa.RecordBatch.from_arrays(arrays, names)

    return run


def pieces(docs: DataFrame, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Pieces of every row, as a stored table; `number` counts those of equal length in the task `run`."""
    ship(docs.sparkSession)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return cut(plain.mapInArrow(released(_cut_batches(capacity, with_ids)), _PIECE + ", ids binary" * with_ids))


def _placed_batches(table: dict[int, np.ndarray]):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length = batch.column("length").to_numpy(zero_copy_only=False)
            number = batch.column("number").to_numpy(zero_copy_only=False)
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            order = np.argsort(length, kind="stable")
            for rows in np.split(order, np.flatnonzero(np.diff(length[order])) + 1) if len(order) else []:
                n = int(length[rows[0]])
                bins = table[n]
                at = np.searchsorted(bins[:, 0], number[rows], "right") - 1
                beyond = number[rows] - bins[at, 0]
                sequence[rows] = bins[at, 2] + beyond // bins[at, 1]
                offset[rows] = bins[at, 3] + beyond % bins[at, 1] * n
            kept = [batch.column(c) for c in batch.schema.names if c != "number"]
            names = [c for c in batch.schema.names if c != "number"]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) of every piece, and its `ids` if asked for."""
    every = pieces(docs, capacity, with_ids)
    kinds = ["doc_id", "piece", "start", "length", "ids_crc32", *["ids"] * with_ids]
    full = every.where(F.col("length") == capacity).select(*kinds, (-1 - F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    short = every.where(F.col("length") < capacity)
    by_run = cut(short.groupBy("run", "length").count())
    stock = {r["length"]: r["n"] for r in by_run.groupBy("length").agg(F.sum("count").alias("n")).collect()}  # fewer rows than `capacity`
    table, _ = places(plan(stock, capacity))
    before = Window.partitionBy("length").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    first = by_run.select("run", "length", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    numbered = short.join(first, ["run", "length"]).select(*kinds, (F.col("number") + F.col("first")).alias("number"))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids + ", sequence_id long, offset long"
    return numbered.mapInArrow(released(_placed_batches(table)), schema).unionByName(full)


def sequences(docs: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """(sequence_id, n_tokens, ids binary: little-endian unsigned 32-bit, documents array) of every sequence."""
    parts = pack(docs, capacity, with_ids=True).groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "doc_id", "piece", "ids"))).alias("p"))
    joined = F.aggregate("p", F.lit("").cast("binary"), lambda a, x: F.concat(a, x["ids"]))
    return parts.select("sequence_id", (F.octet_length(joined) / 4).cast("long").alias("n_tokens"), joined.alias("ids"), F.transform("p", lambda x: F.struct(x["doc_id"].alias("doc_id"), x["piece"].alias("piece"), x["offset"].alias("offset"))).alias("documents"))
