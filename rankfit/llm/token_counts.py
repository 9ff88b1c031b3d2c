"""Exact token counts at every prefix of a text, stored once and asked many times.

A text's table holds, for each character, by how much it changes the token count of the prefix it ends; running sums
give the exact count at every prefix, with no further encoding for budgets, truncation or limits. Tables of repeated
chunks come from a cache; a chunk's own is found by dynamic programming (see `byte_bpe`).

Defined results: a null or empty text has an empty table and no tokens. Special strings inside texts count as the
library counts them by default. Repeated rows each give a row; null ids are carried; extra columns are ignored. An
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from rankfit.llm import byte_bpe
from rankfit.llm.rows import released
from rankfit.session import ship

LIMIT, SLICE = 1024, 2048


def counts(steps: bytes) -> np.ndarray:
    """Token counts of every prefix, the empty one first."""
    return np.concatenate(([0], np.cumsum(np.frombuffer(steps, "<i4").astype(np.int64))))


def count_of_prefix(steps: bytes, characters: int) -> int:
    """Tokens of the first `characters` of the text."""
    return int(np.frombuffer(steps, "<i4", count=min(characters, len(steps) // 4)).astype(np.int64).sum())


def longest_within(steps: bytes, budget: int) -> int:
    """Characters of the longest prefix of at most `budget` tokens."""
    return int(np.flatnonzero(counts(steps) <= budget)[-1]) if budget >= 0 else 0


def _plain(docs: DataFrame) -> DataFrame:
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def prefix_tables(docs: DataFrame) -> DataFrame:
    """(doc_id, steps binary) of every row."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for at in range(0, len(texts), 256):
                tables = pa.array(byte_bpe.prefix_steps_of(texts[at : at + 256]), pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(at, 256), tables], ["doc_id", "steps"])

    return _plain(docs).mapInArrow(released(run), "doc_id long, steps binary")


def token_counts(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every row, read off each text's table."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            size = pa.array([0 if t is None else len(t.encode()) for t in texts], pa.int64())
            steps = (x for at in range(0, len(texts), SLICE) for x in byte_bpe.prefix_steps_of(texts[at : at + SLICE]))
            tokens = [int(np.frombuffer(x, "<i4").sum(dtype=np.int64)) for x in steps]
            over = pa.array([n > limit for n in tokens], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), size, pa.array(tokens, pa.int64()), over], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return _plain(docs).mapInArrow(released(run), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
