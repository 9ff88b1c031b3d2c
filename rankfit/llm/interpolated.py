"""Language-model scoring by deleted interpolation.

The model mixes maximum-likelihood estimates of a word given the word before it, of the word alone, and a uniform one
over the training words and one more. The mixture's weights depend on a bucket of the context's frequency and are
learned by expectation-maximisation on the words of held-out training documents (a slice of the training fold), whose
counts are kept out of the estimates while the weights are learned and join them afterwards.

Texts are read once. A task numbers the words of about `batch_tokens` tokens and stores them as one row, a batch.
From each batch goes one sorted list of its distinct n-grams (64-bit hashes) with counts, cut by hash range into
parts; a part's task adds up what all batches send it and answers each batch with the corpus counts of what it asked
for, in the same order. So what moves grows with the distinct n-grams of the batches, no task holds a table of the
whole corpus, and a frequent n-gram is one number for each batch. Batches and answers then meet by batch.

The weights come from a histogram of held-out words by context bucket and both estimates on a fixed logarithmic grid.

Defined results: a null or word-less text is its end token. A null id is in the training fold. Repeated rows each
count and each give a row. Extra columns are ignored. An empty table gives an empty result; with an empty training
fold the uniform estimate alone gives the score.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from math import ceil

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame, functions as F

from rankfit.llm.rows import released
from rankfit.session import cut, drop_table, new_table, ship

FOLDS, TEST, SLICE = 7, 2, 0
BATCH_TOKENS, GRAMS_IN_PART = 1 << 20, 1 << 21
CONTEXT_BUCKETS, GRID, ROUNDS, LEAST_WEIGHT = 32, 16, 60, 1e-4

_END, _BEGIN = np.uint64(0x1D8AF066D1C4A5B2), np.uint64(0x6C62272E07BB0142)
_odd, _mix = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_one = np.uint64(1)


def fold(doc_id: Column) -> Column:
    """0: learned from; 1: held out for the weights; 2: not learned from."""
    rest = F.crc32(doc_id.cast("string")) % FOLDS
    return F.when(rest == TEST, 2).when(rest == SLICE, 1).otherwise(0).cast("int")


# Compact arrays ----------------------------------------------------------------------------------------------------


def packed(values: np.ndarray) -> bytes:
    """Bytes of an unsigned array, place by place, compressed."""
    planes = values.view(np.uint8).reshape(len(values), values.itemsize).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes())


def unpacked(raw: bytes, kind: str) -> np.ndarray:
    width = np.dtype(kind).itemsize
    content = zstandard.ZstdDecompressor().decompress(raw)
    if not content:
        return np.zeros(0, kind)
    planes = np.frombuffer(content, np.uint8).reshape(width, -1)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def packed_sorted(values: np.ndarray) -> bytes:
    return packed(np.diff(values, prepend=np.uint64(0)))


def unpacked_sorted(raw: bytes) -> np.ndarray:
    return np.cumsum(unpacked(raw, "<u8"), dtype=np.uint64)


# Batches -----------------------------------------------------------------------------------------------------------


class Numbers(dict):
    def __missing__(self, key):
        self[key] = n = len(self)
        return n


_BATCH = "batch long, doc_ids binary, absent binary, lengths binary, folds binary, words binary, tokens binary, n_tokens long"


def _batch_row(batch: int, number: Numbers, docs: list[tuple[int | None, int, np.ndarray]]) -> pa.RecordBatch:
    hashes = np.array([xxhash.xxh64_intdigest(w) for w in number], np.uint64)
    ids = np.array([d or 0 for d, _, _ in docs], np.int64).view(np.uint64)
    absent = np.array([d is None for d, _, _ in docs], np.uint8)
    lengths = np.array([len(t) for _, _, t in docs], np.uint32)
    folds = np.array([f for _, f, _ in docs], np.uint8)
    tokens = np.concatenate([t for _, _, t in docs]).astype(np.uint32)
    columns = [pa.array([batch]), *(pa.array([packed(x)], pa.binary()) for x in (ids, absent, lengths, folds, hashes, tokens)), pa.array([len(tokens) + len(docs)])]
    return pa.RecordBatch.from_arrays(columns, [x.split()[0] for x in _BATCH.split(", ")])


def _batch_batches(batch_tokens: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        first = TaskContext.get().partitionId() << 32
        # The slice's documents have batches of their own, so that learning the weights reads no others.
        open_ones = {sliced: [first, Numbers(), [], 0] for sliced in (True, False)}

        def stored(sliced: bool) -> pa.RecordBatch:
            batch, number, docs, _ = open_ones[sliced]
            open_ones[sliced] = [batch + 1, Numbers(), [], 0]
            return _batch_row(batch if sliced else -1 - batch, number, docs)

        for rows in batches:
            for doc, part, text in zip(*(rows.column(c).to_pylist() for c in ("doc_id", "fold", "text")), strict=True):
                own = open_ones[part == 1]
                number = own[1]
                tokens = np.array([number[w] for w in (text or b"").lower().split()], np.uint32)
                own[2].append((doc, part, tokens))
                own[3] += len(tokens) + 1
                if own[3] >= batch_tokens:
                    yield stored(part == 1)
        for sliced in (True, False):
            if open_ones[sliced][2]:
                yield stored(sliced)

    return run


class Batch:
    """A stored batch: its tokens' n-grams, and where each stands in the sorted list of distinct ones."""

    def __init__(self, row: dict):
        self.ids, self.absent = unpacked(row["doc_ids"], "<u8").view(np.int64), unpacked(row["absent"], "u1").astype(bool)
        lengths, folds = unpacked(row["lengths"], "<u4").astype(np.int64), unpacked(row["folds"], "u1")
        words, tokens = unpacked(row["words"], "<u8"), unpacked(row["tokens"], "<u4")
        hashes = np.concatenate([words, [_END]]) & ~_one
        ends = np.cumsum(lengths + 1) - 1
        inside = np.ones(ends[-1] + 1, bool)
        inside[ends] = False
        at = np.full(len(inside), len(words), np.int64)
        at[inside] = tokens
        self.starts = ends - lengths
        before = np.concatenate(([len(words) + 1], at[:-1]))
        before[self.starts] = len(words) + 1
        self.folds = np.repeat(folds, lengths + 1)
        pair, self.pair_of = np.unique(before * (len(words) + 2) + at, return_inverse=True)
        first, second = pair // (len(words) + 2), pair % (len(words) + 2)
        contexts = np.concatenate([hashes, [_BEGIN & ~_one]])
        mixed = contexts[first] * _odd + hashes[second]
        mixed = ((mixed ^ (mixed >> np.uint64(29))) * _mix) | _one
        # A word's own count, and its count as a context: of the tokens that follow it.
        asked = np.concatenate([contexts, mixed])
        self.grams, place = np.unique(asked, return_inverse=True)
        self.word_at, self.pair_at = place[: len(contexts)], place[len(contexts) :]
        self.first, self.second, self.token = first, second, at

    def counts(self) -> tuple[np.ndarray, np.ndarray]:
        """How often each distinct n-gram stands in the documents learned from, and in those of the slice."""
        out = []
        for fold_number in (0, 1):
            own = self.folds == fold_number
            pairs = np.bincount(self.pair_of[own], minlength=len(self.first))
            words = np.bincount(self.token[own], minlength=len(self.word_at))
            words[-1] = np.count_nonzero(own[self.starts])  # texts that begin
            counted = np.zeros(len(self.grams), np.int64)
            np.add.at(counted, self.word_at, words)
            np.add.at(counted, self.pair_at, pairs)
            out.append(counted.astype(np.uint32))
        return out[0], out[1]


_ASK = "batch long, part int, grams binary, learned binary, sliced binary"


def _ask_batches(parts: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        width = (1 << 64) // parts + 1
        bounds = np.array([i * width for i in range(1, parts)], np.uint64)
        for rows in batches:
            for row in rows.to_pylist():
                batch = Batch(row)
                learned, sliced = batch.counts()
                places = [0, *np.searchsorted(batch.grams, bounds, "left").tolist(), len(batch.grams)]
                blobs = [(p, packed_sorted(batch.grams[a:b]), packed(learned[a:b]), packed(sliced[a:b])) for p, (a, b) in enumerate(zip(places, places[1:], strict=False))]
                columns = [pa.array([row["batch"]] * parts), *(pa.array(x, k) for x, k in zip(zip(*blobs, strict=True), (pa.int32(), pa.binary(), pa.binary(), pa.binary()), strict=True))]
                yield pa.RecordBatch.from_arrays(columns, ["batch", "part", "grams", "learned", "sliced"])

    return run


_ANSWER = "batch long, part int, learned binary, sliced binary, kinds long, kinds_learned long"


def _answers(table: pa.Table) -> pa.Table:
    rows = table.to_pylist()
    grams = [unpacked_sorted(r["grams"]) for r in rows]
    every, place = np.unique(np.concatenate(grams), return_inverse=True)
    sums = []
    for name in ("learned", "sliced"):
        total = np.zeros(len(every), np.int64)
        np.add.at(total, place, np.concatenate([unpacked(r[name], "<u4") for r in rows]).astype(np.int64))
        sums.append(total)
    words = ((every & _one) == 0) & (every != (_BEGIN & ~_one))
    kinds, kinds_learned = int(np.count_nonzero(words & (sums[0] + sums[1] > 0))), int(np.count_nonzero(words & (sums[0] > 0)))
    out, at = [], 0
    for i, (r, g) in enumerate(zip(rows, grams, strict=True)):
        own = place[at : at + len(g)]
        at += len(g)
        out.append((r["batch"], r["part"], packed(sums[0][own].astype(np.uint64)), packed(sums[1][own].astype(np.uint64)), kinds if not i else 0, kinds_learned if not i else 0))
    kinds_of = (pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64())
    return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(zip(*out, strict=True), kinds_of, strict=True)], names=[x.split()[0] for x in _ANSWER.split(", ")])


# Estimates ---------------------------------------------------------------------------------------------------------


def bucket(context: np.ndarray) -> np.ndarray:
    """Bucket of a context's frequency: unseen, then by powers of two."""
    return np.where(context > 0, np.minimum(np.floor(np.log2(np.maximum(context, 1))).astype(np.int64) + 1, CONTEXT_BUCKETS - 1), 0)


class Answered:
    """A batch and the corpus counts of its n-grams."""

    def __init__(self, row: dict, answers: list[dict], with_slice: bool):
        self.batch = batch = Batch(row)
        ordered = sorted(answers, key=lambda r: r["part"])
        learned = np.concatenate([unpacked(r["learned"], "<u8") for r in ordered]).astype(np.int64)
        if with_slice:
            learned = learned + np.concatenate([unpacked(r["sliced"], "<u8") for r in ordered]).astype(np.int64)
        word = learned[batch.word_at]
        self.pair, self.context, self.word = learned[batch.pair_at], word[batch.first], word[batch.second]
        self.word_of_token = word[batch.token]


def _tables(left: pa.Table, right: pa.Table) -> tuple[dict, list[dict]] | None:
    return (left.to_pylist()[0], right.to_pylist()) if left.num_rows and right.num_rows else None


def _histogram(tokens: int):
    """Of a batch's held-out words: (bucket, log grid of both estimates, or -1 for zero, how many)."""

    def grid(p: np.ndarray) -> np.ndarray:
        return np.where(p > 0, np.round(-GRID * np.log10(np.maximum(p, 1e-300))).astype(np.int64), -1)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        found = np.zeros((0, 4), np.int64)
        if both := _tables(left, right):
            a = Answered(*both, with_slice=False)
            own = np.bincount(a.batch.pair_of[a.batch.folds == 1], minlength=len(a.pair))
            some = own > 0
            key = np.stack([bucket(a.context), grid(a.pair / np.maximum(a.context, 1)), grid(a.word / max(tokens, 1))], 1)[some]
            cells, at = np.unique(key, axis=0, return_inverse=True)
            found = np.column_stack([cells, np.bincount(at.ravel(), weights=own[some], minlength=len(cells)).astype(np.int64)]) if len(key) else found
        return pa.Table.from_arrays([pa.array(x) for x in found.T.copy()] if len(found) else [pa.array([], pa.int64())] * 4, names=["b", "p2", "p1", "n"])

    return run


def weights(cells: np.ndarray, kinds: int, rounds: int = ROUNDS) -> np.ndarray:
    """Mixture weights (pair, word, uniform) of each context bucket, by expectation-maximisation."""
    out = np.tile([0.4, 0.5, 0.1], (CONTEXT_BUCKETS, 1))
    out[0] = [0.0, 0.9, 0.1]
    if len(cells):
        estimate = np.column_stack([np.where(cells[:, 1:3] >= 0, 10.0 ** (-cells[:, 1:3] / GRID), 0.0), np.full(len(cells), 1.0 / (kinds + 1))])
        for _ in range(rounds):
            share = out[cells[:, 0]] * estimate
            share *= (cells[:, 3] / np.maximum(share.sum(1), 1e-300))[:, None]
            sums = np.zeros_like(out)
            np.add.at(sums, cells[:, 0], share)
            # A bucket with few words leans on what it began with.
            out = (sums + 5 * out) / (sums.sum(1) + 5)[:, None]
    out = np.maximum(out, [0.0, LEAST_WEIGHT, LEAST_WEIGHT])
    out[0, 0] = 0.0
    return out / out.sum(1, keepdims=True)


_SCORE = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double"


def _scored(table: np.ndarray, tokens: int, kinds: int):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        names = [x.split()[0] for x in _SCORE.split(", ")]
        types = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
        if not (both := _tables(left, right)):
            return pa.Table.from_arrays([pa.array([], k) for k in types], names=names)
        a = Answered(*both, with_slice=True)
        mix = table[bucket(a.context)]
        p = mix[:, 0] * a.pair / np.maximum(a.context, 1) + mix[:, 1] * a.word / max(tokens, 1) + mix[:, 2] / (kinds + 1)
        starts = a.batch.starts
        score = np.add.reduceat(np.log10(p)[a.batch.pair_of], starts)
        base = np.add.reduceat(np.log10((a.word_of_token + 1) / (tokens + kinds + 1)), starts)
        known = np.add.reduceat((a.word_of_token > 0).astype(np.int64), starts)
        size = np.diff(np.append(starts, len(a.batch.token)))
        ids = pa.array(a.batch.ids, pa.int64(), mask=a.batch.absent)
        return pa.Table.from_arrays([ids, pa.array(a.batch.folds[starts] == 2), pa.array(size), pa.array(known), pa.array(base), pa.array(score)], names=names)

    return run


def scored(docs: DataFrame, batch_tokens: int = BATCH_TOKENS, grams_in_part: int = GRAMS_IN_PART) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row, as a stored table."""
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(fold(F.col("doc_id")), F.lit(0)).alias("fold"), F.col("text").cast("binary").alias("text"))
    path = new_table(spark, "batches")
    rows.mapInArrow(released(_batch_batches(batch_tokens)), _BATCH).write.parquet(path)
    batches = spark.read.schema(_BATCH).parquet(path)
    total = batches.agg(F.sum("n_tokens")).first()[0] or 0
    parts = max(1, ceil(total / grams_in_part))
    asked = batches.drop("n_tokens").mapInArrow(released(_ask_batches(parts)), _ASK)
    answers = cut(asked.groupBy("part").applyInArrow(_answers, _ANSWER))
    kinds, kinds_learned = (answers.agg(F.sum("kinds"), F.sum("kinds_learned")).first()) if total else (0, 0)
    kinds, kinds_learned = kinds or 0, kinds_learned or 0
    by_fold = {r["fold"]: r["n"] for r in _fold_tokens(batches).groupBy("fold").agg(F.sum("n").alias("n")).collect()}
    learned, train = by_fold.get(0, 0), by_fold.get(0, 0) + by_fold.get(1, 0)
    given = answers.select("batch", "part", "learned", "sliced")
    plain = batches.drop("n_tokens")
    sliced = plain.where("batch >= 0").groupBy("batch")
    cells = sliced.cogroup(given.where("batch >= 0").groupBy("batch")).applyInArrow(_histogram(learned), "b long, p2 long, p1 long, n long")
    found = cells.groupBy("b", "p2", "p1").agg(F.sum("n").alias("n")).toPandas().to_numpy(np.int64)  # the grid bounds its rows
    table = weights(found, kinds_learned)
    out = cut(plain.groupBy("batch").cogroup(given.groupBy("batch")).applyInArrow(_scored(table, train, kinds), _SCORE))
    drop_table(spark, path)
    return out.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(train).cast("long").alias("train_tokens"), "base_score", "score")


def _fold_tokens(batches: DataFrame) -> DataFrame:
    def run(rows: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in rows:
            for lengths, folds in zip(part.column("lengths").to_pylist(), part.column("folds").to_pylist(), strict=True):
                n = np.bincount(unpacked(folds, "u1"), weights=unpacked(lengths, "<u4").astype(np.int64) + 1, minlength=3).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([0, 1, 2]), pa.array(n)], ["fold", "n"])

    return batches.select("lengths", "folds").mapInArrow(released(run), "fold long, n long")
