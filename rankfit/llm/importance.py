"""Quality classification by importance resampling.

Two generative models over hashed n-grams, one of target text (labelled good and not toxic) and one of all raw text,
give each document the log of its likelihood ratio. The n-grams are words, pairs of words and pairs of word shapes (a
shape keeps case, digits and marks, and says whether a word repeats the one before), each family with hash buckets of
its own; a document draws a bucket or doesn't, so a text that repeats one n-gram a thousand times tells no more of it
than another. Raw counts cover every document; target counts come from about `labelled_rows` labelled documents, kept
apart in `FOLDS` folds by the text's hash. A labelled document is scored by a model of the other folds, never by one
that counted its text, so that its log ratio is what it would be without the label; all others by the model of all folds.
Raw counts are scaled to the target's number of n-grams and both models add the same pseudo-count. A bucket whose two
rates differ by less than `least_effect` or `least_errors` standard errors isn't evidence: the target model gives all
such buckets the raw model's rates, times what makes its own rates sum to one. So both are normalised, and what they say
alike doesn't add up over a long text.

Documents are then sampled without replacement by Gumbel top-k: log ratio over `temperature` (1: in proportion to the
ratio of the models) plus a Gumbel draw that hangs on id and text alone; the k largest stay. k can be given, as a number
(`k`) or share (`share`) of the rows. By default it is the number of keys at or above the place that best parts labelled
good rows from bad ones while the sample loses at most `lose` of the good: by their held-out ratios, and with each
row's chance to be lost under the draw, not its one draw. The k-th largest key is found by repeated histograms, so no
sort of all documents is needed.

Defined results: null and word-less texts have log ratio zero and are drawn like any other. Rows with equal keys (same
id, if any, and text) stay or go together. Without labels of both kinds the place is `DEFAULT_THRESHOLD`, which without
good ones, where all log ratios are zero, no draw in 10^8 misses. Extra columns are ignored by `sampled` and carried by `accepted`. An empty table gives an empty result.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from rankfit.llm.rows import hashed_sample, keep_rows, released, text_hash
from rankfit.session import cut, ship

WORD_BITS, PAIR_BITS, SHAPE_BITS, BLOCK_BITS = 20, 18, 16, 16
LABELLED_ROWS, PSEUDO, LEAST_EFFECT, LEAST_ERRORS, TEMPERATURE, LOSE, DEFAULT_THRESHOLD, SEED = 20_000, 3.0, 0.7, 5.0, 1.0, 0.005, -3.0, 17
FOLDS, FAN_IN = 5, 64

FAMILIES = (0, 1 << WORD_BITS, (1 << WORD_BITS) + (1 << PAIR_BITS))
BUCKETS = FAMILIES[2] + (1 << SHAPE_BITS)

_kinds = bytes(65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 48 if 48 <= b <= 57 else b for b in range(256))
_around = bytes(b for b in range(33, 127) if not chr(b).isalnum())
_runs = re.compile(rb"(.)\1+", re.S)
_odd, _mix = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def _mixed(x: np.ndarray, bits: int) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _mix
    return (x >> np.uint64(64 - bits)).astype(np.int64)


class Numbers(dict):
    """Numbers in order of first sight."""

    def __missing__(self, key):
        self[key] = n = len(self)
        return n


class Features:
    """Hash buckets of texts; what is known of a word is kept while few enough words are."""

    def __init__(self, bound: int = 250_000):
        self.bound = bound
        self.clear()

    def clear(self) -> None:
        self.number, self.words, self.shapes = Numbers(), np.zeros(0, np.uint64), np.zeros(0, np.uint64)

    def __call__(self, raw: bytes | None) -> np.ndarray:
        words = (raw or b"").split()
        if not words:
            return np.zeros(0, np.int64)
        if len(self.number) > self.bound:
            self.clear()
        known = len(self.number)
        ids = np.array([self.number[w] for w in words], np.int64)
        if len(self.number) > known:
            new = list(self.number)[known:] if known < len(self.number) // 2 else [w for w in dict.fromkeys(words) if self.number[w] >= known]
            hashes = np.array([xxhash.xxh64_intdigest(w.lower().strip(_around) or w) for w in new], np.uint64)
            shapes = np.array([xxhash.xxh64_intdigest(_runs.sub(rb"\1", w.translate(_kinds))) for w in new], np.uint64)
            self.words, self.shapes = self._grown(self.words, known, hashes), self._grown(self.shapes, known, shapes)
        word, shape = self.words[ids], self.shapes[ids]
        out = [_mixed(word, WORD_BITS)]
        if len(ids) > 1:
            same = (ids[1:] == ids[:-1]).astype(np.uint64)
            out.append(_mixed(word[:-1] * _odd + word[1:], PAIR_BITS) + FAMILIES[1])
            out.append(_mixed((shape[:-1] * _odd + shape[1:]) * np.uint64(2) + same, SHAPE_BITS) + FAMILIES[2])
        return np.unique(np.concatenate(out))

    @staticmethod
    def _grown(old: np.ndarray, n: int, new: np.ndarray) -> np.ndarray:
        if n + len(new) > len(old):
            old = np.concatenate([old[:n], np.zeros(max(1024, n + 2 * len(new)), np.uint64)])
        old[n : n + len(new)] = new
        return old


_BLOB = "block int, part int, raw binary, target binary"


def _blobs(raw: np.ndarray, target: np.ndarray, part: int) -> Iterator[pa.RecordBatch]:
    step = 1 << BLOCK_BITS
    pack = lambda x: zlib.compress(x.astype("<i8").tobytes(), 1)
    for block in range(-(-(BUCKETS + 1) // step)):
        own = slice(block * step, (block + 1) * step)
        if raw[own].any() or target[:, own].any():
            columns = [pa.array([block], pa.int32()), pa.array([part], pa.int32()), pa.array([pack(raw[own])]), pa.array([pack(target[:, own])])]
            yield pa.RecordBatch.from_arrays(columns, ["block", "part", "raw", "target"])


def _count_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    raw, target, features = np.zeros(BUCKETS + 1, np.int32), np.zeros((FOLDS, BUCKETS + 1), np.int32), Features()
    for batch in batches:
        for text, fold in zip(batch.column("text").to_pylist(), batch.column("fold").to_pylist(), strict=True):
            found = np.append(features(text), BUCKETS)
            raw[found] += 1
            if fold is not None:
                target[fold, found] += 1
    yield from _blobs(raw, target, TaskContext.get().partitionId())


def _sum_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums: dict[int, list] = {}
    unpack = lambda x: np.frombuffer(zlib.decompress(x), "<i8").astype(np.int64)
    part = 0
    for batch in batches:
        for block, part, raw, target in zip(*(batch.column(c).to_pylist() for c in ("block", "part", "raw", "target")), strict=True):  # noqa: B007
            both = sums.setdefault(block, [0, 0])
            both[0], both[1] = both[0] + unpack(raw), both[1] + unpack(target)
    for block, (raw, target) in sums.items():
        columns = [pa.array([x], k) for x, k in ((block, pa.int32()), (part, pa.int32()), (zlib.compress(raw.astype("<i8").tobytes(), 1), pa.binary()), (zlib.compress(target.astype("<i8").tobytes(), 1), pa.binary()))]
        yield pa.RecordBatch.from_arrays(columns, ["block", "part", "raw", "target"])


def _chosen(labels: DataFrame, bound: int, seed: int) -> DataFrame:
    """About `bound` labelled ids by hash: (label_id, good), good if every label of the id says so."""
    good = (F.col("quality") == 1) & (F.coalesce(F.col("toxic"), F.lit(0)) == 0)
    each = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("label_id")).agg(F.min(good.cast("int")).alias("good"))
    return cut(hashed_sample(cut(each), bound, seed, "label_id"))


def _fold() -> Column:
    """The fold of a text; equal texts share it."""
    return F.pmod(F.xxhash64(F.lit(SEED + 2), "text"), F.lit(FOLDS)).cast("int").alias("fold")


def learn(docs: DataFrame, chosen: DataFrame, pseudo: float = PSEUDO, least_effect: float = LEAST_EFFECT, least_errors: float = LEAST_ERRORS) -> np.ndarray:
    """Log ratios of target to raw of every hash bucket, a row for all folds but each and a last one for all of them."""
    good = F.broadcast(chosen.where("good = 1").select("label_id"))
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("binary").alias("text"), _fold())
    marked = rows.join(good, F.col("id") == F.col("label_id"), "left").select("text", F.when(F.col("label_id").isNotNull(), F.col("fold")).alias("fold"))
    counted = marked.mapInArrow(released(_count_batches), _BLOB)
    # A tree: each round sums the tables of `FAN_IN` tasks; a task holds one sum for each block it meets.
    parts, some = rows.rdd.getNumPartitions(), counted
    while True:
        parts = -(-parts // FAN_IN)
        some = some.withColumn("part", F.floor(F.col("part") / FAN_IN).cast("int")).repartition("block", "part").mapInArrow(released(_sum_batches), _BLOB)
        if parts <= FAN_IN:
            break
    raw, target = np.zeros(BUCKETS + 1, np.int64), np.zeros((FOLDS, BUCKETS + 1), np.int64)
    for row in some.repartition("block").mapInArrow(released(_sum_batches), _BLOB).collect():  # one row for each block
        own = slice(row["block"] << BLOCK_BITS, (row["block"] + 1) << BLOCK_BITS)
        raw[own] += np.frombuffer(zlib.decompress(row["raw"]), "<i8")
        target[:, own] += np.frombuffer(zlib.decompress(row["target"]), "<i8").reshape(FOLDS, -1)
    whole = target.sum(0)
    return np.array([log_ratio(raw, whole - part, pseudo, least_effect, least_errors) for part in (*target, np.zeros_like(whole))])


def log_ratio(raw: np.ndarray, target: np.ndarray, pseudo: float = PSEUDO, least_effect: float = LEAST_EFFECT, least_errors: float = LEAST_ERRORS) -> np.ndarray:
    """Log of the target's rate over the raw one of every bucket, from numbers of documents with each (last: of all)."""
    raw, own = raw[:-1].astype(float), target[:-1].astype(float)
    if not own.sum() or not raw.sum():
        return np.zeros(len(raw), np.float32)
    expected = raw * (own.sum() / raw.sum())
    ratio = np.log((own + pseudo) / (expected + pseudo))
    clear = (np.abs(ratio) >= least_effect) & (np.abs(own - expected) >= least_errors * np.sqrt(np.minimum(own, expected) + pseudo / 4))
    every = own.sum() + pseudo * len(own)
    rest = np.log((every - (own[clear] + pseudo).sum()) / (every - (expected[clear] + pseudo).sum())) if not clear.all() else 0.0
    return np.where(clear, ratio, rest).astype(np.float32)


def log_weights(docs: DataFrame, ratios: np.ndarray, chosen: DataFrame) -> DataFrame:
    """(doc_id, text_hash, n_features, log_ratio) of every row, those of `chosen` held out, as a stored table."""
    shared = docs.sparkSession.sparkContext.broadcast(ratios)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables, features = shared.value, Features()
        for batch in batches:
            found = [features(t) for t in batch.column("text").to_pylist()]
            columns = [pa.array([len(f) for f in found], pa.int64()), pa.array([float(tables[k, f].sum(dtype=np.float64)) for k, f in zip(batch.column("fold").to_pylist(), found, strict=True)], pa.float64())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_hash"), *columns], ["doc_id", "text_hash", "n_features", "log_ratio"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_hash(), F.col("text").cast("binary").alias("text"), _fold())
    labelled = F.broadcast(chosen.select("label_id"))
    rows = rows.join(labelled, F.col("doc_id") == F.col("label_id"), "left").withColumn("fold", F.when(F.col("label_id").isNotNull(), F.col("fold")).otherwise(FOLDS))
    return cut(rows.select("doc_id", "text_hash", "text", "fold").mapInArrow(released(run), "doc_id long, text_hash long, n_features long, log_ratio double"))


def threshold(weights: DataFrame, chosen: DataFrame, lose: float = LOSE, temperature: float = TEMPERATURE, bound: int = LABELLED_ROWS, seed: int = SEED) -> float:
    """The key at which a sample parts labelled good rows best from bad ones, from their held-out log ratios."""
    labelled = cut(weights.join(F.broadcast(chosen), F.col("doc_id") == F.col("label_id")).select("label_id", "text_hash", "log_ratio", "good"))
    found = hashed_sample(labelled, 2 * bound, seed + 3, "label_id", "text_hash").select("log_ratio", "good").toPandas()
    good, bad = (np.sort(found["log_ratio"][found["good"] == g].to_numpy()) / temperature for g in (1, 0))
    if len(good) < 5 or len(bad) < 5:
        return DEFAULT_THRESHOLD / temperature
    places = np.unique(np.concatenate([good, bad, [good[0] - 8]]))
    if len(places) > 2000:
        places = np.quantile(places, np.linspace(0, 1, 2000))

    def lost(rows: np.ndarray) -> np.ndarray:
        """The mean chance that ratio and draw together stay below each place."""
        with np.errstate(over="ignore", under="ignore"):
            return np.array([np.exp(-np.exp(rows - p)).mean() for p in places])

    of_good, of_bad = lost(good), lost(bad)
    allowed = of_good <= max(lose, of_good[0])
    return float(places[allowed][np.argmax((of_bad - of_good)[allowed])])


def kth_largest(rows: DataFrame, column: str, k: int, at_once: int = 4096) -> float:
    """The k-th largest value of a stored table's column, by histograms of an ever smaller range."""
    low, high = rows.agg(F.min(column), F.max(column)).first()
    while True:
        inside = rows.where((F.col(column) >= low) & (F.col(column) <= high))
        if inside.limit(at_once + 1).count() <= at_once or low == high:
            values = sorted((r[0] for r in inside.select(column).distinct().collect()), reverse=True) if low != high else [low]
            tally = {r[0]: r[1] for r in inside.groupBy(column).count().collect()} if low != high else {}
            for v in values:
                k -= tally.get(v, k)
                if k <= 0:
                    return v
            return values[-1]
        place = F.floor((F.col(column) - low) / F.lit((high - low) / at_once)).cast("int")
        bins = inside.groupBy(F.least(place, F.lit(at_once - 1)).alias("b")).agg(F.count("*").alias("n"), F.min(column).alias("low"), F.max(column).alias("high"))
        for b in sorted(bins.collect(), key=lambda r: -r["b"]):
            if b["n"] >= k:
                low, high = b["low"], b["high"]
                break
            k -= b["n"]


def sampled(docs: DataFrame, labels: DataFrame, labelled_rows: int = LABELLED_ROWS, temperature: float = TEMPERATURE, lose: float = LOSE, k: int | None = None, share: float | None = None, seed: int = SEED) -> DataFrame:
    """(doc_id, text_hash, n_features, log_ratio, sample_key, kept) of every row of `docs`."""
    ship(docs.sparkSession)
    chosen = _chosen(labels, labelled_rows, seed)
    weights = log_weights(docs, learn(docs, chosen), chosen)
    uniform = (F.shiftrightunsigned(F.xxhash64(F.lit(seed + 1), "doc_id", "text_hash"), 11).cast("double") + 0.5) / float(1 << 53)
    keyed = cut(weights.withColumn("sample_key", F.col("log_ratio") / temperature - F.log(-F.log(uniform))))
    if share is not None:
        k = round(share * keyed.count())
    elif k is None:
        k = keyed.where(F.col("sample_key") >= threshold(weights, chosen, lose, temperature, labelled_rows, seed)).count()
    cut_at = kth_largest(keyed, "sample_key", min(k, keyed.count())) if k else float("inf")
    return keyed.withColumn("kept", F.col("sample_key") >= cut_at)


def accepted(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of `docs`, all columns, that the sample keeps."""
    kept = sampled(docs, labels, **options).where("kept").select("doc_id", "text_hash", F.lit(False).alias("single"))
    return keep_rows(docs, cut(kept.distinct()))
