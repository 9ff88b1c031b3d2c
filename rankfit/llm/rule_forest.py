"""Quality rules judged by an isolation forest.

One pass over whole texts counts the rule statistics. The forest is grown on `trees` * `rows_in_tree` rows of shares
made from them (about so many different ones, by hash of the id and the statistics, a documented bound): random splits isolate odd rows after
few steps, so a short mean path means an odd document. That each tree is grown on few rows drawn from all is the method. The threshold
is the smallest score that all but `lose` of the labelled good rows don't exceed, over all of them (of fewer than
`LEAST_LABELLED`, `DEFAULT_THRESHOLD`). Shares are
shrunk toward zero by a few words' worth, so that short texts aren't odd for being short. Small trees tell clusters of
junk from the rest better than large ones, and rules that good texts break too (repeated lines, digits, long words)
have no share: they would hide the others.

Defined results: a null or word-less text has no words and fails the base rule. Null ids are judged and never
labelled. Repeated rows each give a row; several labels of an id are one if any says good. Extra columns are ignored. An empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from rankfit.llm.rows import hashed_sample, released
from rankfit.plans.exact import exact_quantiles
from rankfit.session import cut, ship

#: Fixed: the characters that count as symbols.
SYMBOLS = b"#*$%&|<>"
LEAST_WORDS, MOST_REPEATED = 50, 50
TREES, ROWS_IN_TREE, LEAST_LABELLED, LOSE, DEFAULT_THRESHOLD, SEED = 200, 64, 20, 0.005, 0.65, 7

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
SHARES = ("symbols", "upper", "marks", "repeats")

_white = np.frombuffer(b" \t\n\r\x0b\x0c", np.uint8)
_symbols = np.frombuffer(SYMBOLS, np.uint8)
_continuation = np.arange(0x80, 0xC0)
_upper, _lower = np.arange(65, 91), np.arange(97, 123)
_marks = np.array([i for i in range(33, 127) if not chr(i).isalnum() and i not in SYMBOLS])


def statistics(raw: bytes | None) -> tuple[tuple[int, ...], tuple[float, ...]]:
    """COUNTS and SHARES of one UTF-8 text."""
    raw = raw or b""
    words = raw.split()
    n = len(words)
    bytes_of = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    word_chars = int(bytes_of.sum() - bytes_of[_continuation].sum() - bytes_of[_white].sum())
    n_symbols = int(bytes_of[_symbols].sum())
    lines = [x for x in raw.split(b"\n") if x.strip()] if n else []
    n_dup_lines = len(lines) - len(set(lines))
    repeated = repeat_words(words)
    letters = bytes_of[_upper].sum() + bytes_of[_lower].sum()
    shares = (n_symbols / (word_chars + 200.0), bytes_of[_upper].sum() / (letters + 200.0), bytes_of[_marks].sum() / (word_chars + 200.0), repeated / (n + 50.0))
    return (n, word_chars, n_symbols, n_dup_lines, repeated), tuple(map(float, shares))


def repeat_words(words: list[bytes]) -> int:
    """Words that stand in a 3-word window found at least twice."""
    n = len(words)
    if n < 4:
        return 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, n)
    if len(number) == n:
        return 0
    pair = ids[:-1] * len(number) + ids[1:]
    if len(number) < 1 << 20:
        window = pair[:-1] * len(number) + ids[2:]
    else:
        window = np.unique(pair, return_inverse=True)[1][:-1] * len(number) + ids[2:]
    order = np.argsort(window, kind="stable")
    ranked = window[order]
    equal = ranked[1:] == ranked[:-1]
    if not equal.any():
        return 0
    again = order[np.concatenate((equal, [False])) | np.concatenate(([False], equal))]
    covered = np.zeros(n, bool)
    for step in range(3):
        covered[again + step] = True
    return int(covered.sum())


_STATS = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", " + ", ".join(f"{c} double" for c in SHARES)


def _stat_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [statistics(x) for x in batch.column("text").to_pylist()]
        counts = np.array([a for a, _ in found], np.int64).reshape(-1, len(COUNTS))
        shares = np.array([b for _, b in found], np.float64).reshape(-1, len(SHARES))
        arrays = [pa.array(x) for x in (*counts.T.copy(), *shares.T.copy())]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *arrays], ["doc_id", *COUNTS, *SHARES])


def rule_statistics(docs: DataFrame) -> DataFrame:
    """(doc_id, the counts, the shares) of every row, as a stored table."""
    ship(docs.sparkSession)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    return cut(plain.mapInArrow(released(_stat_batches), _STATS))


def mean_path(n: np.ndarray | float) -> np.ndarray:
    """Mean path length of an unsuccessful search among n rows."""
    n = np.asarray(n, float)
    return np.where(n > 2, 2 * (np.log(np.maximum(n - 1, 1)) + 0.5772156649015329) - 2 * (n - 1) / np.maximum(n, 1), np.where(n == 2, 1.0, 0.0))


def grow(rows: np.ndarray, trees: int = TREES, rows_in_tree: int = ROWS_IN_TREE, seed: int = SEED) -> dict[str, np.ndarray]:
    """Trees of complete levels: the split's column (-1 at a leaf), its place, and the leaf's path length."""
    random = np.random.default_rng(seed)
    psi = min(rows_in_tree, len(rows))
    depth = int(np.ceil(np.log2(max(psi, 2))))
    nodes = (1 << (depth + 1)) - 1
    column, place, path = np.full((trees, nodes), -1, np.int64), np.zeros((trees, nodes)), np.zeros((trees, nodes))
    for t in range(trees):
        pending = [(0, 0, rows[random.choice(len(rows), psi, replace=False)])]
        while pending:
            node, level, own = pending.pop()
            low, high = own.min(0), own.max(0)
            wide = np.flatnonzero(high > low)
            if level == depth or not len(wide):
                path[t, node] = level + mean_path(len(own))
                continue
            c = int(random.choice(wide))
            column[t, node], place[t, node] = c, random.uniform(low[c], high[c])
            left = own[:, c] < place[t, node]
            for child, part in ((2 * node + 1, own[left]), (2 * node + 2, own[~left])):
                if len(part):
                    pending.append((child, level + 1, part))
                else:
                    path[t, child] = level + 1
    return {"column": column, "place": place, "path": path, "psi": np.array(psi), "depth": np.array(depth)}


def scores(forest: dict[str, np.ndarray], rows: np.ndarray) -> np.ndarray:
    """Anomaly scores in 0..1: above a half, a row is easier to isolate than the mean one."""
    total = np.zeros(len(rows))
    every = np.arange(len(rows))
    for column, place, path in zip(forest["column"], forest["place"], forest["path"], strict=True):
        node = np.zeros(len(rows), np.int64)
        for _ in range(int(forest["depth"])):
            c = column[node]
            node = np.where(c >= 0, 2 * node + 1 + (rows[every, np.maximum(c, 0)] >= place[node]), node)
        total += path[node]
    return 2.0 ** (-total / len(forest["path"]) / max(float(mean_path(float(forest["psi"]))), 1e-9))


_SCORED = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", anomaly double"


def _score_batches(forest: dict[str, np.ndarray]):
    """Of rows with their counts and shares, the id, the counts and the score."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = np.column_stack([batch.column(c).to_numpy(zero_copy_only=False) for c in SHARES])
            kept = [batch.column(c) for c in ("doc_id", *COUNTS)]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(scores(forest, rows))], ["doc_id", *COUNTS, "anomaly"])

    return run


def in_order(rows: np.ndarray) -> np.ndarray:
    """Rows sorted by all their columns: what is drawn from them doesn't depend on how they came."""
    return rows[np.lexsort(rows.T)]


def fit(stats: DataFrame, labels: DataFrame | None, trees: int = TREES, rows_in_tree: int = ROWS_IN_TREE, labelled_rows: int | None = None, lose: float = LOSE, seed: int = SEED) -> tuple[dict[str, np.ndarray] | None, float]:
    """The forest, on the rows its trees draw, and its threshold, from all labelled good rows or, if asked, about `labelled_rows`."""
    shares, keys = list(SHARES), ("doc_id", *COUNTS, *SHARES)
    sample = in_order(hashed_sample(stats, trees * rows_in_tree, seed, *keys).select(*shares).toPandas().to_numpy(float))
    if not len(sample):
        return None, DEFAULT_THRESHOLD
    forest = grow(sample, trees, rows_in_tree, seed)
    if labels is None:
        return forest, DEFAULT_THRESHOLD
    good = cut(labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id")).distinct())
    found = cut(stats.where(~base_failed()).join(good, "doc_id", "left_semi"))
    if labelled_rows is not None:
        found = cut(hashed_sample(found, labelled_rows, seed + 1, *keys))
    if found.count() < LEAST_LABELLED:
        return forest, DEFAULT_THRESHOLD
    scored = cut(found.select("doc_id", *COUNTS, *shares).mapInArrow(released(_score_batches(forest)), _SCORED))
    return forest, exact_quantiles(scored, "anomaly", [1 - lose]).first()["value"]


def base_failed() -> F.Column:
    return (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words"))


def judged(docs: DataFrame, labels: DataFrame | None = None, **options) -> DataFrame:
    """(doc_id, the counts, base_failed, kept, anomaly double, threshold double) of every row of `docs`."""
    stats = rule_statistics(docs)
    forest, threshold = fit(stats, labels, **options)

    scored = stats.mapInArrow(released(_score_batches(forest)), _SCORED) if forest else stats.select("doc_id", *COUNTS, F.lit(0.0).alias("anomaly"))
    failed = base_failed()
    return scored.select("doc_id", *COUNTS, failed.alias("base_failed"), (~failed & (F.col("anomaly") <= threshold)).alias("kept"), "anomaly", F.lit(threshold).alias("threshold"))
