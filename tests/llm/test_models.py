import re
import zlib
from collections import Counter
from math import log, log10

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from rankfit.llm import importance, interpolated, rule_forest
from rankfit.llm.rows import hashed_sample

WORD = re.compile("[^\x20\x09-\x0d]+")


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def lm_brute(rows):
    """Scores by dictionaries, with the weights learned on exact estimates."""
    tokens = [(i, zlib.crc32(str(i).encode()) % 7 if i is not None else 3, WORD.findall(lower(t)) + [None]) for i, t in rows]

    def counted(folds):
        pair, word, context = Counter(), Counter(), Counter()
        for _, f, ts in tokens:
            if f in folds:
                word.update(ts)
                for a, b in zip(["<begin>", *ts], ts, strict=False):
                    pair[a, b] += 1
                    context[a] += 1
        return pair, word, context

    every = set(range(7)) - {2}
    pair, word, context = counted(every - {0})
    n, kinds = sum(word.values()), len(word)
    cells = Counter()
    for _, f, ts in tokens:
        if f == 0:
            for a, b in zip(["<begin>", *ts], ts, strict=False):
                cells[int(interpolated.bucket(np.array([context[a]]))[0]), pair[a, b] / max(context[a], 1), word[b] / n] += 1
    mix = np.tile([0.4, 0.5, 0.1], (interpolated.CONTEXT_BUCKETS, 1))
    mix[0] = [0, 0.9, 0.1]
    at = np.array([c[0] for c in cells])
    estimate = np.array([[c[1], c[2], 1 / (kinds + 1)] for c in cells])
    for _ in range(interpolated.ROUNDS):
        share = mix[at] * estimate
        share *= (np.array(list(cells.values())) / share.sum(1))[:, None]
        sums = np.zeros_like(mix)
        np.add.at(sums, at, share)
        mix = (sums + 5 * mix) / (sums.sum(1) + 5)[:, None]
    mix = np.maximum(mix, [0, 1e-4, 1e-4])
    mix[0, 0] = 0
    mix /= mix.sum(1, keepdims=True)
    pair, word, context = counted(every)
    n, kinds = sum(word.values()), len(word)
    out = []
    for i, f, ts in tokens:
        base = sum(log10((word[t] + 1) / (n + kinds + 1)) for t in ts)
        score = 0
        for a, b in zip(["<begin>", *ts], ts, strict=False):
            w = mix[int(interpolated.bucket(np.array([context[a]]))[0])]
            score += log10(w[0] * pair[a, b] / max(context[a], 1) + w[1] * word[b] / n + w[2] / (kinds + 1))
        out.append((i, f == 2, len(ts), sum(word[t] > 0 for t in ts), n, base, score))
    return out


@pytest.mark.parametrize("batch_tokens", [1 << 20, 3000])
def test_interpolated(odd, documents, none, batch_tokens):
    for df in (odd, documents.repartition(3)) if batch_tokens < 5000 else (documents,):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        order = lambda r: (str(r[0]), r[2], round(r[5], 4))
        want = sorted(lm_brute(rows), key=order)
        got = sorted(map(tuple, interpolated.scored(df, batch_tokens=batch_tokens, grams_in_part=5000).collect()), key=order)
        assert [g[:5] for g in got] == [w[:5] for w in want]
        assert np.allclose([g[5] for g in got], [w[5] for w in want], rtol=1e-9)
        assert np.allclose([g[6] for g in got], [w[6] for w in want], rtol=0.02, atol=0.1)
    held = [g for g in got if g[1]]
    assert sum(g[6] for g in held) > sum(g[5] for g in held)
    assert interpolated.scored(none).count() == 0


def test_packed_arrays_round_trip():
    values = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 1000, np.uint64))
    assert (interpolated.unpacked_sorted(interpolated.packed_sorted(values)) == values).all()
    assert len(interpolated.unpacked(interpolated.packed(np.zeros(0, np.uint32)), "<u4")) == 0


def test_importance(spark, odd, none):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = {r.doc_id: r for r in importance.sampled(df, labels).collect()}
    truth = {r.doc_id: r.quality == 1 and r.toxic == 0 for r in labels.collect()}
    good = [got[d].kept for d, ok in truth.items() if ok]
    bad = [got[d].kept for d, ok in truth.items() if not ok]
    assert sum(good) >= 0.97 * len(good) and sum(bad) <= 0.6 * len(bad)
    keys = sorted((r.sample_key for r in got.values()), reverse=True)
    k = sum(r.kept for r in got.values())
    assert all(r.kept == (r.sample_key >= keys[k - 1]) for r in got.values())
    stored = importance.accepted(df, labels)
    assert stored.columns == df.columns and {r.doc_id for r in stored.collect()} == {d for d, r in got.items() if r.kept}
    assert importance.sampled(odd, labels).count() == odd.count()
    assert importance.accepted(odd, labels.limit(0)).count() == odd.count()
    assert importance.accepted(none, labels).count() == 0


def test_importance_keeps_good_rows_it_did_not_learn_from(spark):
    df = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet").cache()
    kept = {r.doc_id: r.kept for r in importance.sampled(df, labels.where("doc_id % 5 != 0")).select("doc_id", "kept").collect()}
    rows = [(r.quality == 1 and r.toxic == 0, kept[r.doc_id]) for r in labels.where("doc_id % 5 = 0").collect() if r.doc_id in kept]
    good, bad = [k for ok, k in rows if ok], [k for ok, k in rows if not ok]
    assert len(good) > 300 and sum(good) >= 0.98 * len(good)
    assert sum(bad) <= 0.4 * len(bad)


def test_kth_largest(spark):
    values = [float(v) for v in np.random.default_rng(2).normal(size=3000).round(2)]
    df = spark.createDataFrame([(v,) for v in values], "v double").cache()
    for k in (1, 17, 1500, 3000):
        assert importance.kth_largest(df, "v", k, at_once=50) == sorted(values, reverse=True)[k - 1]


def grams_brute(text):
    """(family, bucket) of a text's words, pairs of words and pairs of shapes, by plain integers."""
    most, words = (1 << 64) - 1, (text or "").encode().split()

    def bucket(x, bits):
        return ((x ^ (x >> 31)) * 0xBF58476D1CE4E5B9 & most) >> (64 - bits)

    def shape(w):
        kinds = [65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 48 if 48 <= b <= 57 else b for b in w]
        return bytes(b for i, b in enumerate(kinds) if not i or b != kinds[i - 1])

    around = bytes(b for b in range(33, 127) if not chr(b).isalnum())
    word = [xxhash.xxh64_intdigest(w.lower().strip(around) or w) for w in words]
    shapes = [xxhash.xxh64_intdigest(shape(w)) for w in words]
    out = {(0, bucket(h, importance.WORD_BITS)) for h in word}
    for i in range(len(words) - 1):
        out.add((1, bucket((word[i] * 0x9E3779B97F4A7C15 + word[i + 1]) & most, importance.PAIR_BITS)))
        pair = (shapes[i] * 0x9E3779B97F4A7C15 + shapes[i + 1]) & most
        out.add((2, bucket((pair * 2 + (words[i] == words[i + 1])) & most, importance.SHAPE_BITS)))
    return out


def test_importance_against_brute_force(documents, labels):
    rows = [(r.doc_id, r.text, r.fold) for r in documents.select("doc_id", "text", importance._fold()).collect()]
    good = {r.doc_id: r.quality == 1 and not r.toxic for r in labels.collect() if r.doc_id is not None and r.quality is not None}
    grams = {i: grams_brute(t) for i, t, _ in rows}
    raw = Counter(g for i, _, _ in rows for g in grams[i])

    def ratios(skipped):
        own = Counter(g for i, _, f in rows if good.get(i) and f != skipped for g in grams[i])
        mass, scale = sum(own.values()), sum(own.values()) / sum(raw.values())
        every = mass + importance.PSEUDO * importance.BUCKETS
        clear, left, right = {}, every, every
        for g, n in raw.items():
            a, b = own[g] + importance.PSEUDO, n * scale + importance.PSEUDO
            errors = abs(own[g] - n * scale) / (min(own[g], n * scale) + importance.PSEUDO / 4) ** 0.5
            if abs(log(a / b)) >= importance.LEAST_EFFECT and errors >= importance.LEAST_ERRORS:
                clear[g], left, right = log(a / b), left - a, right - b
        return clear, log(left / right)

    tables = {f: ratios(f) for f in (None, *range(importance.FOLDS))}
    assert tables[None][0]
    got = {r.doc_id: r for r in importance.sampled(documents, labels, share=0.5).collect()}
    for i, _, fold in rows:
        clear, rest = tables[fold if i in good else None]
        assert got[i].n_features == len(grams[i])
        assert abs(got[i].log_ratio - sum(clear.get(g, rest) for g in grams[i])) < 1e-3 * (1 + abs(got[i].log_ratio))
    draws = documents.select("doc_id", "text").select("doc_id", F.xxhash64(F.lit(importance.SEED + 1), "doc_id", F.xxhash64("text")).alias("h")).collect()
    for r in draws:
        uniform = (((r.h & ((1 << 64) - 1)) >> 11) + 0.5) / (1 << 53)
        assert abs(got[r.doc_id].sample_key - (got[r.doc_id].log_ratio / importance.TEMPERATURE - log(-log(uniform)))) < 1e-6
    keys = sorted((r.sample_key for r in got.values()), reverse=True)
    assert sum(r.kept for r in got.values()) == round(len(rows) / 2)
    assert all(r.kept == (r.sample_key >= keys[round(len(rows) / 2) - 1]) for r in got.values())


def test_samples_beyond_their_bounds_do_not_hang_on_files(spark, labels):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    truth = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    small = {"trees": 20, "rows_in_tree": 16, "labelled_rows": 100}
    one, other = (sorted(map(str, rule_forest.judged(x, truth, **small).collect())) for x in (df.coalesce(1), df.repartition(9).unionByName(df.limit(0))))
    assert one == other
    one, other = (sorted(map(str, importance.sampled(x, truth, labelled_rows=150).select("doc_id", "kept").collect())) for x in (df.coalesce(1), df.repartition(9)))
    assert one == other
    copies = df.limit(1).withColumn("n", F.explode(F.sequence(F.lit(1), F.lit(5000)))).drop("n")
    assert hashed_sample(copies, 100, 1, "doc_id", "text").count() == 1


def test_forest_paths_against_brute_force():
    data = np.random.default_rng(4).normal(size=(300, 4))
    forest = rule_forest.grow(data, 30, 32)
    for row, score in zip(data[:40], rule_forest.scores(forest, data[:40]), strict=True):
        total = 0.0
        for column, place, path in zip(forest["column"], forest["place"], forest["path"], strict=True):
            node = 0
            while column[node] >= 0:
                node = 2 * node + (2 if row[column[node]] >= place[node] else 1)
            total += path[node]
        n = 32
        mean = 2 * (log(n - 1) + 0.5772156649015329) - 2 * (n - 1) / n
        assert abs(score - 2 ** (-total / 30 / mean)) < 1e-9


def test_forest_threshold_counts_all_labelled_rows(spark):
    n = 25_000
    shares = [(F.rand(i) / 4).alias(c) for i, c in enumerate(rule_forest.SHARES)]
    stats = spark.range(n).select(F.col("id").alias("doc_id"), F.lit(100).cast("long").alias("n_words"), *[F.lit(0).cast("long").alias(c) for c in rule_forest.COUNTS[1:]], *shares).cache()
    labels = spark.range(n).select(F.col("id").alias("doc_id"), F.lit(1).alias("quality"))
    forest, threshold = rule_forest.fit(stats, labels, trees=20, lose=0.3)
    scores = rule_forest.scores(forest, stats.select(*rule_forest.SHARES).toPandas().to_numpy(float))
    assert threshold == np.sort(scores)[int(np.ceil(0.7 * n)) - 1]
