import re
from collections import defaultdict
from hashlib import sha256

import numpy as np
import xxhash

import corpus_pipeline
from rankfit.llm import exact_dedup, mixing, simhash

WS = re.compile("[\x20\x09-\x0d]+")


def exact_brute(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[WS.sub(" ", t or "")].append(i)
    out = []
    for text, ids in groups.items():
        keep = min((i for i in ids if i is not None), default=None)
        for n, i in enumerate(sorted(ids, key=lambda x: (x is None, x or 0))):
            out.append((i, keep, len(ids), n == 0, sha256(text.encode()).hexdigest()))
    return sorted(out, key=str)


def test_exact_groups(odd, documents, none):
    for df in (odd, documents.repartition(20)):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        got = sorted(map(tuple, exact_dedup.duplicate_groups(df, fanout=4).collect()), key=str)
        assert got == exact_brute(rows)
        kept = exact_dedup.keep_first(df)
        assert kept.columns == df.columns
        assert sorted((r.doc_id, WS.sub(" ", r.text or "")) for r in kept.collect() if r.doc_id is not None) == sorted({(k, WS.sub(" ", t or "")) for k, t in ((min((i for i, u in rows if i is not None and WS.sub(" ", u or "") == WS.sub(" ", t or "")), default=None), t) for _, t in rows) if k is not None})
        assert kept.count() == sum(r[3] for r in got)
    assert exact_dedup.duplicate_groups(none).count() == 0


def fingerprint_brute(text):
    words = [w for w in re.split("[\x20\x09-\x0d]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")) if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def components_brute(prints, ids):
    values = np.array(prints, np.uint64)
    parent = list(range(len(ids)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(ids)):
        for j in np.flatnonzero(np.bitwise_count(values ^ values[i]) <= 4):
            a, b = find(i), find(int(j))
            parent[max(a, b)] = min(a, b)
    name = defaultdict(list)
    for i in range(len(ids)):
        name[find(i)].append(ids[i])
    least = {k: min((x for x in v if x is not None), default=None) for k, v in name.items()}
    return [least[find(i)] for i in range(len(ids))]


def test_simhash(odd, documents, none):
    for df, block in ((odd, 2), (documents, 4096)):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        prints = [fingerprint_brute(t) for _, t in rows]
        want = sorted(zip([i for i, _ in rows], [f"{p:016x}" for p in prints], components_brute(prints, [i for i, _ in rows]), strict=True), key=str)
        got = simhash.near_duplicates(df, block=block).select("doc_id", simhash.hex_fingerprint("fp"), "component_id").collect()
        assert sorted(map(tuple, got), key=str) == want
    kept = simhash.keep_one_of_each(odd)
    assert kept.columns == odd.columns
    assert kept.count() == len(set(components_brute([fingerprint_brute(r.text) for r in odd.collect()], list(range(odd.count())))))
    assert simhash.near_duplicates(none).count() == 0


def similar_brute(texts):
    sets = []
    for t in texts:
        words = [w for w in re.split("[\x20\x09-\x0d]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")) if w]
        sets.append(frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset())
    parent = list(range(len(sets)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] == sets[j] or 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]) > 0:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(sets))]


def test_similar_texts(spark, odd, documents, none, monkeypatch):
    random = np.random.default_rng(5)
    base = [[f"w{x}" for x in random.integers(5000, size=120)] for _ in range(20)]
    made = []
    for b in base:  # copies with one to four changed words lie on both sides of 0.8
        made += [" ".join(b)] + [" ".join(f"c{random.integers(99)}" if i in set(random.integers(120, size=k)) else w for i, w in enumerate(b)) for k in (1, 2, 3, 4, 5, 6)]
    copies = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    for df, frequent, block in ((odd, 2, 4096), (copies, 100, 4096), (copies, 1, 3), (documents, 100, 4096)):
        monkeypatch.setattr(simhash, "PAIRS_A_ROW", 0 if block == 3 else 4)
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        want = defaultdict(list)
        for group, row in zip(similar_brute([t for _, t in rows]), rows, strict=True):
            want[group].append(row[0])
        got = defaultdict(list)
        for r in simhash.similar_texts(df, frequent=frequent, block=block).collect():
            got[r.root].append(r.doc_id)
        assert sorted(sorted(map(str, g)) for g in got.values()) == sorted(sorted(map(str, g)) for g in want.values())
        kept = simhash.keep_one_of_similar(df, frequent=frequent)
        assert kept.columns == df.columns and kept.count() == len(want)
    assert 1 < len(set(similar_brute(made))) < len(made)
    assert simhash.keep_one_of_similar(none).count() == 0


def test_sketches_bound_what_sets_share():
    random = np.random.default_rng(8)
    for _ in range(300):
        pool = random.integers(-(1 << 62), 1 << 62, size=int(random.integers(1, 400)))
        if random.random() < 0.2:
            pool = pool << 9  # one place of the sketch for all
        a, b = (np.unique(random.choice(pool, int(random.integers(1, 300)))) for _ in range(2))
        most = simhash._most_shared(simhash._sketch(a), simhash._sketch(b), len(a), len(b))
        assert most >= len(np.intersect1d(a, b))
    assert simhash._most_shared(simhash._sketch(a), simhash._sketch(a), len(a), len(a)) == len(a)


def test_pipeline_links_by_similarity(spark):
    words = [f"w{i}" for i in range(120)]
    near, far = list(words), list(words)
    near[30] = near[70] = "x"  # 106 of 126 shingles shared: 0.84
    far[30] = far[60] = far[90] = "y"  # 101 of 131: 0.77
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(far))], "doc_id long, text string")
    assert sorted(r.doc_id for r in corpus_pipeline.near(spark, docs, "").collect()) == [1, 3]


def test_hot_bucket_in_blocks(spark):
    random = np.random.default_rng(3)
    base = int(random.integers(1 << 62))
    chain = [base]
    for _ in range(400):
        chain.append(chain[-1] ^ (1 << int(random.integers(64))) ^ (1 << int(random.integers(64))))
    others = [int(x) for x in random.integers(1 << 62, size=200)]
    prints = sorted(set(chain + others))
    signed = [int(np.uint64(p).astype(np.int64)) if p < 1 << 63 else p - (1 << 64) for p in prints]
    df = spark.createDataFrame([(s, i) for i, s in enumerate(signed)], "fp long, least_id long")
    want = components_brute(prints, list(range(len(prints))))
    for block, many, hub in ((4096, 1 << 25, 256), (7, 1 << 25, 2), (4096, 0, 256)):
        root = {r.node: r.root for r in simhash.components(simhash.links(df, block=block, many=many), hub=hub).collect()}
        got = [root.get(s, s) for s in signed]
        assert [got.index(x) for x in got] == [want.index(x) for x in want]


def test_chains_and_stars_settle(spark):
    edges = [(i, i + 1) for i in range(300)] + [(1000, 1001 + i) for i in range(400)] + [(5000 + i, 6000) for i in range(50)]
    df = spark.createDataFrame([e[::-1] if i % 2 else e for i, e in enumerate(edges)], "a long, b long")
    for hub in (3, 256):
        root = {r.node: r.root for r in simhash.components(df, hub=hub).collect()}
        assert root == {n: 0 if n < 1000 else 1000 if n < 5000 else 5000 for e in edges for n in e}


def mix_targets_brute(sizes):
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: 1 + i % 3 for i, s in enumerate(order)}
    total, done, target = sum(sizes.values()), {}, {}
    while True:
        free = [s for s in order if s not in done]
        left, share = total - sum(done.values()), sum(weight[s] for s in free)
        target = {s: left * weight[s] / share for s in free}
        over = [s for s in free if target[s] > 3 * sizes[s]]
        if not over:
            return done | target
        done |= {s: 3 * sizes[s] for s in over}


def test_mixing(odd, documents, none):
    repeated = documents.withColumn("doc_id", documents["doc_id"] % 2)
    for df in (odd, documents, repeated, repeated.unionAll(repeated)):
        sizes = defaultdict(int)
        for r in df.collect():
            sizes[r.source] += len(re.findall("[^\x20\x09-\x0d]+", r.text or ""))
        want = mix_targets_brute(dict(sizes))
        key = [(r.doc_id, r.source, r.text) for r in df.collect()]
        got = mixing.mixture(df).collect()
        again = mixing.mixture(df.repartition(5)).collect()
        assert sorted(map(str, got)) == sorted(map(str, again)) and len(got) == len(key)
        assert all(0 <= r.taken <= 3 * r.size for r in got)
        taken = defaultdict(int)
        for r in got:
            taken[(r.source_size, round(r.target, 6))] += r.taken
        share = defaultdict(float)
        for s, t in want.items():
            share[(sizes[s], round(t, 6))] += t
        assert share.keys() == taken.keys()
        assert all(abs(taken[k] - share[k]) <= 2 for k in share)
        mix = mixing.mixed(df)
        assert mix.columns == df.columns
        words = defaultdict(int)
        for r in mix.collect():
            words[r.source] += len(re.findall("[^\x20\x09-\x0d]+", r.text))
        assert all(abs(words[s] - want[s]) <= 1 for s in sizes)
    assert mixing.mixture(none).count() == 0 and mixing.mixed(none).count() == 0


def test_texts_that_share_a_passage_only_are_told_apart_where_they_meet(spark):
    passage = " ".join(f"p{i}" for i in range(60))
    texts = [passage + " " + " ".join(f"o{t}x{i}" for i in range(50)) for t in range(90)]
    texts += [x + " end" for x in texts[:5]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    steps = simhash.SimilarTexts(docs, 5, (4, 5), 4, 4096, 100)
    try:
        alone = spark.createDataFrame([], "v long, root long")
        pairs = {frozenset(r) for r in steps.all_pairs(steps.rooted(steps.shared(), alone)).collect()}
        named = {r.doc_id: r.v for r in steps.rows.select("doc_id", "v").collect()}
    finally:
        steps.store.close()
    assert {frozenset((named[i], named[90 + i])) for i in range(5)} <= pairs
    assert len(pairs) < 50


def test_rows_that_leave_tasks_grow_with_the_sets_of_a_group_not_their_pairs(spark):
    random = np.random.default_rng(11)
    base = [f"w{i}" for i in range(120)]
    texts = [" ".join(f"c{t}x{i}" if i in changed else w for i, w in enumerate(base)) for t, changed in ((t, set(random.integers(120, size=1 + t % 2))) for t in range(250))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = similar_brute(texts)
    for block in (4096, 40):
        steps = simhash.SimilarTexts(docs, 5, (4, 5), 4, block, 1000)
        try:
            alone = spark.createDataFrame([], "v long, root long")
            met = steps.store.table(steps.all_pairs(steps.rooted(steps.shared(), alone)))
            assert met.count() < 20 * len(texts)  # each of few tasks gives a forest
            groups = steps.joined(met)
            for wanted in ("sketch", "s"):
                edges = steps.store.table(steps.in_groups(groups, wanted))
                assert edges.count() < len(texts) * (1 if block == 4096 else 7)  # cells give a forest each
                groups = steps.joined(edges)
            root = {r.v: r.root for r in groups.collect()}
            named = {r.doc_id: r.v for r in steps.rows.select("doc_id", "v").collect()}
        finally:
            steps.store.close()
        got = [root.get(named[i], named[i]) for i in range(len(texts))]
        assert [got.index(x) for x in got] == [want.index(x) for x in want]


def test_spread_joins_what_pairs_join():
    random = np.random.default_rng(12)
    for _ in range(100):
        n = int(random.integers(1, 40))
        root = random.integers(n, size=n) if random.random() < 0.5 else np.arange(n)
        linked = random.random((n, n)) < 1.2 / n
        linked |= linked.T
        x, y = simhash._spread(root, lambda i, left, linked=linked: linked[i, left])
        assert len(x) < n and all(linked[i, j] and root[i] != root[j] for i, j in zip(x, y, strict=True))
        i, j = np.nonzero(linked)
        ties = [dict(zip(*map(np.ndarray.tolist, simhash.forest(a, b)), strict=True)) for a, b in ((root[x], root[y]), (root[i], root[j]))]
        assert [[t.get(r, r) for r in root.tolist()] for t in ties[:1]] == [[t.get(r, r) for r in root.tolist()] for t in ties[1:]]


def test_sets_of_a_group_are_counted_and_bounded():
    random = np.random.default_rng(13)
    for _ in range(50):
        pool = random.integers(-(1 << 62), 1 << 62, size=int(random.integers(1, 300)))
        sets = [np.unique(random.choice(pool, int(random.integers(0, 200)))) for _ in range(int(random.integers(2, 30)))]
        n = np.array([len(s) for s in sets])
        whole, sketches = simhash._Whole(n, np.concatenate(sets)), simhash._Sketches(n, [simhash._sketch(s) for s in sets])
        others = np.arange(len(sets))
        while len(others):
            for x in range(0, len(sets), 5):
                want = [len(np.intersect1d(sets[x], sets[y])) for y in others]
                assert whole.most_shared(x, others).tolist() == want
                assert (sketches.most_shared(x, others) >= want).all()
            others = others[: len(others) // 3]
