"""SimHash near-duplicates by multi-index hashing.

A text's fingerprint has a bit for each of 64 places, one where over half of its shingles' XXH64 values have
one. Two fingerprints link at a Hamming distance of at most `radius`. The index cuts fingerprints into three
segments of 21, 21 and 22 bits and stores every fingerprint under each segment. A pair within distance 4 differs
by at most 1, 1 or 0 bits in one of them (if all exceeded that, the sum would be 5), so a probe enumerates the
Hamming balls of those radii, fetches the fingerprints stored under each value and verifies whole distances. Beyond
`MANY` fingerprints there are two segments of 32 bits with radii 2 and 1, whose buckets stay small for longer.

Equal fingerprints are one vertex, however many rows share them. Inside one (segment, value) bucket the verified
links are reduced to a spanning forest, so the number of edges that leave a task is below its number of rows even
where thousands of near copies are all linked with each other; buckets above `block` stored fingerprints are cut
into blocks, each of which meets every probe, so that no link is lost and no task holds a whole large group.
Components are the connected components of the edges, found by repeated minimum labelling until nothing changes; the
neighbours of a hub learn its label from a table sent to all tasks, so that no task meets all of them.

Defined results: null and word-less texts have fingerprint zero and link like any other. Null ids are ignored for
the component's name; a component of null ids only has a null name. Repeated rows each give a row. Extra columns
are ignored. An empty table gives an empty result.

`similar_texts` links by the Jaccard similarity of the sets of shingles, which no fingerprint decides: at 0.8 two
fingerprints differ in about ten bits, and an index that reaches so far meets a fixed share of all pairs. It takes the
index's links as first candidates, whose components spare most of the work in groups of near copies, and completes them:
two sets with similarity s share one of their first n - ceil(s n) + 1 shingles in any order common to all texts. The
order is that of hashes, with the shingles that many texts begin with last; which ones are known to be frequent changes
the work, not the result. Where sets meet, a small signature of each tells most that differ apart.

Pairs never leave the task where they meet: from it go edges of a forest, fewer than the rows it read, so that no table
grows with the square of a group. Sets that such edges join are candidates of each other, whether met or not, and each
goes once to where its group meets: first with a sketch, counts of its shingles by their last bits, from which follows
how many two sets can share at most, then, in the groups that this leaves, whole, made anew from its text. Only there,
where shared shingles are counted, a pair links. A group larger than a task should hold is cut into blocks, each pair of
which meets in one cell.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from rankfit.llm.rows import keep_rows, released, text_hash
from rankfit.session import Scratch, cut, forget_shuffles, ship

SHINGLE_WORDS = 4
SEED = 42
RADIUS = 4
SIMILAR_WORDS, SIMILAR = 5, (4, 5)
FREQUENT, FREQUENT_KEPT, PASSAGE_SETS = 100, 20_000, 4_000
SENT = 1_000_000
MANY, HUB = 1 << 25, 256
#: In cells of more pairs than this for each row a set meets only those that nothing has joined yet.
PAIRS_A_ROW = 32
#: Blocks of a group of candidates hold about so many shingles at most.
GROUP_SHINGLES = 1 << 20
#: Bytes of what a set takes along to where it meets others, to tell most that differ from it there.
SIGNATURE = 64

_BYTE_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)
_ROW = np.arange(8, dtype=np.int64) * 256


def text_fingerprint(text: bytes | None, words: int = SHINGLE_WORDS, seed: int = SEED) -> int:
    """The 64-bit fingerprint of one UTF-8 text: A-Z lower-cased, words between ASCII white space."""
    hashes = shingles(text, words, seed)
    return majority(hashes) if len(hashes) else 0


def shingles(text: bytes | None, words: int = SHINGLE_WORDS, seed: int = SEED) -> np.ndarray:
    """XXH64 of each run of `words` words; a shorter text is one shingle, a word-less one has none."""
    parts = (text or b"").lower().split()
    digest = xxhash.xxh64_intdigest
    if len(parts) <= words:
        return np.array([digest(b" ".join(parts), seed)] if parts else [], np.uint64)
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[: len(parts) - words + 1].tolist()
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts, ends[words - 1 :].tolist(), strict=True)], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """Bits set in over half of `hashes`, from a histogram of each of their eight bytes."""
    if len(hashes) == 1:
        return int(hashes[0])
    places = hashes.astype("<u8").view(np.uint8).reshape(-1, 8) + _ROW
    counts = np.bincount(places.ravel(), minlength=2048).reshape(8, 256) @ _BYTE_BITS
    bits = (2 * counts > len(hashes)).astype(np.uint8)
    return int.from_bytes(np.packbits(bits.ravel(), bitorder="little").tobytes(), "little")


def _fingerprint_batches(words: int, seed: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = [text_fingerprint(x, words, seed) for x in batch.column("text").to_pylist()]
            signed = np.array(prints, np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_hash"), pa.array(signed, pa.int64())], ["doc_id", "text_hash", "fp"])

    return run


def fingerprints(docs: DataFrame, words: int = SHINGLE_WORDS, seed: int = SEED) -> DataFrame:
    """(doc_id, text_hash, fp long: the unsigned fingerprint's bits) of every row."""
    ship(docs.sparkSession)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_hash(), F.col("text").cast("binary").alias("text"))
    return plain.mapInArrow(released(_fingerprint_batches(words, seed)), "doc_id long, text_hash long, fp long")


def _balls(radius: int, widths: tuple[int, ...]) -> list[tuple[int, int, int, int]]:
    """(segment, shift, mask of its width, flip) of every probe; flip 0 is also what the index stores."""
    # The radii of the segments and one more each must exceed the radius in all.
    radii = [max(0, (radius + 1 - len(widths) + i) // len(widths)) for i in range(len(widths))][::-1]
    out, shift = [], 0
    for segment, (width, r) in enumerate(zip(widths, radii, strict=True)):
        if r > 2:
            raise ValueError(f"radius {radius} needs more segments than {len(widths)}")
        flips = [0] + [1 << i for i in range(width)] * (r >= 1)
        if r == 2:
            flips += [1 << i | 1 << j for i in range(width) for j in range(i)]
        out += [(segment, shift, (1 << width) - 1, f) for f in flips]
        shift += width
    return out


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges (node, root) with the same components as (a, b), one for each node that isn't a root."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[i], label[j])
        before = label.copy()
        np.minimum.at(label, label[i], low)
        np.minimum.at(label, label[j], low)
        label = label[label]
        if (label == before).all():
            break
    rest = label != np.arange(len(nodes))
    return nodes[rest], nodes[label[rest]]


def _linked_batches(radius: int, pairs_at_once: int = 1 << 20):
    """Over batches sorted by (key, block, own first): verified links of each bucket, reduced to forests."""

    def links(own: np.ndarray, rest: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, b = [], []
        step = max(1, pairs_at_once // max(1, len(rest)))
        for i in range(0, len(own), step):
            near = np.bitwise_count((own[i : i + step, None] ^ rest[None, :]).view(np.uint64)) <= radius
            x, y = np.nonzero(near)
            x, y = own[i + x], rest[y]
            keep = x != y
            if keep.any():
                u, v = forest(x[keep], y[keep])
                a.append(u)
                b.append(v)
        return np.concatenate(a) if a else own[:0], np.concatenate(b) if b else own[:0]

    def bucketed(group: np.ndarray, own: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        starts = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
        size = np.diff(np.append(starts, len(group)))
        owned = np.add.reduceat(own.astype(np.int64), starts)
        work = owned * size
        a, b = [], []
        small = (owned > 0) & (size > 1) & (work <= 1 << 14)
        s, o, m, w = starts[small], owned[small], size[small], work[small]
        bounds = np.concatenate(([0], np.cumsum(w)))
        at = 0
        while at < len(s):
            to = max(at + 1, int(np.searchsorted(bounds, bounds[at] + pairs_at_once, "right")) - 1)
            part = slice(at, to)
            n = w[part]
            inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            wide = np.repeat(m[part], n)
            first = np.repeat(s[part], n)
            x, y = fp[first + inner // wide], fp[first + inner % wide]
            near = (np.bitwise_count((x ^ y).view(np.uint64)) <= radius) & (x != y)
            if near.any():
                u, v = forest(x[near], y[near])
                a.append(u)
                b.append(v)
            at = to
        for k in np.flatnonzero((owned > 0) & (size > 1) & (work > 1 << 14)):
            u, v = links(fp[starts[k] : starts[k] + owned[k]], fp[starts[k] : starts[k] + size[k]])
            a.append(u)
            b.append(v)
        return np.concatenate(a) if a else fp[:0], np.concatenate(b) if b else fp[:0]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        names = ["a", "b"]

        def out(rows: tuple[np.ndarray, ...]) -> Iterator[pa.RecordBatch]:
            key, block, own, fp = rows
            if len(key):
                change = np.concatenate(([0], np.cumsum((key[1:] != key[:-1]) | (block[1:] != block[:-1]))))
                a, b = bucketed(change, own, fp)
                if len(a):
                    a, b = forest(a, b)
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names)

        for batch in batches:
            now = tuple(batch.column(c).to_numpy(zero_copy_only=False) for c in ("key", "block", "own", "fp"))
            if not len(now[0]):
                continue
            held.append(now)
            whole = tuple(map(np.concatenate, zip(*held, strict=True)))
            # The last bucket may go on in the next batch.
            same = (whole[0] == whole[0][-1]) & (whole[1] == whole[1][-1])
            end = len(same) if not same.any() else int(np.argmax(same))
            if end:
                yield from out(tuple(x[:end] for x in whole))
            held = [tuple(x[end:] for x in whole)]
        if held:
            yield from out(held[0])

    return run


def links(prints: DataFrame, radius: int = RADIUS, block: int = 4096, many: int = MANY) -> DataFrame:
    """Edges (a, b) over the distinct `fp` of `prints`, a stored table, whose components are those of all links within `radius`."""
    widths = (32, 32) if prints.count() > many and radius <= 5 else (21, 21, 22)
    probe = F.explode(F.array(*[F.struct(F.lit(s).cast("long").alias("s"), F.lit(h).alias("h"), F.lit(m).cast("long").alias("m"), F.lit(f << h if f << h < 1 << 63 else (f << h) - (1 << 64)).cast("long").alias("f")) for s, h, m, f in _balls(radius, widths)]))
    flipped = F.col("fp").bitwiseXOR(F.col("p.f"))
    value = F.expr("shiftrightunsigned(fp ^ p.f, p.h) & p.m")
    rows = prints.select("fp", probe.alias("p")).select("fp", (F.col("p.s") * (1 << 33) + value).alias("key"), (flipped == F.col("fp")).alias("own"))
    # Hot buckets: every stored and every visiting fingerprint has a block of its own and meets all blocks of the other kind.
    hot = cut(rows.where("own").groupBy("key").count().where(F.col("count") > block).select("key", F.ceil(F.col("count") / block).cast("int").alias("blocks")))
    if hot.isEmpty():
        dealt = rows.withColumn("block", F.lit(0).cast("long"))
    else:
        each = F.sequence(F.lit(0).cast("long"), F.coalesce("blocks", F.lit(1)).cast("long") - 1)
        mine = F.pmod(F.xxhash64("fp"), F.coalesce("blocks", F.lit(1)).cast("long"))
        pairs = rows.join(hot, "key", "left").select("key", "own", "fp", mine.alias("mine"), F.explode(each).alias("other"))
        grid = pairs.select("key", "own", "fp", F.when(F.col("own"), F.col("mine")).otherwise(F.col("other")).alias("i"), F.when(F.col("own"), F.col("other")).otherwise(F.col("mine")).alias("j"))
        # Stored fingerprints also visit: without this, two of them in different blocks would not meet.
        twice = grid.unionByName(pairs.where("own and other != mine").select("key", F.lit(False).alias("own"), "fp", F.col("other").alias("i"), F.col("mine").alias("j")))
        dealt = twice.select("key", "own", "fp", (F.col("i") * (1 << 20) + F.col("j")).alias("block"))
    sorted_rows = dealt.select("key", "block", "own", "fp").repartition("key", "block").sortWithinPartitions("key", "block", F.desc("own"))
    return sorted_rows.mapInArrow(released(_linked_batches(radius)), "a long, b long").distinct()


def _labelled(edges: DataFrame, least: DataFrame, hubs: DataFrame, store: Scratch) -> DataFrame:
    """`edges` (u, v) with the label m of u from `least` (u, m); those of `hubs` (u), a small stored table, are sent."""
    sent = F.broadcast(store.table(least.join(F.broadcast(hubs), "u", "left_semi")).withColumnRenamed("m", "hub_m"))
    both = edges.join(sent, "u", "left")
    rest = both.where("hub_m is null").drop("hub_m").join(least, "u")
    return both.where("hub_m is not null").withColumnRenamed("hub_m", "m").unionByName(rest)


def _hubs(edges: DataFrame, store: Scratch, hub: int = HUB) -> DataFrame:
    """The nodes u of `edges` (u, v) with more than `hub` edges, as a stored table; of too many, those with most."""
    degrees = store.table(edges.groupBy("u").count().where(F.col("count") > hub))
    while degrees.count() > SENT:
        hub *= 8
        degrees = degrees.where(F.col("count") > hub)
    return degrees.select("u")


def _forest_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges (u, v) with the components of each batch's (a, b), in each of which all meet the smallest node."""
    for batch in batches:
        if len(batch):
            u, v = forest(*(batch.column(c).to_numpy(zero_copy_only=False) for c in ("a", "b")))
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])


def _shape(edges: DataFrame) -> tuple[int, int]:
    """Of `edges` (u, v), each from a larger to a smaller node: how many nodes keep them from being stars, and the most edges down to one."""
    ends = edges.selectExpr("u as n", "1 as up", "0 as down").unionByName(edges.selectExpr("v as n", "0 as up", "1 as down"))
    each = ends.groupBy("n").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
    return tuple(each.agg(F.count_if((F.col("up") > 1) | (F.col("up") > 0) & (F.col("down") > 0)), F.coalesce(F.max("down"), F.lit(0))).first())


def components(edges: DataFrame, hub: int = HUB) -> DataFrame:
    """(node, root) of every node of `edges` (a, b): root is the smallest node of its component.

    Alternates two steps until only stars are left, whose middles are the roots: every node's larger neighbours are tied
    to the smallest node it knows, then so are its smaller ones. Both are an aggregate, which combines before rows move,
    and a join, in which a hub's label goes to its edges. What tasks can join on their own comes first.
    """
    spark = edges.sparkSession
    ship(spark)
    # A round reads the last one's edges and, where there are hubs, two small tables of its own.
    store = Scratch(spark, keep=4)
    now = store.table(edges.select("a", "b").mapInArrow(released(_forest_batches), "u long, v long").distinct())
    while (shape := _shape(now))[0]:
        turned = now.select(F.col("v").alias("u"), F.col("u").alias("v"))
        least = now.unionByName(turned).groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        met = turned.join(least, "u") if shape[1] <= hub else _labelled(turned, least, _hubs(turned, store, hub), store)
        large = met.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
        now = store.table(small.where("u != v").distinct())
        forget_shuffles(spark)
    found = cut(now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()))
    store.close()
    return found


def near_duplicates(docs: DataFrame, radius: int = RADIUS, words: int = SHINGLE_WORDS, block: int = 4096) -> DataFrame:
    """(doc_id, text_hash, fp long, root long: the component's smallest fp, component_id) of every row of `docs`."""
    prints = cut(fingerprints(docs, words))
    distinct = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    found = components(links(distinct, radius, block))
    named = found.join(distinct, found["node"] == distinct["fp"]).select("node", "root", "least_id")
    by_root = named.groupBy("root").agg(F.min("least_id").alias("component_id"))
    linked = named.select("node", "root").join(by_root, "root").select(F.col("node").alias("fp"), "root", "component_id")
    every = cut(distinct.join(linked, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), F.when(F.col("root").isNull(), F.col("least_id")).otherwise(F.col("component_id")).alias("component_id")))
    return prints.join(every, "fp").select("doc_id", "text_hash", "fp", "root", "component_id")


def hex_fingerprint(fp) -> F.Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def _lists(found: list[np.ndarray]) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0] + [len(x) for x in found]), pa.int32()), pa.array(np.concatenate(found) if found else np.zeros(0, np.int64)))


def _named(distinct: np.ndarray, seed: int = SEED) -> int:
    """A set's name: the hash of its sorted shingles."""
    return int(np.uint64(xxhash.xxh64_intdigest(distinct.tobytes(), seed)).astype(np.int64))


def _firsts(distinct: np.ndarray, similar: tuple[int, int], late: np.ndarray | None = None) -> np.ndarray:
    """The shingles of which similar sets share one: the first by hash, those in `late` after all others."""
    up, down = similar
    n = len(distinct) - -(-up * len(distinct) // down) + 1 if len(distinct) else 0
    if late is not None and len(late):
        is_late = late[np.minimum(np.searchsorted(late, distinct), len(late) - 1)] == distinct
        distinct = np.concatenate((distinct[~is_late], distinct[is_late]))
    return distinct[:n]


def _sketch(distinct: np.ndarray) -> bytes:
    """Counts (15 at most) of a set's shingles by their last bits, two to a byte; as many as shingles, or up to twice."""
    size = max(2, 1 << (len(distinct) - 1).bit_length()) if len(distinct) else 2
    counts = np.minimum(np.bincount(distinct & (size - 1), minlength=size), 15).astype(np.uint8)
    return (counts[0::2] | counts[1::2] << 4).tobytes()


def _signature(distinct: np.ndarray) -> bytes:
    """Counts as of a sketch, but of a fixed size: `SIGNATURE` bytes."""
    counts = np.minimum(np.bincount(distinct & (2 * SIGNATURE - 1), minlength=2 * SIGNATURE), 15).astype(np.uint8)
    return (counts[0::2] | counts[1::2] << 4).tobytes()


class _Sketches:
    """The sketches of some sets of n shingles, by their sizes."""

    def __init__(self, n: np.ndarray, sketches: list[bytes]):
        self.sizes = np.array([2 * len(x) for x in sketches])
        self.place, self.counts, self.beyond = np.zeros(len(n), np.int64), {}, np.zeros(len(n), np.int64)
        for size in np.unique(self.sizes):
            own = np.flatnonzero(self.sizes == size)
            c = np.frombuffer(b"".join(sketches[i] for i in own), np.uint8).reshape(len(own), -1)
            self.counts[size] = np.stack([c & 15, c >> 4], 2).reshape(len(own), -1)
            self.place[own] = np.arange(len(own))
            self.beyond[own] = n[own] - self.counts[size].sum(1, dtype=np.int64)

    def most_shared(self, x: int, others: np.ndarray) -> np.ndarray:
        """How many shingles set x can share with each of `others` at most."""
        out = self.beyond[x] + self.beyond[others]
        for size in np.unique(self.sizes[others]):
            of = np.flatnonzero(self.sizes[others] == size)
            least = min(size, self.sizes[x])
            a, b = self.counts[self.sizes[x]][self.place[x]][None], self.counts[size][self.place[others[of]]]
            a, b = (c if c.shape[1] == least else c.reshape(len(c), -1, least).sum(1, dtype=np.int32) for c in (a, b))
            out[of] += np.minimum(a, b).sum(1, dtype=np.int64)
        return out


def _most_shared(a: bytes, b: bytes, na: int, nb: int) -> int:
    """How many shingles two sets of na and nb can share at most, from their sketches."""
    return int(_Sketches(np.array([na, nb]), [a, b]).most_shared(0, np.array([1]))[0])


class _Whole:
    """Some whole sets: `values` holds their shingles one set after another, n of each."""

    def __init__(self, n: np.ndarray, values: np.ndarray):
        self.ends = np.cumsum(n)
        self.codes = np.unique(values, return_inverse=True)[1]
        self.owner = np.repeat(np.arange(len(n)), n)
        self.index(np.arange(len(n)))

    def index(self, sets: np.ndarray) -> None:
        """Look up shingles in `sets` only."""
        chosen = np.zeros(len(self.ends), bool)
        chosen[sets] = True
        of = np.flatnonzero(chosen[self.owner])
        self.held = of[np.argsort(self.codes[of], kind="stable")]
        self.starts = np.searchsorted(self.codes[self.held], np.arange(self.codes.max(initial=-1) + 2))
        self.indexed = len(sets)

    def most_shared(self, x: int, others: np.ndarray) -> np.ndarray:
        """How many shingles set x shares with each of `others`, which only get fewer from call to call."""
        if 2 * len(others) < self.indexed:
            self.index(others)
        own = self.codes[(self.ends[x - 1] if x else 0) : self.ends[x]]
        first, many = self.starts[own], self.starts[own + 1] - self.starts[own]
        at = np.arange(many.sum()) + np.repeat(first - np.cumsum(many) + many, many)
        return np.bincount(self.owner[self.held[at]], minlength=len(self.ends))[others]


def _spread(root: np.ndarray, near) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (x, y) of places that join all those with near(x, [y]) but for those of equal `root`, which are joined.

    Each place in turn meets only those that nothing has joined yet; the pairs are fewer than the places.
    """
    a, b, left = [], [], np.arange(len(root))
    while len(left) > 1:
        same = root[left] == root[left[0]]
        queue, left = left[same].tolist(), left[~same]
        while queue and len(left):
            x = queue.pop()
            found = left[near(x, left)]
            if len(found):
                _, each = np.unique(root[found], return_index=True)
                a.append(np.full(len(each), x))
                b.append(found[each])
                reached = np.isin(root[left], root[found])
                queue += left[reached].tolist()
                left = left[~reached]
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *a]), np.concatenate([none, *b])


def _starts(*keys: np.ndarray) -> np.ndarray:
    """Where runs of equal keys begin."""
    return np.flatnonzero(np.concatenate(([True], np.logical_or.reduce([k[1:] != k[:-1] for k in keys])))) if len(keys[0]) else np.zeros(0, np.int64)


def _group_batches(similar: tuple[int, int]):
    """Over rows sorted by (root, cell): edges (a, b) that join the sets of each cell that are, or by their sketches may be, similar."""
    up, down = similar

    def edges(c: dict, i: int, j: int) -> tuple[np.ndarray, np.ndarray]:
        n = c["n"][i:j]
        if "s" in c:
            bounds = np.concatenate(([0], np.cumsum(c["n"])))
            held = _Whole(n, c["s"][bounds[i] : bounds[j]])
        else:
            held = _Sketches(n, c["sketch"][i:j])

        def near(x: int, left: np.ndarray) -> np.ndarray:
            out = (down * n[left] >= up * n[x]) & (down * n[x] >= up * n[left])
            fits = np.flatnonzero(out)
            if len(fits):
                of = left if "s" in c else left[fits]
                shared = held.most_shared(x, of)
                shared = shared[fits] if "s" in c else shared
                out[fits] = (up + down) * shared >= up * (n[x] + n[left[fits]])
            return out

        x, y = _spread(np.arange(j - i), near)
        return c["v"][i + x], c["v"][i + y]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in _whole_cells(batches, "root"):
            starts = _starts(c["root"], c["cell"])
            for i, j in zip(starts.tolist(), [*starts[1:].tolist(), len(c["v"])], strict=True):
                if j - i > 1:
                    a, b = edges(c, i, j)
                    if len(a):
                        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

    return run


_SETS = {"sketch": "sketch binary", "sig": "sig binary", "v": "v long", "fp": "fp long", "n": "n int", "first": "first array<long>", "s": "s array<long>"}


def _set_batches(words: int, similar: tuple[int, int], wanted: tuple[str, ...], late=None, at_once: int = 1 << 20):
    """Of each text, besides the columns that come with it, those of `_SETS` that are `wanted`."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = late.value if late is not None else None
        for batch in batches:
            texts, held, start = batch.column("text"), 0, 0
            out = {c: [] for c in wanted}
            for i in range(len(batch)):
                hashes = shingles(texts[i].as_py(), words)
                distinct = np.unique(hashes.view(np.int64))
                values = {"v": lambda d=distinct: _named(d), "fp": lambda h=hashes: majority(h) if len(h) else 0, "n": lambda d=distinct: len(d), "sketch": lambda d=distinct: _sketch(d), "sig": lambda d=distinct: _signature(d), "first": lambda d=distinct: _firsts(d, similar, last), "s": lambda d=distinct: d}
                for c in wanted:
                    out[c].append(values[c]())
                held += len(distinct)
                if held >= at_once or i == len(batch) - 1:
                    own = batch.slice(start, i + 1 - start)
                    made = [_lists(x) if c in ("first", "s") else pa.array(np.array(x, np.uint64).view(np.int64)) if c == "fp" else pa.array(x, {"n": pa.int32(), "sketch": pa.binary(), "sig": pa.binary()}.get(c, pa.int64())) for c, x in out.items()]
                    names = [c for c in own.schema.names if c != "text"]
                    yield pa.RecordBatch.from_arrays([*(own.column(c) for c in names), *made], [*names, *wanted])
                    out, held, start = {c: [] for c in wanted}, 0, i + 1

    return run


def _late_batches(shared):
    """Whether any of a set's first shingles is known to be frequent."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = shared.value
        for batch in batches:
            lists = batch.column("first")
            values, sizes = lists.flatten().to_numpy(zero_copy_only=False), lists.value_lengths().to_numpy(zero_copy_only=False)
            hit = late[np.minimum(np.searchsorted(late, values), len(late) - 1)] == values
            found = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[hit], minlength=len(sizes)) > 0
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found)], [*batch.schema.names, "late"])

    return run


def _sent(few: DataFrame) -> DataFrame:
    """A stored table of numbers for a join with larger rows, which stay where they are if it is small enough to send."""
    return F.broadcast(few) if few.count() <= SENT else few


class SimilarTexts:
    """The steps of `similar_texts` over one table, and the tables they store."""

    def __init__(self, docs: DataFrame, words: int, similar: tuple[int, int], radius: int, block: int, frequent: int):
        ship(docs.sparkSession)
        self.spark, self.store = docs.sparkSession, Scratch(docs.sparkSession)
        self.words, self.similar, self.radius, self.block, self.frequent = words, similar, radius, block, frequent
        self.texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_hash(), F.col("text").cast("binary").alias("text"))
        stored = ("v", "fp", "n", "sketch", "sig", "first")
        made = self.texts.mapInArrow(released(_set_batches(words, similar, stored)), f"doc_id long, text_hash long, {self._schema(*stored)}")
        self.rows = self.store.table(made.withColumn("row", F.monotonically_increasing_id()))
        again = self.store.table(self.rows.groupBy("v").agg(F.count("*").alias("rows"), F.min("row").alias("one")).where("rows > 1").select("v", "one"))
        self.sets = self.rows.join(_sent(again), "v", "left").where("one is null or one = row").select("v", "n", "fp", "text_hash", "sketch", "sig", "first")

    @staticmethod
    def _schema(*columns: str) -> str:
        return ", ".join(_SETS[c] for c in columns)

    def made_again(self, asked: DataFrame, *wanted: str, late=None) -> DataFrame:
        """`wanted` of the sets `asked` (v), a stored table, from their texts; a row for each."""
        hashes = self.store.table(self.sets.join(_sent(asked), "v", "left_semi").select("text_hash").distinct())
        texts = self.texts.join(_sent(hashes), "text_hash", "left_semi").select("text")
        made = texts.mapInArrow(released(_set_batches(self.words, self.similar, ("v", *wanted), late)), self._schema("v", *wanted))
        return made.join(_sent(asked), "v", "left_semi").dropDuplicates(["v"])

    def first_pairs(self) -> DataFrame:
        """Candidates (a, b): links of fingerprints, and sets that share one."""
        prints = self.store.table(self.rows.groupBy("fp").agg(F.min("v").alias("v")))
        linked = links(prints.select("fp"), self.radius, self.block)
        a, b = (prints.select(F.col("fp").alias(e), F.col("v").alias(f"v{e}")) for e in ("a", "b"))
        same = self.sets.select("fp", F.col("v").alias("b")).join(prints, "fp").where("b != v").select(F.col("v").alias("a"), "b")
        return linked.join(a, "a").join(b, "b").select(F.col("va").alias("a"), F.col("vb").alias("b")).unionByName(same)

    def marked(self, begun: DataFrame, late: np.ndarray) -> tuple:
        """`late` as sent to the tasks, and `begun` with whether a set begins with any of it."""
        shared = self.spark.sparkContext.broadcast(late)
        return shared, begun.mapInArrow(released(_late_batches(shared)), "v long, n int, first array<long>, late boolean")

    @staticmethod
    def _most(tally: DataFrame) -> np.ndarray:
        """The shingles (h) of the largest counts, a bounded number, sorted."""
        counts = tally.groupBy("h").agg(F.max("count").alias("count")).orderBy(F.desc("count"), "h").limit(FREQUENT_KEPT)
        return np.sort(np.array([r[0] for r in counts.collect()], np.int64))

    def passages(self, begun: DataFrame, late: np.ndarray) -> DataFrame:
        """(h, count) of what else stands often beside `late` shingles: without these, sets would begin with others of a passage.

        Counted over some of the sets that begin with a late one; that changes the work, not the result.
        """
        _, marked = self.marked(begun, late)
        asked = self.store.table(marked.where("late").select("v"))
        share = min(1.0, PASSAGE_SETS / max(1, asked.count()))
        some = self.store.table(asked.where(F.xxhash64(F.lit(3), "v").cast("double") / 2.0**64 + 0.5 <= share))
        counts = self.made_again(some, "s").select(F.explode("s").alias("h")).groupBy("h").count()
        return self.store.table(counts.where(F.col("count") > max(4, self.frequent * share)).select("h", F.floor(F.col("count") / share).cast("long").alias("count")))

    def ordered(self) -> tuple[DataFrame, DataFrame]:
        """(v, n, first) of every set with words, frequent shingles last, and the shingles (h, blocks) many still begin with."""
        begun = self.sets.where("n > 0").select("v", "n", "first")
        tally = self.store.table(begun.select(F.explode("first").alias("h")).groupBy("h").count().where(F.col("count") > self.frequent))
        late = self._most(tally)
        if len(late):
            late = self._most(tally.unionByName(self.passages(begun, late)))
        counts = tally
        if len(late):
            shared, marked = self.marked(begun, late)
            asked = self.store.table(marked.where("late").select("v"))
            again = self.store.table(self.made_again(asked, "n", "first", late=shared))
            begun = marked.where("not late").drop("late").unionByName(again)
            # A shingle that isn't late was counted above or begins at most `frequent` of the sets that stay as they were.
            known = tally.join(F.broadcast(tally.sparkSession.createDataFrame([(int(h),) for h in late], "h long")), "h", "left_anti")
            counts = known.unionByName(again.select(F.explode("first").alias("h")).groupBy("h").count())
        hot = counts.groupBy("h").agg((F.sum("count") + self.frequent).alias("count")).where(F.col("count") > self.block)
        return begun, self.store.table(hot.select("h", F.ceil(F.col("count") / self.block).cast("long").alias("blocks")))

    def shared(self) -> DataFrame:
        """(h, cell, mine, v, n, at) of every first shingle of every set that isn't alone in its cell, as a stored table."""
        begun, hot = self.ordered()
        rows = begun.select("v", "n", F.posexplode("first").alias("at", "h"))
        if hot.isEmpty():
            dealt = rows.withColumns({"cell": F.lit(0).cast("long"), "mine": F.lit(0)})
        else:
            # Blocks of a hot shingle's sets meet in cells, each pair of blocks in one.
            dealt = celled(rows.join(_sent(hot), "h", "left"))
        dealt = dealt.select("h", "cell", "mine", "v", "n", "at")
        return self.store.table(in_cells(dealt).mapInArrow(released(_several_batches), dealt.schema))

    def rooted(self, shared: DataFrame, roots: DataFrame) -> DataFrame:
        return shared.join(_sent(roots), "v", "left").withColumn("root", F.coalesce("root", "v"))

    def all_pairs(self, rooted: DataFrame) -> DataFrame:
        """Edges (a, b) between roots that join those of all similar sets, and of others whose signatures leave it open."""
        signed = rooted.join(self.sets.select("v", "sig"), "v")
        return in_cells(signed).mapInArrow(released(_met_batches(self.similar)), "a long, b long").distinct()

    def in_groups(self, groups: DataFrame, *wanted: str) -> DataFrame:
        """Edges (a, b) that join the sets of each of `groups` (v, root) that are similar, or by their sketches may be."""
        sets = self.made_again(groups.select("v"), "n", "s") if "s" in wanted else self.sets.select("v", "n", *wanted)
        sizes = self.sets.select("v", "n").join(_sent(groups), "v").groupBy("root").agg(F.sum("n").alias("n"), F.count("*").alias("sets"))
        # Blocks of a large group meet in cells, each pair of blocks in one.
        blocks = F.ceil(F.greatest(F.col("n") / GROUP_SHINGLES, F.col("sets") / self.block)).cast("long")
        hot = self.store.table(sizes.select("root", blocks.alias("blocks")).where("blocks > 1"))
        rows = sets.join(_sent(groups), "v").join(_sent(hot), "root", "left")
        return in_cells(celled(rows).select("root", "cell", "v", "n", *wanted), key="root").mapInArrow(released(_group_batches(self.similar)), "a long, b long")

    def joined(self, edges: DataFrame, roots: DataFrame | None = None) -> DataFrame:
        """(v, root) of every set of `edges`, and of `roots`, whose components they join."""
        if roots is None:
            return self.store.table(components(edges).select(F.col("node").alias("v"), "root"))
        known = _sent(roots)
        for e in ("a", "b"):
            own = known.select(F.col("v").alias(e), F.col("root").alias("r"))
            edges = edges.join(own, e, "left").withColumn(e, F.coalesce("r", e)).drop("r")
        # Between components known before only their roots are nodes; a root is its own in `roots` too.
        more = self.store.table(components(edges.where("a != b")).select(F.col("node").alias("root"), F.col("root").alias("to")))
        moved = roots.join(_sent(more), "root", "left").select("v", F.coalesce("to", "root").alias("root"))
        return self.store.table(moved.unionByName(more.select(F.col("root").alias("v"), F.col("to").alias("root"))).distinct())

    def roots(self) -> DataFrame:
        """(doc_id, text_hash, root) of every row."""
        first = self.joined(self.first_pairs())
        groups = self.joined(self.all_pairs(self.rooted(self.shared(), first)), first)
        forget_shuffles(self.spark)
        for wanted in ("sketch", "s"):
            groups = self.joined(self.in_groups(groups, wanted))
            forget_shuffles(self.spark)
        return self.rows.select("doc_id", "text_hash", "v").join(_sent(groups), "v", "left").select("doc_id", "text_hash", F.coalesce("root", "v").alias("root"))


def celled(rows: DataFrame) -> DataFrame:
    """`rows` (v, blocks: null for one) dealt to blocks: a row for each `cell` where its block meets another."""
    blocks = F.coalesce("blocks", F.lit(1).cast("long"))
    each = rows.withColumn("mine", F.pmod(F.xxhash64("v"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)))
    return each.withColumn("cell", F.least("mine", "other") * (1 << 31) + F.greatest("mine", "other"))


def in_cells(rows: DataFrame, key: str = "h") -> DataFrame:
    return rows.repartition(key, "cell").sortWithinPartitions(key, "cell")


def _several_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by (h, cell), those that aren't alone in their cell; holds back one row."""

    def kept(rows: pa.RecordBatch, before: tuple | None, after: tuple | None) -> pa.RecordBatch:
        h, cell = (rows.column(c).to_numpy(zero_copy_only=False) for c in ("h", "cell"))
        same = (h[1:] == h[:-1]) & (cell[1:] == cell[:-1])
        first = (h[0], cell[0]) == before if before else False
        last = (h[-1], cell[-1]) == after if after else False
        return rows.filter(pa.array(np.concatenate(([first], same)) | np.concatenate((same, [last]))))

    held, before = None, None
    for batch in batches:
        if not len(batch):
            continue
        if held is not None:
            yield kept(held, before, (batch.column("h")[0].as_py(), batch.column("cell")[0].as_py()))
            before = (held.column("h")[-1].as_py(), held.column("cell")[-1].as_py())
        held = batch
    if held is not None:
        yield kept(held, before, None)


def _whole_cells(batches: Iterable[pa.RecordBatch], key: str = "h") -> Iterator[dict]:
    """Columns of runs of whole cells, of rows sorted by (key, cell); lists one after another."""

    def columns(parts: list[pa.RecordBatch]) -> dict:
        whole = pa.Table.from_batches(parts)
        out = {c: whole.column(c).to_numpy().astype(np.int64, copy=False) for c in whole.schema.names if c not in ("sig", "sketch", "s")}
        if "sig" in whole.schema.names:
            out["sig"] = np.frombuffer(b"".join(whole.column("sig").to_pylist()), np.uint8).reshape(len(whole), -1)
        if "sketch" in whole.schema.names:
            out["sketch"] = whole.column("sketch").to_pylist()
        if "s" in whole.schema.names:
            out["s"] = np.concatenate([x.flatten().to_numpy(zero_copy_only=False) for x in whole.column("s").chunks])
        return out

    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not len(batch):
            continue
        held.append(batch)
        h, cell = (batch.column(x).to_numpy(zero_copy_only=False) for x in (key, "cell"))
        # The last cell may go on in the next batch.
        same = (h == h[-1]) & (cell == cell[-1])
        if not same.all():
            end = len(batch) - int(np.argmin(same[::-1]))
            yield columns([*held[:-1], batch.slice(0, end)])
            held = [batch.slice(end)]
    if held:
        yield columns(held)


def _met_batches(similar: tuple[int, int], pairs_at_once: int = 1 << 20, signed_at_once: int = 1 << 15, edges_at_once: int = 1 << 20):
    """Over rows sorted by (h, cell): edges that join the roots of all sets that meet and may be similar by their signatures `sig`.

    Before the first place that two similar sets share they have few others, and sizes differ little. Of a pair's shared
    places those that keep to this are the first ones, so that a pair that isn't met at its first is never similar.
    """
    up, down = similar
    a_row = PAIRS_A_ROW

    def kept(x: np.ndarray, y: np.ndarray, c: dict[str, np.ndarray]) -> tuple[np.ndarray, ...]:
        nx, ny = c["n"][x], c["n"][y]
        fine = (c["root"][x] != c["root"][y]) & (down * nx >= up * ny) & (down * ny >= up * nx)
        fine &= (up + down) * (c["at"][x] + c["at"][y]) <= (down - up) * (nx + ny)
        # In a cell of two blocks only pairs across them meet.
        fine &= (c["one_block"][x]) | (c["mine"][x] != c["mine"][y])
        x, y = x[fine], y[fine]
        same = np.concatenate([alike(x[i : i + signed_at_once], y[i : i + signed_at_once], c) for i in range(0, len(x), signed_at_once)] or [np.zeros(0, bool)])
        return x[same], y[same]

    def alike(x: np.ndarray, y: np.ndarray, c: dict[str, np.ndarray]) -> np.ndarray:
        # Of no counter can more be shared than the less of two, but for what the counters don't hold.
        a, b = c["sig"][x], c["sig"][y]
        shared = (np.minimum(a & 15, b & 15) + np.minimum(a >> 4, b >> 4)).sum(1, dtype=np.int64)
        return (up + down) * (shared + c["beyond"][x] + c["beyond"][y]) >= up * (c["n"][x] + c["n"][y])

    def pairs(c: dict[str, np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        starts = _starts(c["h"], c["cell"])
        sizes = np.diff(np.append(starts, len(c["h"])))
        several = (sizes > 1) & (np.minimum.reduceat(c["root"], starts) != np.maximum.reduceat(c["root"], starts))
        small = several & (sizes - 1 <= 2 * a_row)
        s, m = starts[small], sizes[small]
        bounds = np.concatenate(([0], np.cumsum(m * m)))
        at = 0
        while at < len(s):
            to = max(at + 1, int(np.searchsorted(bounds, bounds[at] + pairs_at_once, "right")) - 1)
            n = m[at:to] ** 2
            inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            wide, first = np.repeat(m[at:to], n), np.repeat(s[at:to], n)
            x, y = inner // wide, inner % wide
            first, x, y = first[x < y], x[x < y], y[x < y]
            yield kept(first + x, first + y, c)
            at = to
        for i, size in zip(starts[several & ~small].tolist(), sizes[several & ~small].tolist(), strict=True):
            x, y = _spread(c["root"][i : i + size], lambda x, left, i=i: near(i + x, i + left, c))
            yield i + x, i + y

    def near(x: int, left: np.ndarray, c: dict[str, np.ndarray]) -> np.ndarray:
        out = np.zeros(len(left), bool)
        out[np.searchsorted(left, kept(np.full(len(left), x), left, c)[1])] = True
        return out

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u = v = np.zeros(0, np.int64)
        found, several = [], 0
        for c in _whole_cells(batches):
            c["beyond"] = c["n"] - ((c["sig"] & 15) + (c["sig"] >> 4)).sum(1, dtype=np.int64)
            c["one_block"] = (c["cell"] >> 31) == (c["cell"] & ((1 << 31) - 1))
            for x, y in pairs(c):
                found.append((c["root"][x], c["root"][y]))
                several += len(x)
                if several >= max(edges_at_once, len(u)):
                    u, v = forest(*map(np.concatenate, zip((u, v), *found, strict=True)))
                    found, several = [], 0
        if several:
            u, v = forest(*map(np.concatenate, zip((u, v), *found, strict=True)))
        if len(u):
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["a", "b"])

    return run


def similar_texts(docs: DataFrame, words: int = SIMILAR_WORDS, similar: tuple[int, int] = SIMILAR, radius: int = RADIUS, block: int = 4096, frequent: int = FREQUENT) -> DataFrame:
    """(doc_id, text_hash, root long) of every row, a stored table: root is equal where links of similar shingle sets join two texts."""
    steps = SimilarTexts(docs, words, similar, radius, block, frequent)
    try:
        return cut(steps.roots())
    finally:
        steps.store.close()


def keep_one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The rows of `docs`, all columns, less all but one of each component: the one with the smallest id.

    Of rows that share that id in a component one stays. A component of null ids only keeps one row.
    """
    return _keep_first(docs, near_duplicates(docs, **options))


def keep_one_of_similar(docs: DataFrame, **options) -> DataFrame:
    """As `keep_one_of_each`, over the components of `similar_texts`."""
    return _keep_first(docs, similar_texts(docs, **options))


def _keep_first(docs: DataFrame, found: DataFrame) -> DataFrame:
    first = found.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("absent"), "doc_id", "text_hash")).alias("f"))
    named = first.select(F.col("f.doc_id").alias("doc_id"), F.col("f.text_hash").alias("text_hash"))
    chosen = found.join(named, found["doc_id"].eqNullSafe(named["doc_id"]) & (found["text_hash"] == named["text_hash"]), "left_semi")
    return keep_rows(docs, cut(chosen.groupBy("doc_id", "text_hash").agg((F.count("*") > 1).alias("single"))))
