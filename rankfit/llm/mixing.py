"""Mixing sources to target weights, with DataFrame functions only.

Each document gets a hash-random key. The key's leading bits are its range in the source's order; a source's
documents are sorted within their range, and running totals of words are taken in three levels: in each range, over
the ranges of each block of ranges, over the blocks of each source. Ranges hold about `rows_in_range` rows however
large a source is, so no task sees a whole source. A document is taken where its running total meets what is left of
the source's budget after whole epochs; the document at the cut gives only the words that reach the exact budget.

Targets: sources in code point order, null last, weigh 1, 2, 3, repeating, and share all words; a source stops at
`most_epochs` times its words and the excess goes to the others by weight. Sorted by cap over weight, the common
level is the largest of the levels that each source's position would give, so one pass finds it.

The order hangs on id and text: rows that share both are one entry with a number of copies, which follow each other.
The running totals over the sources themselves are taken in ranges too, so that any number of sources is dealt.

Defined results: a null or word-less text has size 0 and takes nothing. Null ids hash like one more id. Of copies of one
entry at a cut, it isn't said which is cut. Extra columns are ignored by `mixture` and carried by `mixed`. An empty table
gives an empty result.
"""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import Column, DataFrame, Window, functions as F

from rankfit.session import cut

WORD = r"[^\x20\x09-\x0D]+"
SEED = 20_011
MOST_EPOCHS = 3
BROADCAST_SOURCES = 20_000


def words_in(text: Column) -> Column:
    """Number of words of a text; null: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_key(source: Column) -> Column:
    """A key that tells null from every string."""
    return F.when(source.isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), source))


def entries(docs: DataFrame, seed: int = SEED) -> DataFrame:
    """(s: the source's key, key, doc_id, text_hash, size, copies) of every row, equal ones together, as a stored table."""
    rows = docs.select(source_key(F.col("source")).alias("s"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"), words_in(F.col("text")).alias("size"))
    keyed = rows.withColumn("key", F.xxhash64(F.lit(seed), "doc_id", "text_hash"))
    return cut(keyed.groupBy("s", "key", "doc_id", "text_hash", "size").agg(F.count("*").alias("copies")))


def _running(rows: DataFrame, order: list[str], sums: dict[str, str]) -> DataFrame:
    """`rows` with the sum of each column (`sums`: name to column) over the rows up to and with this one, in `order`."""
    parted = cut(rows.repartitionByRange(*order).withColumn("part", F.spark_partition_id()))
    totals = parted.groupBy("part").agg(*[F.sum(c).alias(f"{n}_part") for n, c in sums.items()])
    # One row for each task.
    earlier = Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", *[F.coalesce(F.sum(f"{n}_part").over(earlier), F.lit(0)).alias(f"{n}_base") for n in sums])
    upto = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    inside = parted.select("*", *[F.sum(c).over(upto).alias(n) for n, c in sums.items()])
    whole = inside.join(F.broadcast(bases), "part")
    return whole.withColumns({n: F.col(n) + F.col(f"{n}_base") for n in sums}).select(*rows.columns, *sums)


def targets(rows: DataFrame, most_epochs: int = MOST_EPOCHS) -> DataFrame:
    """(s, source_size long, docs long: entries, target double) of every source, as a stored table of one row for each."""
    sums = rows.groupBy("s").agg(F.sum(F.col("size") * F.col("copies")).alias("source_size"), F.count("*").alias("docs"))
    named = sums.select("*", (F.col("s") == "n").alias("last"), F.lit(1).cast("long").alias("one"))
    weighed = _running(named, ["last", "s"], {"place": "one"}).withColumn("weight", 1 + (F.col("place") - 1) % 3)
    weighed = weighed.withColumn("cap", most_epochs * F.col("source_size")).withColumn("ratio", F.col("cap") / F.col("weight"))
    levelled = cut(_running(weighed.select("s", "source_size", "docs", "weight", "cap", "ratio"), ["ratio", "s"], {"caps": "cap", "weights": "weight"}))
    words, weight = levelled.agg(F.sum("source_size"), F.sum("weight")).first()
    # What is left for this source and all with a higher ratio, for each unit of their weight.
    left, share = F.lit(words) - (F.col("caps") - F.col("cap")), F.lit(weight) - (F.col("weights") - F.col("weight"))
    level = levelled.agg(F.max(left / share)).first()[0]
    return levelled.select("s", "source_size", "docs", F.least(F.col("cap").cast("double"), F.col("weight") * F.lit(level).cast("double")).alias("target"))


def _beside(rows: DataFrame, per_source: DataFrame) -> DataFrame:
    """Join by source: broadcast where the sources are few, else a join whose hot keys Spark can split."""
    small = per_source.count() <= BROADCAST_SOURCES
    return rows.join(F.broadcast(per_source) if small else per_source, "s")


def _before(column: str, *by: str, order: list) -> Column:
    """Sum of `column` over the rows before this one."""
    rows = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return F.coalesce(F.sum(column).over(rows), F.lit(0)).cast("long")


def ordered(rows: DataFrame, per_source: DataFrame, rows_in_range: int = 256) -> DataFrame:
    """`rows` with source_size, target, epochs, rest (words after whole epochs) and before (words that precede them)."""
    total = per_source.agg(F.sum("docs")).first()[0] or 0
    bits = max(1, ceil(log2(max(2, total / rows_in_range))))
    half = bits // 2
    ranged = rows.withColumn("range", F.shiftrightunsigned("key", 64 - bits)).withColumn("words", F.col("size") * F.col("copies"))
    sums = cut(ranged.groupBy("s", "range").agg(F.sum("words").alias("words")))
    blocks = sums.groupBy("s", F.shiftright("range", half).alias("block")).agg(F.sum("words").alias("words"))
    blocks = blocks.select("s", "block", _before("words", "s", order=["block"]).alias("before_block"))
    sums = sums.withColumn("block", F.shiftright("range", half))
    sums = sums.withColumn("before_range", _before("words", "s", "block", order=["range"])).drop("words").join(blocks, ["s", "block"])
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    sums = _beside(sums, per_source).withColumn("epochs", epochs)
    rest = (F.floor(F.col("target") + 0.5) - F.col("epochs") * F.col("source_size")).cast("long")
    sums = sums.select("s", "range", (F.col("before_block") + F.col("before_range")).alias("base"), "source_size", "target", "epochs", rest.alias("rest"))
    inside = ranged.withColumn("inside", _before("words", "s", "range", order=["key", "doc_id", "text_hash"]))
    return inside.join(sums, ["s", "range"]).withColumn("before", F.col("base") + F.col("inside"))


def _cut_words(before: Column) -> Column:
    """Words of the last, partial epoch that a row gives."""
    return F.least(F.greatest(F.col("rest") - before, F.lit(0)), F.col("size")).cast("long")


def mixture(docs: DataFrame, seed: int = SEED, most_epochs: int = MOST_EPOCHS) -> DataFrame:
    """(doc_id, size, source_size, target, taken) of every row of `docs`."""
    rows = entries(docs, seed)
    found = ordered(rows, targets(rows, most_epochs))
    each = found.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)).alias("copy"))
    taken = F.col("epochs") * F.col("size") + _cut_words(F.col("before") + F.col("copy") * F.col("size"))
    return each.select("doc_id", "size", "source_size", "target", taken.cast("long").alias("taken"))


def mixed(docs: DataFrame, seed: int = SEED, most_epochs: int = MOST_EPOCHS) -> DataFrame:
    """The mix itself, with the columns of `docs`: a row for each epoch of each document that is taken.

    The document at a source's cut also gives the first words of its text that the budget still holds (its `text`
    and, if there is one, `n_chars` say so). Texts don't move: a source's cut is one entry, and every document
    compares its own key with it. Copies of the entry at the cut give one row for each epoch; the copies that the rest
    still holds whole, and the cut one, are made from one of them.
    """
    rows = entries(docs, seed)
    found = cut(ordered(rows, targets(rows, most_epochs)))
    order = F.struct((F.col("key") < 0).alias("high"), "key", F.col("doc_id").isNotNull().alias("named"), "doc_id", "text_hash")
    # The first entry that the rest doesn't hold whole; none where it holds all.
    beyond = found.where("size > 0 and before + size * copies > rest")
    first = beyond.groupBy("s").agg(F.min(F.struct("before", order.alias("at"), "size")).alias("c"))
    sources = found.groupBy("s").agg(F.first("epochs").alias("epochs"), F.first("rest").alias("rest"))
    held = F.greatest(F.col("rest") - F.col("c.before"), F.lit(0))
    cuts = cut(sources.join(first, "s", "left").select("s", "epochs", "rest", F.col("c.at").alias("cut_at"), F.floor(held / F.col("c.size")).alias("more"), (held % F.col("c.size")).alias("part")))
    wide = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r"), source_key(F.col("source")).alias("s"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"))
    wide = _beside(wide.withColumn("key", F.xxhash64(F.lit(seed), "doc_id", "text_hash")), cuts).withColumn("at", order)
    wide = wide.where(F.col("r.text").rlike(r"[^\x20\x09-\x0D]"))
    whole = F.col("epochs") + F.when(F.col("cut_at").isNull(), (F.col("rest") > 0).cast("long")).when(F.col("at") < F.col("cut_at"), 1).otherwise(0)
    plain = wide.where(whole > 0).select(F.explode(F.array_repeat("r", whole.cast("int"))).alias("r")).select("r.*")
    once = wide.where("at = cut_at and (more > 0 or part > 0)").groupBy("s").agg(F.min("r").alias("r"), F.first("more").alias("more"), F.first("part").alias("part"))
    copies = once.where("more > 0").select("r", F.explode(F.sequence(F.lit(1).cast("long"), F.col("more")))).select("r.*")
    first_words = F.array_join(F.slice(F.regexp_extract_all("r.text", F.lit(r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"), F.lit(0)), 1, F.col("part").cast("int")), "")
    partial = once.where("part > 0").withColumn("r", F.col("r").withField("text", first_words))
    if "n_chars" in docs.columns:
        partial = partial.withColumn("r", F.col("r").withField("n_chars", F.length("r.text").cast(docs.schema["n_chars"].dataType)))
    return plain.unionByName(copies).unionByName(partial.select("r.*"))
