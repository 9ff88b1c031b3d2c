"""Exact duplicates by a tree merge of sorted digest runs, with DataFrame functions only.

Every partition of the input is a run of (digest, length) keys. In each round, `fanout` neighbouring runs of the
binomial tree meet in one: a row's run number loses log2(fanout) bits, and the runs are sorted and merged by key,
which keeps the smallest identifier and the number of copies of each key. The first merge happens before any row
moves (a partial aggregate), so a group of copies, however large, sends one row from each task. The last round
leaves one run with one row for each distinct text. A key is the SHA-256 of the normalised text and its length.

Defined results: a null text counts as empty. Of equal texts the row with the smallest doc_id stays; null ids come
last, and of rows that share that id one stays. Repeated rows each give a row, at most one of them kept. Extra
columns are ignored by `duplicate_groups` and carried by `keep_first`. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from rankfit.session import cut

WHITE_SPACE = r"[\x20\x09-\x0D]+"


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), WHITE_SPACE, " ")


def digests(docs: DataFrame) -> DataFrame:
    """(doc_id, row long: a number for the row, run, digest binary, length) of every row, as a stored table."""
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), normalised(F.col("text")).alias("text"))
    keyed = text.select("doc_id", F.unhex(F.sha2("text", 256)).alias("digest"), F.octet_length("text").alias("length"))
    return cut(keyed.select("doc_id", F.monotonically_increasing_id().alias("row"), F.spark_partition_id().alias("run"), "digest", "length"))


def merge_runs(rows: DataFrame, fanout: int = 16) -> DataFrame:
    """(digest, length, first struct<absent, doc_id, row>, group_size): the tree's last run."""
    bits = fanout.bit_length() - 1
    if fanout != 1 << bits or bits < 1:
        raise ValueError("fanout is a power of two")
    last = rows.agg(F.max("run")).first()[0] or 0
    runs = rows.select("run", "digest", "length", F.struct(F.col("doc_id").isNull().alias("absent"), "doc_id", "row").alias("first"), F.lit(1).cast("long").alias("n"))
    while True:
        runs = runs.groupBy(F.shiftright("run", bits).alias("run"), "digest", "length").agg(F.min("first").alias("first"), F.sum("n").alias("n"))
        last >>= bits
        if not last:
            return cut(runs.select("digest", "length", "first", F.col("n").alias("group_size")))


def duplicate_groups(docs: DataFrame, fanout: int = 16) -> DataFrame:
    """(doc_id, keep_id, group_size long, kept boolean, text_sha256 string) of every row."""
    rows = digests(docs)
    merged = merge_runs(rows, fanout)
    joined = rows.join(merged, ["digest", "length"])
    return joined.select(
        "doc_id", F.col("first.doc_id").alias("keep_id"), "group_size",
        (F.col("row") == F.col("first.row")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"),
    )


def keep_first(docs: DataFrame, fanout: int = 16) -> DataFrame:
    """The rows of `docs`, all columns, less every copy of a text but the one that stays."""
    rows = digests(docs)
    first = merge_runs(rows, fanout).select(F.col("first.doc_id").alias("kept_id"), F.col("digest").alias("kept_digest"), F.col("length").alias("kept_length"))
    twice = cut(rows.groupBy("doc_id", "digest", "length").count().where("count > 1"))
    marked = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r"), F.col("doc_id").cast("long").alias("id"), normalised(F.col("text")).alias("t"))
    marked = marked.select("r", "id", F.unhex(F.sha2("t", 256)).alias("digest"), F.octet_length("t").alias("length"))
    same = F.col("id").eqNullSafe(F.col("kept_id")) & (F.col("digest") == F.col("kept_digest")) & (F.col("length") == F.col("kept_length"))
    left = marked.join(first, same, "left_semi")
    if twice.isEmpty():
        return left.select("r.*")
    again = twice.select(F.col("doc_id").alias("kept_id"), F.col("digest").alias("kept_digest"), F.col("length").alias("kept_length"))
    once, several = left.join(again, same, "left_anti"), left.join(again, same, "left_semi")
    return once.select("r.*").unionByName(several.groupBy("id", "digest", "length").agg(F.min("r").alias("r")).select("r.*"))


ORACLE = """
WITH t AS (
  SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')) AS text_sha256 FROM documents
), g AS (
  SELECT text_sha256, min(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY text_sha256
)
SELECT t.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, t.doc_id = g.keep_id AS kept, t.text_sha256
FROM t JOIN g USING (text_sha256)
"""
