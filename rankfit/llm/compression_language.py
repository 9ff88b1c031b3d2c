"""Language identification by compression.

For each language, raw-content dictionaries are cut from labelled texts. A text's letters, lower-cased, with one space
for all between them, are cut into blocks; each block is compressed with every language's dictionary, and the language
with the smallest total wins: its dictionary holds the strings the text is made of. Where the margin is narrow, the
languages' further dictionaries, from other texts, add to the totals. A margin that stays below `NARROW_BITS` for each
block marks the answer as rejected (`narrow_margin`); the best guess stays in `lang_pred`.

Learns only from rows with a language and a text whose crc32 of the id, as text, leaves another remainder than 2 when
divided by 4; of these, the `texts` different ones of each language that come first by hash of id and text, a documented
bound. Each gives a dictionary an equal share of its bytes, cut from a place in the text that hangs on the hash (out of
at most `text_chars` characters from there on). The language, the source and the id play no part in a prediction, which
reads whole texts.

Defined results: a null text or one without letters is `und` with score 0, as is every text if nothing could be
learned. Rows with a null id are held in (their remainder isn't 2). Ties go to the language with more rows.
Repeated rows each give a row; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from math import exp

import pyarrow as pa
import regex
import zstandard
from pyspark.sql import Column, DataFrame, Window, functions as F

from rankfit.llm.rows import released
from rankfit.session import cut, ship

UNKNOWN = "und"
FOLDS, HELD = 4, 2
DICTIONARIES, DICTIONARY_BYTES, TEXTS, TEXT_CHARS, BLOCK, LEVEL, NARROW_BITS, SCALE = 3, 32_768, 200, 4096, 4096, 9, 32, 0.05

_letter = regex.compile(r"\p{L}")
_between = regex.compile(r"[^\p{L}\p{M}]+")


def letters(text: str) -> bytes:
    return _between.sub(" ", text.lower()).strip().encode()


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % FOLDS == HELD, F.lit(False))


def learn(docs: DataFrame, texts: int = TEXTS, dictionaries: int = DICTIONARIES, size: int = DICTIONARY_BYTES, text_chars: int = TEXT_CHARS, seed: int = 11) -> dict[str, list[bytes]]:
    """Dictionaries of each language."""
    own = docs.select(F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"), F.col("doc_id").cast("long").alias("id"))
    rows = own.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("id"))).withColumn("h", F.xxhash64(F.lit(seed), "text", "id"))
    counts = cut(rows.groupBy("lang").agg(F.count("*").alias("rows"), F.approx_count_distinct("h").alias("kinds")))
    # The lowest share of all hashes holds about twice the texts wanted; of these the first by hash are taken.
    share = F.least(F.lit(1.0), F.lit(2.0 * texts) / F.col("kinds"))
    near = rows.join(F.broadcast(counts) if counts.count() < 10_000 else counts, "lang").where(F.col("h").cast("double") / 2.0**64 + 0.5 <= share)
    start = F.pmod(F.col("h"), F.greatest(F.length("text") - text_chars + 1, F.lit(1))).cast("int") + 1
    near = near.select("lang", "h", F.substring(F.col("text"), start, F.lit(text_chars)).alias("t")).dropDuplicates(["lang", "h"])
    first = near.withColumn("place", F.row_number().over(Window.partitionBy("lang").orderBy("h"))).where(F.col("place") <= texts)
    by_language: dict[str, list[bytes]] = {}
    for row in sorted(first.select("lang", "h", "t").collect(), key=lambda r: (r["lang"], r["h"])):
        by_language.setdefault(row["lang"], []).append(letters(row["t"]))
    rows_of = {r["lang"]: r["rows"] for r in counts.collect()}
    out = {}
    for language, found in sorted(by_language.items(), key=lambda x: (-rows_of[x[0]], x[0])):
        usable = [p for p in (filled(found[i::dictionaries], size) for i in range(dictionaries)) if len(p) >= 8]
        if usable:
            out[language] = (usable * dictionaries)[:dictionaries]
    return out


def filled(parts: list[bytes], size: int) -> bytes:
    """At most `size` bytes with an equal share of each part; what short ones leave goes to the others."""
    left, taken = size, {}
    for n, i in enumerate(sorted(range(len(parts)), key=lambda i: (len(parts[i]), i))):
        taken[i] = min(len(parts[i]), max(0, left // (len(parts) - n) - 1))
        left -= taken[i] + 1
    return b" ".join(parts[i][: taken[i]] for i in range(len(parts)) if taken[i])


class Classifier:
    """Compressors of every language, and their verdict on a text."""

    def __init__(self, learned: dict[str, list[bytes]], level: int = LEVEL, block: int = BLOCK):
        self.languages, self.block = list(learned), block
        self.compress = []
        for language in self.languages:
            own = []
            for content in learned[language]:
                data = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                data.precompute_compress(level=level)
                own.append(zstandard.ZstdCompressor(level=level, dict_data=data, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
            self.compress.append(own)

    def __call__(self, text: str | None) -> tuple[str, float, bool]:
        """Language, score, and whether the margin is too narrow."""
        if text is None or not self.languages or not _letter.search(text):
            return UNKNOWN, 0.0, True
        raw = letters(text)
        blocks = [raw[i : i + self.block] for i in range(0, len(raw), self.block)]
        size = [0] * len(self.languages)
        for compressors in zip(*self.compress, strict=True):
            size = [s + sum(len(c(b)) for b in blocks) for s, c in zip(size, compressors, strict=True)]
            best = min(range(len(size)), key=size.__getitem__)
            bits = [8 * (s - size[best]) for s in size]
            second = min((b for i, b in enumerate(bits) if i != best), default=1 << 30)
            if second >= NARROW_BITS * len(blocks):
                break
        score = 1 / sum(exp(-min(SCALE * b, 700)) for b in bits)
        return self.languages[best], score, second < NARROW_BITS * len(blocks)


def identified(docs: DataFrame, learned: dict[str, list[bytes]] | None = None, **options) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, narrow_margin) of every row of `docs`."""
    ship(docs.sparkSession)
    learned = learn(docs, **options) if learned is None else learned

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classify = Classifier(learned)
        for batch in batches:
            found = [classify(x) for x in batch.column("text").to_pylist()]
            columns = [pa.array([f[i] for f in found], k) for i, k in enumerate((pa.string(), pa.float64(), pa.bool_()))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), *columns], ["doc_id", "held_out", "lang_pred", "score", "narrow_margin"])

    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("string").alias("text"))
    return plain.mapInArrow(released(run), "doc_id long, held_out boolean, lang_pred string, score double, narrow_margin boolean")
