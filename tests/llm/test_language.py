import regex
import zstandard
from pyspark.sql import functions as F

from rankfit.llm import compression_language as language


def dictionaries_brute(rows, texts=language.TEXTS, parts=language.DICTIONARIES, size=language.DICTIONARY_BYTES, chars=language.TEXT_CHARS):
    """From (lang, text, h) of all rows that may be learned from."""
    kinds = {}
    for lang, text, h in rows:
        kinds.setdefault(lang, {})[h] = text
    out = {}
    for lang in sorted(kinds, key=lambda x: (-sum(r[0] == x for r in rows), x)):
        cuts = []
        for h, text in sorted(kinds[lang].items())[:texts]:
            start = h % max(1, len(text) - chars + 1)
            cuts.append(regex.sub(r"[^\p{L}\p{M}]+", " ", text[start : start + chars].lower()).strip().encode())
        usable = [d for d in (language.filled(cuts[i::parts], size) for i in range(parts)) if len(d) >= 8]
        if usable:
            out[lang] = (usable * parts)[:parts]
    return out


def verdict_brute(text, dictionaries):
    if text is None or not regex.search(r"\p{L}", text) or not dictionaries:
        return "und"
    raw = regex.sub(r"[^\p{L}\p{M}]+", " ", text.lower()).strip().encode()
    blocks = [raw[i : i + language.BLOCK] for i in range(0, len(raw), language.BLOCK)]
    total = dict.fromkeys(dictionaries, 0)
    for i in range(language.DICTIONARIES):
        for lang, own in dictionaries.items():
            data = zstandard.ZstdCompressionDict(own[i], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            press = zstandard.ZstdCompressor(level=language.LEVEL, dict_data=data, write_content_size=False, write_checksum=False, write_dict_id=False)
            total[lang] += sum(len(press.compress(b)) for b in blocks)
        ranked = sorted(total.values())
        if len(ranked) < 2 or 8 * (ranked[1] - ranked[0]) >= language.NARROW_BITS * len(blocks):
            break
    return min(total, key=total.get)


def learnable(df):
    h = F.xxhash64(F.lit(11), F.col("text"), F.col("doc_id"))
    return [tuple(r) for r in df.where("lang is not null and text is not null and not coalesce(crc32(cast(doc_id as string)) % 4 = 2, false)").select("lang", "text", h).collect()]


def test_language_against_brute_force(odd, documents, none):
    for df in (odd, documents):
        dictionaries = dictionaries_brute(learnable(df))
        assert language.learn(df) == dictionaries and language.learn(df.repartition(7)) == dictionaries
        texts = sorted(((r.doc_id, r.text) for r in df.collect()), key=str)
        got = language.identified(df).collect()
        assert sorted(((r.doc_id, r.lang_pred) for r in got), key=str) == sorted(((i, verdict_brute(t, dictionaries)) for i, t in texts), key=str)
        assert all(0 <= r.score <= 1 for r in got)
    assert language.identified(none).count() == 0


def test_clashing_names_null_ids_and_one_language(spark, documents):
    plain = documents.select("doc_id", "text", "lang")
    clashing = plain.withColumns({c: F.lit(1) for c in ("n", "h", "kinds", "rows", "t", "id", "place")})
    assert language.learn(clashing) == language.learn(plain)
    nameless = plain.withColumn("doc_id", F.lit(None).cast("long"))
    assert set(language.learn(nameless)) == {r.lang for r in plain.where("lang is not null").select("lang").distinct().collect()}
    copies = spark.createDataFrame([(None, "the same words in each of them", "en")] * 3000, "doc_id long, text string, lang string")
    assert list(language.learn(copies)) == ["en"]
    assert {r.lang_pred for r in language.identified(copies.limit(5)).collect()} == {"en"}


def test_filled_gives_equal_shares():
    assert language.filled([b"a" * 100, b"b" * 100, b"cc"], 30) == b"a" * 12 + b" " + b"b" * 13 + b" cc"
    assert len(language.filled([b"x" * 9] * 50, 120)) <= 120
    assert language.filled([], 10) == b""
