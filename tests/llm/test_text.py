import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from rankfit.llm import byte_bpe, chat_format, compression_language, packing, queries, rule_forest, token_counts


@pytest.fixture(scope="module")
def library():
    return byte_bpe.library_tokenizer()


PARTS = ["a", "the", " ", "  ", "\n", "\t", " \n", "é", "ß", "don't", "'re", "'ll", "'v", "'", "!!!", "12", "345", "<|endoftext|>", "<|endo", "中", "文字", "😀", "ñ", "ing", "\r\n", "\x1c", "　", "A", "-", "_", " x"]


def test_tokens_and_prefix_counts_equal_the_library(library):
    pick = random.Random(5)
    for _ in range(600):
        text = "".join(pick.choice(PARTS) for _ in range(pick.randint(1, 16)))
        ids = library.encode(text, add_special_tokens=False).ids
        assert np.frombuffer(byte_bpe.token_bytes(text), "<u4").tolist() == ids
        steps = byte_bpe.prefix_steps(text)
        truth = [len(library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
        assert token_counts.counts(steps).tolist() == truth
        budget = pick.randint(0, 8)
        assert token_counts.longest_within(steps, budget) == max(i for i, n in enumerate(truth) if n <= budget)


def test_texts_together_equal_each_alone(library):
    pick = random.Random(6)
    texts = [None, "", " ", *(" ".join("".join(pick.choice(PARTS) for _ in range(pick.randint(1, 5))) for _ in range(pick.randint(1, 30))) for _ in range(300))]
    assert byte_bpe.token_bytes_of(texts) == [byte_bpe.token_bytes(t) for t in texts]
    assert byte_bpe.prefix_steps_of(texts) == [byte_bpe.prefix_steps(t) for t in texts]
    for text in texts:
        if text and "<|" not in text:
            found = library.encode(text, add_special_tokens=False)
            got = byte_bpe.offsets(text, np.frombuffer(byte_bpe.token_bytes(text), "<i4"))
            at = 0
            for (a, b), token in zip(got.tolist(), byte_bpe.plain_encoding().decode_tokens_bytes(found.ids), strict=True):
                # Exactly the characters that have bytes of the token.
                before, through = text.encode()[:at], text.encode()[: at + len(token)]
                at += len(token)
                assert (a, b) == (len(before.decode(errors="ignore")), len(through.decode(errors="replace")))


def test_loss_masks_against_brute_force():
    pick = random.Random(7)
    for _ in range(60):
        turns = [(pick.choice(["user", "assistant", "a<turn:>\n\n"]), "".join(pick.choice([*PARTS, "</turn>", "\\", "<|"]) for _ in range(pick.randint(0, 12)))) for _ in range(pick.randint(1, 6))]
        text, spans = chat_format.render(turns)
        assert chat_format.parse(text) == turns
        tokens = byte_bpe.offsets(text, np.frombuffer(byte_bpe.token_bytes(text), "<i4"))
        mask, pieces = chat_format.overlaps(tokens, spans)
        under = {i for a, b in spans.tolist() for i in range(a, b)}
        assert mask.tolist() == [any(i in under for i in range(a, b)) for a, b in tokens.tolist()]
        assert {i for a, b in pieces.tolist() for i in range(a, b)} == under
        assert chat_format.unescaped("".join(text[a:b] for a, b in pieces.tolist())) == "".join(t for r, t in turns if r == "assistant")


def test_chat_on_odd_tables(spark):
    schema = "conv_id long, turn long, role string, text string, formatted string, turns int, t int"
    assert chat_format.digests(chat_format.format_conversations(spark.createDataFrame([], schema))).count() == 0
    long = "word " * 60_000
    rows = [(None, None, None, None, "x", 1, 2), (1, 2, "assistant", long, "x", 1, 2), (1, 1, "user", "", "x", 1, 2), (1, 1, "user", "", "x", 1, 2), (2, 0, "assistant", None, None, None, None)]
    got = {r.conv_id: r for r in chat_format.digests(chat_format.format_conversations(spark.createDataFrame(rows, schema))).collect()}
    assert {k: (v.n_turns, v.loss_chars) for k, v in got.items()} == {None: (1, 0), 1: (3, len(long)), 2: (1, 0)}


def test_character_classes_agree_below_the_plain_bound(library):
    plain = byte_bpe.plain_encoding()
    for code in range(1, ord(byte_bpe.PLAIN_BELOW)):
        text = f"a{chr(code)}1{chr(code)}.{chr(code)} {chr(code)}b {chr(code)}{chr(code)}"
        assert plain.encode_ordinary(text) == library.encode(text, add_special_tokens=False).ids


def test_token_counts(odd, documents, none, library):
    for df in (odd, documents):
        rows = df.collect()
        want = sorted(((r.doc_id, len((r.text or "").encode()), n := len(library.encode(r.text or "", add_special_tokens=False).ids), n > 1024) for r in rows), key=str)
        assert sorted(map(tuple, token_counts.token_counts(df).collect()), key=str) == want
    assert token_counts.token_counts(none).count() == 0


def best_fit_decreasing(lengths):
    room = []
    for n in sorted(lengths, reverse=True):
        fits = [i for i, r in enumerate(room) if r >= n]
        if fits:
            room[min(fits, key=room.__getitem__)] -= n
        else:
            room.append(1024 - n)
    return len(room)


def test_packing(odd, documents, none, library):
    for df in (odd, documents):
        rows = packing.pack(df).collect()
        by_sequence = defaultdict(list)
        for r in rows:
            by_sequence[r.sequence_id].append((r.offset, r.length))
        for parts in by_sequence.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 1024
        assert len(by_sequence) <= 1.01 * best_fit_decreasing([r.length for r in rows])
        want = Counter()
        for d in df.collect():
            ids = library.encode(d.text or "", add_special_tokens=False).ids + [2]
            first = len(ids) - 1024 * ((len(ids) - 1) // 1024)
            for piece, (a, b) in enumerate(zip([0, *range(first, len(ids), 1024)], range(first, len(ids) + 1, 1024), strict=False)):
                want[(d.doc_id, piece, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes()))] += 1
        assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == want
    whole = packing.sequences(documents).collect()
    assert all(len(s.ids) == 4 * s.n_tokens <= 4096 for s in whole)
    assert packing.pack(none).count() == 0


def test_fullest_combination_is_optimal():
    pick = random.Random(2)
    for _ in range(200):
        stock = {pick.randint(1, 60): pick.randint(1, 3) for _ in range(pick.randint(1, 6))}
        room = pick.randint(1, 100)
        sums = {0}
        for k, n in stock.items():
            sums = {s + k * i for s in sums for i in range(n + 1) if s + k * i <= room}
        got = packing.fullest(stock, room)
        assert all(n <= stock[k] for k, n in got.items())
        assert sum(k * n for k, n in got.items()) == max(sums)


def rules_brute(text):
    words = re.findall("[^\x20\x09-\x0d]+", text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search("[^\x20\x09-\x0d]", line):
            dup += line in seen
            seen.add(line)
    windows = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    hit = {j for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    return len(words), sum(map(len, words)), len(re.findall("[#*$%&|<>]", text or "")), dup, len(hit)


def test_rules(odd, documents, labels, none):
    for df in (odd, documents):
        got = rule_forest.judged(df, labels).collect()
        want = []
        for r in df.collect():
            n, chars, symbols, dup, again = rules_brute(r.text)
            want.append((r.doc_id, n, chars, symbols, dup, again, n < 50 or 100 * again > 50 * n))
        assert sorted((tuple(r)[:7] for r in got), key=str) == sorted(want, key=str)
        assert not any(r.kept and r.base_failed for r in got)
    quality = {r.doc_id: r.quality for r in labels.collect()}
    kept = {r.doc_id: r.kept for r in rule_forest.judged(documents, labels).collect() if not r.base_failed}
    good = [kept[d] for d, q in quality.items() if q and d in kept]
    assert sum(good) >= 0.95 * len(good)
    assert rule_forest.judged(none, labels).count() == 0


def test_forest_isolates_outliers():
    random_rows = np.random.default_rng(1).normal(size=(1000, 3))
    forest = rule_forest.grow(random_rows)
    score = rule_forest.scores(forest, np.array([[0.0, 0, 0], [9, 9, 9]]))
    assert score[0] < 0.5 < score[1]


def test_languages(odd, documents, none):
    got = compression_language.identified(documents).collect()
    truth = {r.doc_id: r.lang for r in documents.collect()}
    held = [r for r in got if r.held_out and truth[r.doc_id]]
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) >= 0.97 * len(held)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    texts = Counter((r.doc_id, r.text is None or not any(c.isalpha() for c in r.text)) for r in odd.collect())
    assert Counter((r.doc_id, r.lang_pred == "und") for r in compression_language.identified(odd).collect()) == texts
    assert compression_language.identified(none).count() == 0


def test_chat_round_trip(spark):
    texts = [r"\### Assistant: </turn> ok", "", None, "<turn:user>\nhi\n</turn>\n", "a\\lb <|endoftext|>", "\n\n x \n", "文字😀é", "\\", "<", " "]
    rows = [(c, t, ("user", "assistant", None, "a>b\nc")[(c + t) % 4], texts[(c * 3 + t) % len(texts)]) for c in range(12) for t in range(5)]
    df = spark.createDataFrame([*rows, (None, None, None, None), (3, None, "assistant", "null turn")], "conv_id long, turn long, role string, text string")
    formatted = chat_format.format_conversations(df).collect()
    source = defaultdict(list)
    for r in df.collect():
        source[r.conv_id].append((r.turn is not None, r.turn or 0, r.role is not None, r.role or "", r.text is not None, r.text or ""))
    for f in formatted:
        turns = [(x[3], x[5]) for x in sorted(source[f.conv_id])]
        assert chat_format.parse(f.formatted) == turns
        loss = chat_format.unescaped("".join(f.formatted[s.start : s.end] for s in f.loss_spans))
        assert loss == "".join(t for role, t in turns if role == "assistant")
        assert len(f.token_ids) == len(f.loss_mask) and 50256 not in f.token_ids


def test_chat_query_on_a_table(spark):
    got = queries.op1_chat_format(spark, "/root/testdata/sf0.001").collect()
    assert {r.conv_id for r in got} >= {-7} and all(r.loss_chars <= r.formatted_chars for r in got)
