"""Token ids and counts of the byte-level BPE vocabulary, by chunks that repeat.

The vocabulary's pattern never lets a token cross the place before a single space between two other characters, so
a text is cut there into chunks and each distinct chunk is encoded once in a worker while the cache holds it. Where
white space stands side by side the cut is made by a pattern, else by a plain split. Chunks of letters that the two
libraries class alike are encoded by tiktoken, whose merges are the same; all others, and those that hold the special
token's string, by tokenizers itself.
"""

from __future__ import annotations

import base64
import re
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

VOCABULARY = "byte_bpe_50k.json"
RANKS = "byte_bpe_50k.tiktoken"
SPECIAL = "<|endoftext|>"
END = 2
#: Below this code point the libraries' character classes are the same.
PLAIN_BELOW = "԰"

_beside_space = re.compile(r" \s|\s ")
_lone_space = re.compile(r"(?<=\S) (?=\S)")


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(maxsize=2)
def library_tokenizer(path: str | None = None):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path or vocabulary_path(VOCABULARY))
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


@lru_cache(maxsize=1)
def ranks() -> dict[bytes, int]:
    with open(vocabulary_path(RANKS), "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


@lru_cache(maxsize=1)
def plain_encoding():
    import public_tokenizers
    import tiktoken

    return tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks(), special_tokens={})


def chunks(text: str) -> list[str]:
    """Pieces of `text` that are encoded alone; the spaces between them belong to the front of the later ones."""
    if _beside_space.search(text):
        return _lone_space.split(text)
    if text[:1] == " " or text[-1:] == " ":
        return _lone_space.split(text)
    return text.split(" ")


def encode(chunk: str) -> list[int]:
    if SPECIAL not in chunk and (chunk.isascii() or max(chunk) < PLAIN_BELOW):
        return plain_encoding().encode_ordinary(chunk)
    return library_tokenizer().encode(chunk, add_special_tokens=False).ids


class Cache(dict):
    """Values of chunks, in two generations of at most `bound` entries: those used again outlive a turn."""

    def __init__(self, make, bound: int):
        super().__init__()
        self.make, self.bound, self.old = make, bound, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(self) >= self.bound:
            self.old = dict(self)
            self.clear()
        if len(key) <= 64:
            self[key] = value
        return value


#: What follows a run of letters is a piece, or pieces, of its own.
_lead = regex.compile(r"\p{L}+")


def _plain(chunk: str) -> bool:
    return (chunk.isascii() or max(chunk) < PLAIN_BELOW) and SPECIAL not in chunk


#: Characters of the texts whose chunks are looked up together.
TOGETHER = 1 << 21


def _tables(texts: list[str | None], alone, spaced: Cache, whole) -> list[bytes]:
    """For each text the values of its chunks, one after another: `whole` of it, but with a look-up for each distinct chunk."""
    out: list[bytes] = [b""] * len(texts)
    plain, held = [], 0
    for i, text in enumerate(texts):
        if not text:
            continue
        if text[0] == " " or text[-1] == " " or _beside_space.search(text):
            out[i] = whole(text)
            continue
        plain.append(i)
        held += len(text)
        if held >= TOGETHER:
            _look_up(texts, plain, out, alone, spaced)
            plain, held = [], 0
    if plain:
        _look_up(texts, plain, out, alone, spaced)
    return out


def _look_up(texts: list[str | None], plain: list[int], out: list[bytes], alone, spaced: Cache) -> None:
    lists = pc.split_pattern(pa.array([texts[i] for i in plain], pa.large_string()), " ")
    bounds = lists.offsets.to_numpy()
    words = lists.values.dictionary_encode()
    at = words.indices.to_numpy().astype(np.int64)
    heads = bounds[:-1]
    # Each text's first chunk has no space before it, so it has an entry of its own.
    first = [alone[w] for w in lists.values.take(pa.array(heads)).to_pylist()]
    at[heads] = len(words.dictionary) + np.arange(len(plain))
    used = np.zeros(len(words.dictionary), bool)
    used[at[at < len(used)]] = True
    entries = [spaced[w] if u else b"" for w, u in zip(words.dictionary.to_pylist(), used.tolist(), strict=True)] + first
    ends = np.cumsum([0, *map(len, entries)]) // 4
    table = pa.LargeListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(entries), "<i4")))
    raw = table.take(pa.array(at)).flatten().to_numpy().tobytes()
    sizes = np.concatenate(([0], np.cumsum(np.diff(ends)[at])))[bounds] * 4
    for i, a, b in zip(plain, sizes[:-1].tolist(), sizes[1:].tolist(), strict=True):
        out[i] = raw[a:b]


def _ids(chunk: str) -> bytes:
    return array("I", encode(chunk)).tobytes()


def _spaced_ids(chunk: str) -> bytes:
    if chunk.isalpha() and (chunk.isascii() or max(chunk) < PLAIN_BELOW):
        # Letters and the space before them are one piece of the pattern.
        return array("I", _encode_piece()(b" " + chunk.encode())).tobytes()
    return _ids(" " + chunk)


@lru_cache(maxsize=1)
def _encode_piece():
    return plain_encoding()._core_bpe.encode_single_piece


@lru_cache(maxsize=1)
def _id_caches() -> tuple[Cache, Cache]:
    return Cache(_ids, 50_000), Cache(_spaced_ids, 80_000)


def token_bytes(text: str | None) -> bytes:
    """Ids of a text as little-endian unsigned 32-bit numbers."""
    if not text:
        return b""
    first, spaced = _id_caches()
    head, *rest = chunks(text)
    return first[head] + b"".join([spaced[c] for c in rest])


def token_bytes_of(texts: list[str | None]) -> list[bytes]:
    """As `token_bytes` of each text."""
    return _tables(texts, *_id_caches(), token_bytes)


@lru_cache(maxsize=1)
def _widths() -> np.ndarray:
    """Bytes of each token."""
    out = np.zeros(max(ranks().values()) + 1, np.int64)
    for token, rank in ranks().items():
        out[rank] = len(token)
    return out


def offsets(text: str, ids: np.ndarray) -> np.ndarray:
    """(start, end) in characters of each token of a text without the special token's string; tokens may share one."""
    ends = np.cumsum(_widths()[ids])
    starts = ends - _widths()[ids]
    if not text.isascii():
        character = np.cumsum((np.frombuffer(text.encode(), np.uint8) & 0xC0) != 0x80)
        starts, ends = character[starts] - 1, character[ends - 1]
    return np.stack([starts, ends], 1)


# Prefix counts -----------------------------------------------------------------------------------------------------


@lru_cache(maxsize=1)
def _longest() -> int:
    return max(map(len, ranks()))


#: Whether neighbouring tokens (left, right as one number) stay as they are; a left of 0xFFFF stands for a piece's start.
_apart: dict[int, bool] = {}
_APART_BOUND = 1 << 20
_stems: dict[bytes, tuple] = {}
_STEM, _STEMS_BOUND = 6, 1 << 17


def _stays(left: int, right: int, before: bytes, token: bytes) -> bool:
    """True if the vocabulary encodes the two tokens' bytes as these two tokens (at the start: this one)."""
    if len(_apart) >= _APART_BOUND:
        _apart.clear()
    found = plain_encoding()._core_bpe.encode_single_piece(before + token) == ([left, right] if before else [right])
    _apart[left << 16 | right] = found
    return found


def piece_prefix_counts(piece: bytes) -> list[int]:
    """Token counts of every byte prefix of one pre-token, by dynamic programming over each prefix's last token.

    A prefix's encoding ends in a token; what stands before it is the encoding of a shorter prefix, and a sequence of
    tokens is an encoding if each neighbouring pair is. So just one last token fits. It is looked for where it mostly
    is, at the last token of the prefix one byte shorter or as one byte, and then among all suffixes.
    """
    known, longest, apart = ranks(), _longest(), _apart
    # Pieces that begin alike share that part of their tables.
    shared = piece[:_STEM] if len(piece) > _STEM else b""
    found = _stems.get(shared)
    last, begin, count = ([*x] for x in found) if found else ([0xFFFF], [0], [0])
    for end in range(len(count), len(piece) + 1):
        near = begin[-1]
        start = near
        rest = None
        while True:
            token = piece[start:end]
            rank = known.get(token)
            if rank is not None:
                left = last[start]
                fits = apart.get(left << 16 | rank)
                if fits is None:
                    fits = _stays(left, rank, piece[begin[start] : start] if start else b"", token)
                if fits:
                    break
            if rest is None:
                rest = iter([end - 1, *(i for i in range(max(0, end - longest), end - 1) if i != near)])
            start = next(rest)
        last.append(rank)
        begin.append(start)
        count.append(count[start] + 1)
        if end == _STEM and shared:
            if len(_stems) >= _STEMS_BOUND:
                _stems.clear()
            _stems[shared] = (tuple(last), tuple(begin), tuple(count))
    return count


@lru_cache(maxsize=1)
def _pattern():
    import public_tokenizers

    return regex.compile(public_tokenizers.PATTERN)


def _pieces(segment: str) -> list[str]:
    """Pre-tokens of a text without the special token's string."""
    if segment.isascii() or max(segment) < PLAIN_BELOW:
        return _pattern().findall(segment)
    return [segment[a:b] for _, (a, b) in library_tokenizer().pre_tokenizer.pre_tokenize_str(segment)]


def chunk_prefix_counts(chunk: str) -> np.ndarray:
    """Token counts of every character prefix of a chunk taken alone, without the empty one."""
    out: list[int] = []
    base = 0
    segments = chunk.split(SPECIAL)
    for number, segment in enumerate(segments):
        pieces = _pieces(segment) if segment else []
        for at, piece in enumerate(pieces):
            raw = piece.encode()
            counts = piece_prefix_counts(raw)
            if len(raw) != len(piece):
                counts = [0] + [counts[i] for i in np.cumsum([len(c.encode()) for c in piece]).tolist()]
            if piece[0] == "'" and len(piece) == 3:
                # The first letters of 're, 've and 'll alone are a mark and a word.
                counts[2] = len(encode(piece[:2]))
            out += [base + c for c in counts[1:]]
            if at and piece[0].isspace() and pieces[at - 1].isspace():
                # A prefix that ends in white space gives all of it to one run.
                run = pieces[at - 1] + piece[0]
                start = base - len(encode(pieces[at - 1]))
                out[len(out) - len(piece)] = start + len(encode(run))
            base += counts[-1]
        if number + 1 < len(segments):
            # While it is incomplete, the special string is text that may join what stands before it.
            tail = "".join(pieces[-2:])
            start = base - (len(encode(tail)) if tail else 0)
            out += [start + len(encode(tail + SPECIAL[:i])) for i in range(1, len(SPECIAL))]
            base += 1
            out.append(base)
    return np.array(out, np.int64)


_ONE = (1).to_bytes(4, "little")


def _letters(piece: str) -> bytes:
    """Steps of one pre-token of plain letters and the space before them."""
    counts = piece_prefix_counts(piece.encode())
    if not piece.isascii():
        places, at = [0], 0
        for c in piece:
            at += 1 if c < "\x80" else 2
            places.append(at)
        counts = [counts[i] for i in places]
    return array("i", map(int.__sub__, counts[1:], counts[:-1])).tobytes()


def _steps(chunk: str) -> bytes:
    """Steps of a chunk without a space before it. What follows a run of letters, or a lone line feed, stands alone."""
    if not chunk:
        return b""
    if _plain(chunk):
        alone = _step_caches()[0]
        lead = _lead.match(chunk)
        if lead and lead.end() == len(chunk):
            return _letters(chunk)
        if lead:
            return alone[lead[0]] + alone[chunk[lead.end() :]]
        if "\n" in chunk:
            parts = chunk.split("\n")
            if all(parts[1:-1]) and not any(p and (p[0].isspace() or p[-1].isspace()) for p in parts):
                return _ONE.join([alone[p] if p else b"" for p in parts])
    return np.diff(chunk_prefix_counts(chunk), prepend=0).astype("<i4").tobytes()


def _spaced_steps(chunk: str) -> bytes:
    if chunk and _plain(chunk):
        lead = _lead.match(chunk)
        if lead and lead.end() == len(chunk):
            return _letters(" " + chunk)
        if lead:
            alone, spaced = _step_caches()
            return spaced[lead[0]] + alone[chunk[lead.end() :]]
    return np.diff(chunk_prefix_counts(" " + chunk), prepend=0).astype("<i4").tobytes()


@lru_cache(maxsize=1)
def _step_caches() -> tuple[Cache, Cache]:
    return Cache(_steps, 50_000), Cache(_spaced_steps, 100_000)


def prefix_steps(text: str | None) -> bytes:
    """By how much each character of a text changes the token count of its prefix; signed 32-bit little-endian."""
    if not text:
        return b""
    first, spaced = _step_caches()
    head, *rest = chunks(text)
    return first[head] + b"".join([spaced[c] for c in rest])


def prefix_steps_of(texts: list[str | None]) -> list[bytes]:
    """As `prefix_steps` of each text."""
    return _tables(texts, *_step_caches(), prefix_steps)
