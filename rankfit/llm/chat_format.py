"""Chat formatting with offset-aligned loss masks.

A conversation is rendered whole, encoded once with offsets, and the sorted spans of its assistant texts are met with
the sorted spans of its tokens by binary search. A token counts for the loss if it overlaps such a span; its share of
the text is the overlap, so a token that joins a marker and a text gives only the text.

Template: each turn is a line `<turn:ROLE>`, the text, and a line `</turn>`. Inside texts and roles a backslash is
doubled and the `<` that begins `<turn:`, `</turn>` or `<|` becomes `\\l`; roles also write `>` as `\\g` and a line
feed as `\\n`. So markers stand only where turns begin and end, and `unescaped` gives the exact text back. The special
token's string can't occur.

Defined results: a null text or role is empty. Rows of a conversation go by turn, null turns first; equal turns by
role and text, and repeated rows are repeated turns. A null conversation id is one conversation. A conversation is one
string by nature and so is held by one task. Extra columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from rankfit.llm import byte_bpe
from rankfit.llm.rows import released
from rankfit.session import ship

LOSS_ROLE = "assistant"
CONTROL = ("<turn:", "</turn>", "<|")

_control = re.compile("<(?=turn:|/turn>|[|])")
_escape = re.compile(r"\\(.)", re.S)
_meaning = {"\\": "\\", "l": "<", "g": ">", "n": "\n"}
_turn = re.compile("<turn:([^>\n]*)>\n(.*?)\n</turn>\n", re.S)


def escaped(text: str) -> str:
    return _control.sub(r"\\l", text.replace("\\", "\\\\"))


def escaped_role(role: str) -> str:
    return escaped(role).replace(">", "\\g").replace("\n", "\\n")


def unescaped(text: str) -> str:
    return _escape.sub(lambda m: _meaning[m[1]], text)


def render(turns: list[tuple[str, str]]) -> tuple[str, np.ndarray]:
    """The formatted conversation and the spans (start, end) of its texts under the loss."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"<turn:{escaped_role(role)}>\n", escaped(text)
        parts += [head, body, "\n</turn>\n"]
        if role == LOSS_ROLE and body:
            spans.append((at + len(head), at + len(head) + len(body)))
        at += len(head) + len(body) + 9
    return "".join(parts), np.array(spans, np.int64).reshape(-1, 2)


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted conversation."""
    out, at = [], 0
    for m in _turn.finditer(formatted):
        if m.start() != at:
            raise ValueError("text outside of turns")
        out.append((unescaped(m[1]), unescaped(m[2])))
        at = m.end()
    if at != len(formatted):
        raise ValueError("text outside of turns")
    return out


def overlaps(tokens: np.ndarray, spans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Loss mask over `tokens` (start, end) and the pieces of text under it; both inputs sorted and `spans` disjoint."""
    mask = np.zeros(len(tokens), bool)
    pieces = []
    first = np.searchsorted(tokens[:, 1], spans[:, 0], "right")
    beyond = np.searchsorted(tokens[:, 0], spans[:, 1], "left")
    for (start, end), i, j in zip(spans.tolist(), first.tolist(), beyond.tolist(), strict=True):
        mask[i:j] = True
        # Tokens that share a character overlap; each adds what the ones before it don't cover.
        ends = np.minimum(tokens[i:j, 1], end)
        starts = np.maximum(np.maximum(tokens[i:j, 0], start), np.concatenate(([start], np.maximum.accumulate(ends)[:-1])) if j > i else ends)
        own = np.stack([starts, ends], 1)[ends > starts]
        if len(own):
            new = np.concatenate(([True], own[1:, 0] > own[:-1, 1]))
            pieces.append(np.stack([own[new, 0], own[np.append(np.flatnonzero(new)[1:] - 1, len(own) - 1), 1]], 1))
    return mask, np.concatenate(pieces) if pieces else np.zeros((0, 2), np.int64)


_SCHEMA = "conv_id long, formatted string, token_ids array<int>, loss_mask array<boolean>, loss_spans array<struct<start:int,end:int>>"


def _lists(parts: list[np.ndarray], values: pa.Array) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, parts)]), pa.int32()), values)


def _format_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, turns = batch.column("conv_id"), batch.column("turns")
        for at in range(0, batch.num_rows, 64):
            own = turns.slice(at, 64)
            rows = own.flatten()
            said = zip(rows.field("role").fill_null("").to_pylist(), rows.field("text").fill_null("").to_pylist(), strict=True)
            rendered = [render([next(said) for _ in range(n)]) for n in own.value_lengths().to_pylist()]
            texts = [text for text, _ in rendered]
            tokens = [np.frombuffer(x, "<i4") for x in byte_bpe.token_bytes_of(texts)]
            met = [overlaps(byte_bpe.offsets(text, t), spans) for (text, spans), t in zip(rendered, tokens, strict=True)]
            masks, pieces = [m for m, _ in met], [p for _, p in met]
            every = np.concatenate(pieces).astype(np.int32)
            spans = pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(every[:, 0])), pa.array(np.ascontiguousarray(every[:, 1]))], ["start", "end"])
            columns = [
                ids.slice(at, 64), pa.array(texts, pa.string()), _lists(tokens, pa.array(np.concatenate(tokens))),
                _lists(masks, pa.array(np.concatenate(masks))), _lists(pieces, spans),
            ]
            yield pa.RecordBatch.from_arrays(columns, ["conv_id", "formatted", "token_ids", "loss_mask", "loss_spans"])


def format_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, formatted, token_ids, loss_mask for each token, loss_spans in characters) of every conversation."""
    ship(turns.sparkSession)
    plain = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.struct(F.col("turn"), F.col("role"), F.col("text")).alias("t"))
    whole = plain.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))
    return whole.mapInArrow(released(_format_batches), _SCHEMA)


def _digest_batches(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        lists = batch.column("loss_spans")
        flat = lists.flatten()
        spans = iter(zip(flat.field("start").to_pylist(), flat.field("end").to_pylist(), strict=True))
        for text, n in zip(batch.column("formatted").to_pylist(), lists.value_lengths().to_pylist(), strict=True):
            turns = parse(text)
            loss = unescaped("".join([text[a:b] for a, b in (next(spans) for _ in range(n))]))
            said = "".join(f"{role}\n{said}\n" for role, said in turns)
            rows.append((len(turns), sha256(said.encode()).hexdigest(), len(loss), sha256(loss.encode()).hexdigest(), len(text)))
        columns = [pa.array(x, k) for x, k in zip(zip(*rows, strict=True) if rows else [[]] * 5, (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("conv_id"), *columns], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])


def digests(formatted: DataFrame) -> DataFrame:
    """What a reader of the formatted conversations gets back, as digests."""
    read = formatted.select("conv_id", "formatted", "loss_spans")
    return read.mapInArrow(released(_digest_batches), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


ORACLE = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), e AS (
  SELECT *,
    length(replace(replace(replace(replace(text, '\', '\\'), '<turn:', '\lturn:'), '</turn>', '\l/turn>'), '<|', '\l|'))
    + length(replace(replace(replace(replace(replace(replace(role, '\', '\\'), '<turn:', '\lturn:'), '</turn>', '\l/turn>'), '<|', '\l|'), '>', '\g'), chr(10), '\n'))
    + 17 AS chars
  FROM c
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
