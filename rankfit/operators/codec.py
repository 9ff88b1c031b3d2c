"""Portable binary form of a summary: a versioned header and the raw arrays."""

from __future__ import annotations

import json
import struct
from collections import Counter
from dataclasses import asdict
from functools import lru_cache

import numpy as np

from rankfit.config import AcsConfig
from rankfit.operators.frequent import FrequentItems
from rankfit.operators.kernel import State, axis_dtype

MAGIC, VERSION = b"ACDF", 2


def encode(state: State) -> bytes:
    """Bytes of a state; a finished one has no locks, counters or buffer to carry."""
    v, w = state.buffer
    kind = axis_dtype(state.cfg)
    arrays = [state.t.astype(kind), state.r.astype(float), state.items.v.astype(kind), state.items.chat.astype(np.int64), v.astype(kind), w.astype(np.int64), np.packbits(state.own)]
    if not state.finished:
        arrays += [np.packbits(state.locked), state.items.c.astype(np.int64)]
    head = {
        "cfg": asdict(state.cfg), "k": state.k, "n": state.n, "nulls": state.n_null, "nans": state.n_nan, "end": state.epoch_end, "c": state.c_bound,
        "z": None if np.isinf(state.zeta) else state.zeta, "done": state.finished, "meta": dict(state.meta), "len": [len(state.t), len(state.items.v), len(v)],
    }
    raw = json.dumps(head, separators=(",", ":")).encode()
    return b"".join([MAGIC, struct.pack("<HI", VERSION, len(raw)), raw, *(a.tobytes() for a in arrays)])


def decode(raw: bytes) -> State:
    """The state that `encode` was given; arrays are copies that may be changed."""
    raw = bytes(raw)
    if raw[:4] != MAGIC:
        raise ValueError("not a summary")
    version, size = struct.unpack_from("<HI", raw, 4)
    if version not in (1, VERSION):
        raise ValueError(f"summary version {version} is unknown")
    head = json.loads(raw[10 : 10 + size])
    cfg = AcsConfig(**head["cfg"])
    kind, at = np.dtype(axis_dtype(cfg)), 10 + size
    buckets, items, held = head["len"]

    def read(dtype, n):
        nonlocal at
        out = np.frombuffer(raw, dtype, n, at).copy()
        at += out.nbytes
        return out

    t, r, iv, chat, bv, bw = (read(d, n) for d, n in ((kind, buckets), (float, buckets), (kind, items), (np.int64, items), (kind, held), (np.int64, held)))
    bits = lambda: np.unpackbits(read(np.uint8, -(-buckets // 8)), count=buckets).astype(bool) if buckets else np.zeros(0, bool)
    # The first version didn't tell which thresholds are items.
    own = bits() if version > 1 else np.zeros(buckets, bool)
    locked, c = np.zeros(buckets, bool), chat.copy()
    if not head["done"]:
        locked = bits()
        c = read(np.int64, items)
    state = State(cfg, head["n"], head["nulls"], head["nans"], t, r, locked, own, head["end"], head["c"], float("inf") if head["z"] is None else head["z"], k=head["k"], finished=head["done"], meta=Counter(head["meta"]), items=FrequentItems(head["k"], iv, c, chat))
    state.hold(bv, bw)
    return state


@lru_cache(maxsize=256)
def answers(raw: bytes):
    """Prefix sums of an encoded summary, kept for the summaries asked last."""
    from rankfit.operators.kernel import Answers

    return Answers(decode(raw))


def size_bytes(state: State) -> int:
    """Bytes of a finished summary by the usual count: 16 for each bucket and each frequent item."""
    return 16 * (len(state.t) + len(state.items.v))
