"""Weighted frequent items in at most k - 1 counters.

Each tracked item has a counter `c`, which prunes lower, and a count `chat` since it last entered, which nothing
lowers. A whole batch is absorbed as one exact summary: counters of equal items add, and if more than k - 1 remain the
k-th largest counter is taken off all. Items that reach zero leave with their `chat` for the buckets. A counter falls
short of the true count by at most n / k, so every item above n / k is tracked.
"""

from __future__ import annotations

import numpy as np


def compact(v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values in order with the sums of their weights."""
    if len(v) < 2:
        return v, w.astype(np.int64)
    if (w == 1).all():
        v = np.sort(v)
        first = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
        return v[first], np.diff(np.append(first, len(v)))
    order = np.argsort(v, kind="stable")
    v, w = v[order], w[order]
    first = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
    return v[first], np.add.reduceat(w, first)


class FrequentItems:
    """Tracked items in order of value."""

    def __init__(self, k: int, v: np.ndarray, c: np.ndarray | None = None, chat: np.ndarray | None = None):
        self.k = k
        self.v = v
        self.c = np.zeros(0, np.int64) if c is None else c
        self.chat = np.zeros(0, np.int64) if chat is None else chat

    def absorb(self, v: np.ndarray, w: np.ndarray, chat: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Add distinct ordered items; gives back what the filter doesn't hold, with weights."""
        chat = w if chat is None else chat
        every, at = np.unique(np.concatenate([self.v, v]), return_inverse=True)
        c, total = np.zeros(len(every), np.int64), np.zeros(len(every), np.int64)
        for place, counts, sums in ((at[: len(self.v)], self.c, self.chat), (at[len(self.v) :], w, chat)):
            c[place] += counts
            total[place] += sums
        if len(every) >= self.k:
            c = c - np.partition(c, len(c) - self.k)[len(c) - self.k]
        stay = c > 0
        self.v, self.c, self.chat = every[stay], c[stay], total[stay]
        return every[~stay], total[~stay]

    def merge(self, other: FrequentItems) -> tuple[np.ndarray, np.ndarray]:
        return self.absorb(other.v, other.c, other.chat)

    def compress(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Drop items below n / (2 k); gives them back with weights."""
        few = self.chat < n / (2 * self.k)
        out = self.v[few], self.chat[few]
        self.v, self.c, self.chat = self.v[~few], self.c[~few], self.chat[~few]
        return out

    @property
    def weight(self) -> int:
        return int(self.chat.sum())
