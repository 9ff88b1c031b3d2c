"""Counts in buckets of equal relative width: a bound on the value's error, not on the rank's."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline


class LogBuckets(Baseline):
    """`size` buckets at most: if more are hit, pairs of neighbours join and the relative error grows."""

    def __init__(self, size: int, alpha: float = 0.01):
        super().__init__(size)
        self.log_base = float(np.log((1 + alpha) / (1 - alpha)))
        self.counts: dict[int, int] = {}

    @property
    def alpha(self) -> float:
        base = np.exp(self.log_base)
        return float((base - 1) / (base + 1))

    def _key(self, v: np.ndarray) -> np.ndarray:
        """Sign times bucket of the magnitude, shifted so that all kept magnitudes are above zero; zero alone is 0."""
        with np.errstate(divide="ignore"):
            place = np.ceil(np.log(np.abs(v)) / self.log_base - 1e-12).astype(float)
        shift = np.ceil(745 / self.log_base) + 2
        return np.where(v == 0, 0, np.sign(v) * (np.where(v == 0, 0, place) + shift)).astype(np.int64)

    def _edge(self, key: np.ndarray) -> np.ndarray:
        """Largest magnitude of a bucket."""
        shift = np.ceil(745 / self.log_base) + 2
        return np.exp(np.minimum((np.abs(key) - shift) * self.log_base, 709.0))

    def _fit(self) -> None:
        while len(self.counts) > self.size:
            # Doubling the base halves every magnitude's bucket number.
            old = np.ceil(745 / self.log_base) + 2
            self.log_base *= 2
            new = np.ceil(745 / self.log_base) + 2
            joined: dict[int, int] = {}
            for key, n in self.counts.items():
                to = 0 if key == 0 else int(np.sign(key) * (np.ceil((abs(key) - old) / 2) + new))
                joined[to] = joined.get(to, 0) + n
            self.counts = joined

    def _add(self, v):
        keys, n = np.unique(self._key(v), return_counts=True)
        for key, c in zip(keys.tolist(), n.tolist(), strict=True):
            self.counts[key] = self.counts.get(key, 0) + c
        self._fit()

    def _join(self, other):
        while other.log_base < self.log_base * (1 - 1e-9) or self.log_base < other.log_base * (1 - 1e-9):
            small = other if other.log_base < self.log_base else self
            kept, small.size = small.size, -1
            old_counts = small.counts
            old = np.ceil(745 / small.log_base) + 2
            small.log_base *= 2
            new = np.ceil(745 / small.log_base) + 2
            small.counts = {}
            for key, n in old_counts.items():
                to = 0 if key == 0 else int(np.sign(key) * (np.ceil((abs(key) - old) / 2) + new))
                small.counts[to] = small.counts.get(to, 0) + n
            small.size = kept
        for key, n in other.counts.items():
            self.counts[key] = self.counts.get(key, 0) + n
        self._fit()

    def rank(self, x) -> np.ndarray:
        keys = np.array(sorted(self.counts), np.int64)
        sums = np.concatenate(([0.0], np.cumsum([self.counts[k] for k in keys.tolist()])))
        x = np.asarray(x, float)
        key = self._key(x)
        below, upto = sums[np.searchsorted(keys, key, "left")], sums[np.searchsorted(keys, key, "right")]
        high = self._edge(key)
        low = high * np.exp(-self.log_base)
        with np.errstate(all="ignore"):
            share = np.clip((np.abs(x) - low) / (high - low), 0, 1)
        share = np.where(key < 0, 1 - share, np.where(key == 0, 1.0, share))
        return np.where(x >= self.high, float(self.n), np.where(x < self.low, 0.0, below + (upto - below) * np.nan_to_num(share, nan=1.0)))

    def quantile(self, q) -> np.ndarray:
        """The middle, in the relative sense, of the bucket that holds the rank."""
        keys = np.array(sorted(self.counts), np.int64)
        sums = np.cumsum([self.counts[k] for k in keys.tolist()])
        at = keys[np.minimum(np.searchsorted(sums, np.clip(np.ceil(np.asarray(q, float) * self.n), 1, self.n)), len(keys) - 1)]
        high = self._edge(at)
        middle = 2 * high / (1 + np.exp(self.log_base))
        return np.clip(np.where(at == 0, 0.0, np.sign(at) * middle), self.low, self.high)

    @property
    def bytes(self) -> int:
        return 16 * len(self.counts)
