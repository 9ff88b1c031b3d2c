"""What every baseline shares."""

from __future__ import annotations

import pickle

import numpy as np

from rankfit.operators.kernel import quantile_by_rank


class Baseline:
    """Update in batches, merge, ask for ranks and quantiles, count bytes."""

    status = "ok"

    def __init__(self, size: int):
        self.size, self.n, self.low, self.high = size, 0, np.inf, -np.inf

    def update(self, v: np.ndarray) -> Baseline:
        v = np.asarray(v, float)
        if len(v):
            self.n += len(v)
            self.low, self.high = min(self.low, float(v.min())), max(self.high, float(v.max()))
            self._add(v)
        return self

    def merge(self, other: Baseline) -> Baseline:
        if other.n:
            self.n += other.n
            self.low, self.high = min(self.low, other.low), max(self.high, other.high)
            self._join(other)
        return self

    def quantile(self, q) -> np.ndarray:
        r = np.clip(np.ceil(np.asarray(q, float) * self.n), 1, self.n)
        return quantile_by_rank(self.rank, r, self.low, self.high)

    def encode(self) -> bytes:
        return pickle.dumps(self)

    @staticmethod
    def decode(raw: bytes) -> Baseline:
        return pickle.loads(bytes(raw))
