"""Counts on fixed dyadic ranges of an integer axis; light siblings fold into their parents."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline

BITS = 32


class Dyadic(Baseline):
    """Values are scaled to 32 bits over a fixed range; ranges are aligned, so any two summaries merge."""

    def __init__(self, size: int, low: float = -1e6, high: float = 1e6):
        super().__init__(size)
        self.from_, self.to = low, high
        self.nodes: dict[tuple[int, int], int] = {}

    def _scaled(self, v):
        share = np.clip((np.asarray(v, float) - self.from_) / (self.to - self.from_), 0, 1)
        return np.minimum((share * (1 << BITS)).astype(np.int64), (1 << BITS) - 1)

    def _compress(self) -> None:
        for level in range(BITS):
            if len(self.nodes) <= self.size:
                break
            limit = self.n / (self.size / 3)
            for (at, i) in [x for x in self.nodes if x[0] == level]:
                own = self.nodes.get((at, i), 0)
                sibling, parent = self.nodes.get((at, i ^ 1), 0), self.nodes.get((at + 1, i >> 1), 0)
                if own and own + sibling + parent <= limit:
                    self.nodes[at + 1, i >> 1] = own + sibling + parent
                    self.nodes.pop((at, i), None)
                    self.nodes.pop((at, i ^ 1), None)

    def _add(self, v):
        for at in range(0, len(v), 1 << 14):
            keys, n = np.unique(self._scaled(v[at : at + (1 << 14)]), return_counts=True)
            for key, c in zip(keys.tolist(), n.tolist(), strict=True):
                self.nodes[0, key] = self.nodes.get((0, key), 0) + c
            self._compress()

    def _join(self, other):
        for key, c in other.nodes.items():
            self.nodes[key] = self.nodes.get(key, 0) + c
        self._compress()

    def rank(self, x) -> np.ndarray:
        level = np.array([k[0] for k in self.nodes], np.int64)
        low = np.array([k[1] << k[0] for k in self.nodes], np.int64)
        high, count = low + (np.int64(1) << level) - 1, np.array(list(self.nodes.values()), float)
        place = self._scaled(x)
        share = np.clip((place[:, None] - low[None, :] + 1) / (high - low + 1)[None, :], 0, 1)
        return np.where(np.asarray(x, float) >= self.high, float(self.n), share @ count)

    @property
    def bytes(self) -> int:
        return 16 * len(self.nodes)
