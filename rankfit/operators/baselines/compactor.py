"""Levels of compactors: a full level keeps a random half of its sorted items at double weight."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline


class Compactor(Baseline):
    """`size` is the top level's capacity; lower levels shrink by two thirds each. Seeded, so reruns agree."""

    def __init__(self, size: int, seed: int = 1):
        super().__init__(size)
        self.levels: list[np.ndarray] = [np.zeros(0)]
        self.random = np.random.default_rng(seed)

    def _capacity(self, level: int) -> int:
        return max(2, int(np.ceil(self.size * (2 / 3) ** (len(self.levels) - 1 - level))))

    def _compress(self) -> None:
        level = 0
        while level < len(self.levels):
            own = self.levels[level]
            if len(own) > self._capacity(level):
                own = np.sort(own)
                odd = own[:1] if len(own) % 2 else own[:0]
                even = own[len(odd) :]
                if level + 1 == len(self.levels):
                    self.levels.append(np.zeros(0))
                self.levels[level + 1] = np.concatenate([self.levels[level + 1], even[int(self.random.integers(2)) :: 2]])
                self.levels[level] = odd
            level += 1

    def _add(self, v):
        for at in range(0, len(v), 1 << 14):
            self.levels[0] = np.concatenate([self.levels[0], v[at : at + (1 << 14)]])
            self._compress()

    def _join(self, other):
        while len(self.levels) < len(other.levels):
            self.levels.append(np.zeros(0))
        for i, own in enumerate(other.levels):
            self.levels[i] = np.concatenate([self.levels[i], own])
        self._compress()

    def rank(self, x) -> np.ndarray:
        v = np.concatenate(self.levels)
        w = np.repeat(2.0 ** np.arange(len(self.levels)), [len(own) for own in self.levels])
        order = np.argsort(v, kind="stable")
        sums = np.concatenate(([0.0], np.cumsum(w[order])))
        return sums[np.searchsorted(v[order], np.asarray(x, float), "right")] * (self.n / max(sums[-1], 1))

    @property
    def bytes(self) -> int:
        return 8 * sum(map(len, self.levels))
