"""Centroids with a flat weight cap: clusters of neighbouring items, linear between their means."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline


class Centroids(Baseline):
    """At most about `size` centroids of weight up to 2 n / size; a centroid of weight one is a point."""

    def __init__(self, size: int):
        super().__init__(size)
        self.mean, self.weight = np.zeros(0), np.zeros(0)

    def _cluster(self, mean: np.ndarray, weight: np.ndarray) -> None:
        order = np.argsort(mean, kind="stable")
        mean, weight = mean[order], weight[order]
        cap, before = 2 * weight.sum() / self.size, np.concatenate(([0.0], np.cumsum(weight)))
        ends, at = [], 0
        while at < len(mean):
            at = max(at + 1, int(np.searchsorted(before, before[at] + cap, "right")) - 1)
            ends.append(at)
        starts = np.array([0, *ends[:-1]])
        self.weight = np.add.reduceat(weight, starts)
        with np.errstate(over="ignore"):
            share = weight / np.repeat(self.weight, np.diff([*starts, len(mean)]))
            self.mean = np.add.reduceat(mean * share, starts)

    def _add(self, v):
        for at in range(0, len(v), max(1, 64 * self.size)):
            part = v[at : at + 64 * self.size]
            self._cluster(np.concatenate([self.mean, part]), np.concatenate([self.weight, np.ones(len(part))]))

    def _join(self, other):
        self._cluster(np.concatenate([self.mean, other.mean]), np.concatenate([self.weight, other.weight]))

    def rank(self, x) -> np.ndarray:
        x = np.asarray(x, float)
        before = np.cumsum(self.weight) - self.weight
        single = self.weight == 1
        # Half of a centroid lies on each side of its mean; a point counts whole at its place.
        places = np.concatenate(([self.low], self.mean, [self.high]))
        ranks = np.concatenate(([0.0], np.where(single, before + 1, before + self.weight / 2), [float(self.n)]))
        last = np.concatenate((np.diff(places) > 0, [True]))
        with np.errstate(all="ignore"):
            scale = max(abs(self.low), abs(self.high), 1.0)
            out = np.interp(x / scale, places[last] / scale, np.maximum.accumulate(ranks)[last])
        return np.where(x < self.low, 0.0, np.where(x >= self.high, float(self.n), out))

    @property
    def bytes(self) -> int:
        return 16 * len(self.mean)
