"""Fixed buckets with linear interpolation: of equal width, or of equal depth on the first batch."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline


class EquiDepth(Baseline):
    """Bounds are quantiles of the first batch and stay; items outside extend the end buckets."""

    def __init__(self, size: int):
        super().__init__(size)
        self.bounds, self.counts = np.zeros(0), np.zeros(0)

    def _start(self, v):
        return np.unique(np.quantile(v, np.linspace(0, 1, self.size), method="inverted_cdf"))

    def _add(self, v):
        if not len(self.bounds):
            self.bounds = self._start(v)
            self.counts = np.zeros(len(self.bounds))
        self.bounds[0], self.bounds[-1] = min(self.bounds[0], self.low), max(self.bounds[-1], self.high)
        np.add.at(self.counts, np.searchsorted(self.bounds, v, "left"), 1)

    def _join(self, other):
        if not len(self.bounds):
            self.bounds, self.counts = other.bounds, other.counts
            return
        every = np.union1d(self.bounds, other.bounds)
        ranks = np.interp(every, self.bounds, np.cumsum(self.counts), left=0) + np.interp(every, other.bounds, np.cumsum(other.counts), left=0)
        keep = np.unique(np.concatenate((np.linspace(0, len(every) - 1, self.size).astype(int), [0, len(every) - 1])))
        self.bounds, self.counts = every[keep], np.diff(ranks[keep], prepend=0.0)

    def rank_points(self, x):
        return np.interp(x, self.bounds, np.cumsum(self.counts), left=0)

    def rank(self, x) -> np.ndarray:
        return self.rank_points(np.asarray(x, float))

    @property
    def bytes(self) -> int:
        return 16 * len(self.bounds)


class EquiWidth(EquiDepth):
    """Bounds divide the first batch's range evenly."""

    def _start(self, v):
        return np.unique(v.min() / self.size * np.arange(self.size, 0, -1) + v.max() / self.size * np.arange(self.size)) if v.max() > v.min() else np.array([v.min()])
