"""Full mergeability: one summary for each power-of-two size class, only like sizes merge."""

from __future__ import annotations

import numpy as np

from rankfit.config import AcsConfig
from rankfit.operators import kernel


class Ladder:
    """At most about log2(n / k) summaries; ranks add over them."""

    def __init__(self, cfg: AcsConfig):
        self.cfg, self.rungs = cfg, {}

    @staticmethod
    def size_class(state: kernel.State) -> int:
        return max(0, int(np.floor(np.log2(max(1, state.n / state.k)))))

    def add(self, state: kernel.State) -> None:
        while (at := self.size_class(state)) in self.rungs:
            state = kernel.merge(self.rungs.pop(at), state)
        self.rungs[at] = state

    @property
    def n(self) -> int:
        return sum(s.n for s in self.rungs.values())

    def rank(self, x) -> np.ndarray:
        x = np.asarray(x, float)
        return sum((kernel.rank(s, x) for s in self.rungs.values()), np.zeros(len(x)))

    def quantile(self, q) -> np.ndarray:
        states = list(self.rungs.values())
        low, high = min(float(s.vmin) for s in states), max(float(s.vmax) for s in states)
        return kernel.quantile_by_rank(self.rank, np.clip(np.ceil(np.asarray(q) * self.n), 1, self.n), low, high)
