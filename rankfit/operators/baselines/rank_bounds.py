"""Tuples (value, gap of least ranks, extra uncertainty) with adaptive compression to a size."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline


class RankBounds(Baseline):
    """At most `size` tuples after each batch; those whose joint uncertainty is least go first."""

    def __init__(self, size: int):
        super().__init__(size)
        self.v, self.g, self.d = np.zeros(0), np.zeros(0), np.zeros(0)

    def _insert(self, v, g, d) -> None:
        """Merge sorted tuples; each side's uncertainty grows by that of the other's next tuple."""
        def extra(own, other_v, other_g, other_d):
            at = np.searchsorted(other_v, own, "right")
            inside = at < len(other_v)
            at = np.minimum(at, max(len(other_v) - 1, 0))
            return np.where(inside, other_g[at] + other_d[at] - 1, 0) if len(other_v) else np.zeros(len(own))

        a, b = extra(self.v, v, g, d), extra(v, self.v, self.g, self.d)
        every = np.concatenate([self.v, v])
        order = np.argsort(every, kind="stable")
        self.v, self.g, self.d = every[order], np.concatenate([self.g, g])[order], np.concatenate([self.d + a, d + b])[order]
        self._compress()

    def _compress(self) -> None:
        while len(self.v) > self.size:
            # Removing tuple i gives its gap to the next one.
            joint = self.g[:-1] + self.g[1:] + self.d[1:]
            joint[0] = np.inf
            # A few at a time: removals beside each other exclude one another, and heavy tuples must not go instead.
            excess = max(1, min(len(self.v) - self.size, len(self.v) // 8))
            # Among equals, into the next tuple that is surest itself: uncertainty is inherited by what comes before it.
            order = np.lexsort((self.d[1:], joint))[: 2 * excess + 2]
            chosen = np.zeros(len(self.v), bool)
            left = excess
            for i in order.tolist():
                if left and not chosen[i - 1] and not chosen[i + 1] and i:
                    chosen[i] = True
                    left -= 1
            gone = np.flatnonzero(chosen)
            self.g[gone + 1] += self.g[gone]
            self.v, self.g, self.d = self.v[~chosen], self.g[~chosen], self.d[~chosen]

    def _add(self, v):
        step = max(64, 8 * self.size)
        for at in range(0, len(v), step):
            part = np.sort(v[at : at + step])
            self._insert(part, np.ones(len(part)), np.zeros(len(part)))

    def _join(self, other):
        self._insert(other.v, other.g, other.d)

    def rank(self, x) -> np.ndarray:
        least = np.concatenate(([0.0], np.cumsum(self.g)))
        at = np.searchsorted(self.v, np.asarray(x, float), "right")
        most = np.where(at < len(self.v), least[np.minimum(at + 1, len(self.v))] + np.append(self.d, 0.0)[np.minimum(at, len(self.d))] - 1, float(self.n))
        return np.where(at == 0, 0.0, np.where(at == len(self.v), float(self.n), (least[at] + np.maximum(most, least[at])) / 2))

    @property
    def bytes(self) -> int:
        return 24 * len(self.v)
