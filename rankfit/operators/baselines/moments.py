"""Minimum, maximum and power sums; the distribution is the one of greatest entropy with these moments."""

from __future__ import annotations

import numpy as np

from rankfit.operators.baselines.base import Baseline

GRID = 1024


class Moments(Baseline):
    """`size` power sums on the scaled axis of the first batch, and as many of the logarithm if all values are above 0.

    A fit that doesn't settle, or numbers a double can't hold, give the status 'failed' and NaN answers.
    """

    def __init__(self, size: int):
        super().__init__(size)
        self.sums, self.logs, self.centre, self.scale = np.zeros(size + 1), np.zeros(size + 1), None, None
        self.lost = 0  # items too small beside the centre to leave a trace in any sum
        self.positive, self.log_centre, self.log_scale, self.fit = True, 0.0, 1.0, None

    def _powers(self, x: np.ndarray) -> np.ndarray:
        out, p = np.zeros(self.size + 1), np.ones(len(x))
        with np.errstate(all="ignore"):
            for i in range(self.size + 1):
                out[i] = p.sum()
                p = p * x
        return out

    def _add(self, v):
        self.fit = None
        if self.centre is None:
            self.centre, self.scale = float(v.mean()), float(max(np.abs(v - v.mean()).max(), 1e-300))
            if v.min() > 0:
                logs = np.log(v)
                self.log_centre, self.log_scale = float(logs.mean()), float(max(np.abs(logs - logs.mean()).max(), 1e-9))
        self.lost += int(np.count_nonzero((v - self.centre == -self.centre) & (v != 0)))
        with np.errstate(all="ignore"):
            self.sums += self._powers((v - self.centre) / self.scale)
        if self.positive and v.min() > 0:
            self.logs += self._powers((np.log(v) - self.log_centre) / self.log_scale)
        else:
            self.positive = False

    @staticmethod
    def _moved(sums, centre, scale, to_centre, to_scale):
        """Power sums about another centre and scale, by the binomial rule."""
        k, ratio, shift = len(sums), scale / to_scale, (centre - to_centre) / to_scale
        out = np.zeros(k)
        binomial = np.zeros(k)
        for i in range(k):
            binomial[1 : i + 1] = binomial[1 : i + 1] + binomial[:i]
            binomial[0] = 1
            j = np.arange(i + 1)
            with np.errstate(all="ignore"):
                out[i] = np.sum(binomial[: i + 1] * ratio**j * shift ** (i - j) * sums[: i + 1])
        return out

    def _join(self, other):
        self.fit = None
        if self.centre is None:
            self.__dict__.update({k: v for k, v in other.__dict__.items() if k not in ("n", "low", "high", "size")})
            return
        self.lost += other.lost
        self.sums = self.sums + self._moved(other.sums, other.centre, other.scale, self.centre, self.scale)
        self.positive &= other.positive
        if self.positive:
            self.logs = self.logs + self._moved(other.logs, other.log_centre, other.log_scale, self.log_centre, self.log_scale)

    def _solve(self):
        """CDF on a grid over [min, max] (or its logarithm), or None if the fit fails."""
        if self.fit is not None:
            return self.fit
        self.fit = False
        log_axis = self.positive and self.low > 0 and self.high / self.low > 1e3
        sums, centre, scale = (self.logs, self.log_centre, self.log_scale) if log_axis else (self.sums, self.centre, self.scale)
        low, high = (np.log(self.low), np.log(self.high)) if log_axis else (self.low, self.high)
        if not log_axis and self.lost > 0.01 * self.n:
            self.status = "failed"
            return False
        if not np.isfinite(high - low) or high <= low:
            self.status = "failed" if not np.isfinite(high - low) else "ok"
            return False
        k = self.size
        raw = self._moved(sums, centre, scale, (low + high) / 2, (high - low) / 2) / max(self.n, 1)
        if not np.isfinite(raw).all() or np.abs(raw).max() > 1 + 1e-6 * k:
            self.status = "failed"
            return False
        x = np.linspace(-1, 1, GRID)
        cheb = np.cos(np.outer(np.arange(k + 1), np.arccos(np.clip(x, -1, 1))))
        want = np.array([np.polynomial.chebyshev.cheb2poly(np.eye(k + 1)[i]) @ raw[: i + 1] for i in range(k + 1)])
        step = 2 / (GRID - 1)
        lam = np.zeros(k + 1)
        lam[0] = np.log(0.5)
        for _ in range(200):
            with np.errstate(all="ignore"):
                density = np.exp(np.minimum(lam @ cheb, 300)) * step
            density[[0, -1]] /= 2
            gradient = cheb @ density - want
            if np.abs(gradient).max() < 1e-7:
                break
            hessian = (cheb * density) @ cheb.T + 1e-12 * np.eye(k + 1)
            try:
                move = np.linalg.solve(hessian, gradient)
            except np.linalg.LinAlgError:
                self.status = "failed"
                return False
            size, value = 1.0, density.sum() - lam @ want
            while size > 1e-8:
                trial = lam - size * move
                with np.errstate(all="ignore"):
                    d = np.exp(np.minimum(trial @ cheb, 300)) * step
                d[[0, -1]] /= 2
                if np.isfinite(d.sum()) and d.sum() - trial @ want <= value - 1e-4 * size * (gradient @ move):
                    break
                size /= 2
            lam = lam - size * move
        else:
            if np.abs(gradient).max() > 1e-5:
                self.status = "failed"
                return False
        if density.max() > 0.5 * density.sum():
            self.status = "failed"  # all mass in one cell: the grid can't hold so wide a range of exponents
            return False
        cdf = np.cumsum(density) / density.sum()
        self.fit = ((low + high) / 2 + x * ((high - low) / 2), np.maximum.accumulate(cdf), log_axis)
        return self.fit

    def quantile(self, q) -> np.ndarray:
        q = np.asarray(q, float)
        fit = self._solve()
        if not fit:
            return np.full(len(q), np.nan if self.status != "ok" else self.low)
        x, cdf, log_axis = fit
        found = np.interp(q, cdf, x)
        return np.exp(found) if log_axis else found

    def rank(self, x) -> np.ndarray:
        """By bisection over quantiles, all queries in each round: the baseline answers no ranks of its own."""
        x = np.asarray(x, float)
        if not self._solve():
            return np.full(len(x), np.nan) if self.status != "ok" else np.where(x >= self.low, float(self.n), 0.0)
        a, b = np.zeros(len(x)), np.ones(len(x))
        for _ in range(40):
            m = (a + b) / 2
            above = self.quantile(m) > x
            a, b = np.where(above, a, m), np.where(above, m, b)
        return np.where(x >= self.high, float(self.n), np.where(x < self.low, 0.0, b * self.n))

    @property
    def bytes(self) -> int:
        return 16 * self.size + 16
