"""Monotone curves through (threshold, rank) points, and their inverses.

All curves are 0 below the first threshold, jump to its rank there, and stay at the last rank beyond the last one.
Thresholds are float64 or int64; only differences of neighbours become floating point, so int64 loses no digits.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

#: Curves by name: from widths and secant-scaled ranks to a function of (bucket, place in 0..1).
_registered: dict[str, Callable[[np.ndarray, np.ndarray], Callable[[np.ndarray, np.ndarray], np.ndarray]]] = {}


def register_curve(name: str, make) -> None:
    """`make(widths, ranks)` gives f(bucket, place): monotone, exact at places 0 and 1 of each bucket."""
    _registered[name] = make


def gaps(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a - b as float64, without losing int64 digits or overflowing on wide float64 ranges."""
    if a.dtype.kind == "i":
        return (a.astype(np.longdouble) - b.astype(np.longdouble)).astype(np.float64)
    return a - b


def slopes(width: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Slopes times nothing: derivative at each node for widths already scaled; 0 where a neighbour is flat."""
    rise = np.diff(rank)
    n = len(rank)
    if n == 2:
        return np.full(2, rise[0] / width[0])
    with np.errstate(all="ignore"):
        secant = rise / width
        out = np.zeros(n)
        w1, w2 = 2 * width[1:] + width[:-1], width[1:] + 2 * width[:-1]
        inner = (w1 + w2) / (w1 / secant[:-1] + w2 / secant[1:])
        out[1:-1] = np.where((secant[:-1] > 0) & (secant[1:] > 0), inner, 0)
        for at, (h0, h1, s0, s1) in ((0, (width[0], width[1], secant[0], secant[1])), (-1, (width[-1], width[-2], secant[-1], secant[-2]))):
            d = ((2 * h0 + h1) * s0 - h0 * s1) / (h0 + h1)
            out[at] = min(max(d, 0.0), 3 * s0) if np.isfinite(d) else 0.0
    return np.nan_to_num(out, nan=0.0, posinf=0.0, neginf=0.0)


class Curve:
    """The rank curve of a summary's buckets."""

    def __init__(self, thresholds: np.ndarray, ranks: np.ndarray, interp: str = "pchip"):
        self.t, self.r, self.interp = thresholds, ranks, interp
        self.width = gaps(thresholds[1:], thresholds[:-1]) if len(thresholds) > 1 else np.zeros(0)
        if interp == "pchip" and len(thresholds) > 1:
            scale = self.width.max()
            scaled = np.maximum(self.width / scale, 1e-300)
            slope = slopes(scaled, ranks)
            with np.errstate(all="ignore"):
                self.left, self.right = np.nan_to_num(slope[:-1] * scaled), np.nan_to_num(slope[1:] * scaled)
        elif interp in _registered:
            self.own = _registered[interp](self.width, ranks)
        elif interp not in ("pchip", "linear", "step"):
            raise ValueError(f"no curve named {interp}")

    def inside(self, i: np.ndarray, u: np.ndarray) -> np.ndarray:
        """Rank at place u in 0..1 between thresholds i and i + 1."""
        low, high = self.r[i], self.r[i + 1]
        if self.interp == "linear":
            return low + (high - low) * u
        if self.interp == "step":
            return np.where(u < 0.5, low, high)
        if self.interp in _registered:
            return self.own(i, u)
        v = 1 - u
        out = low + (high - low) * u * u * (3 - 2 * u) + u * v * (self.left[i] * v - self.right[i] * u)
        return np.minimum(np.maximum(out, low), high)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x)
        if not len(self.t):
            return np.zeros(x.shape)
        at = np.searchsorted(self.t, x, "left")
        out = np.where(at >= len(self.t), self.r[-1], self.r[np.minimum(at, len(self.t) - 1)]).astype(float)
        out[x < self.t[0]] = 0.0
        between = (at > 0) & (at < len(self.t)) & (x != self.t[np.minimum(at, len(self.t) - 1)])
        if between.any():
            i = at[between] - 1
            with np.errstate(all="ignore"):
                u = np.clip(np.nan_to_num(gaps(x[between], self.t[i]) / self.width[i], nan=0.5), 0, 1)
            out[between] = self.inside(i, u)
        return out

    def place(self, i: np.ndarray, rank: np.ndarray, how: str = "newton") -> np.ndarray:
        """Smallest place u in 0..1 of bucket i where the curve reaches `rank`."""
        low, high = np.zeros(len(i)), np.ones(len(i))
        rise = np.maximum(self.r[i + 1] - self.r[i], 1e-300)
        u = np.clip((rank - self.r[i]) / rise, 0, 1)
        if self.interp == "linear":
            return u
        for step in range(60):
            value = self.inside(i, u)
            reached = value >= rank
            high, low = np.where(reached, u, high), np.where(reached, low, u)
            if (high - low < 1e-13).all():
                break
            guess = (low + high) / 2
            if how == "newton" and self.interp == "pchip" and step < 12:
                rise_at = 6 * u * (1 - u) * (self.r[i + 1] - self.r[i]) + self.left[i] * (1 - 4 * u + 3 * u * u) + self.right[i] * (3 * u * u - 2 * u)
                with np.errstate(all="ignore"):
                    newton = u - (value - rank) / rise_at
                fine = np.isfinite(newton) & (newton > low) & (newton < high)
                if (np.abs(value - rank) <= 1e-12 * np.maximum(np.abs(rank), 1)).all():
                    return u
                guess = np.where(fine, newton, guess)
            u = guess
        return high
