"""Reference curves of rank error; constants are one, so these show shapes and are no proven limits."""

from __future__ import annotations

from math import log2


def stream(n: int, k: int, aspect_ratio: float) -> float:
    return n / k * log2(max(2.0, aspect_ratio))


def balanced(n: int, k: int, aspect_ratio: float) -> float:
    return stream(n, k, aspect_ratio) + n / k * log2(max(2.0, n / k))


def optimal(k: int, worst: list[tuple[int, float]]) -> float:
    """c / k, with c fitted on (k, worst error) of comparison-based methods."""
    return min(size * err for size, err in worst) / k
