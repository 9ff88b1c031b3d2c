"""Options of the adaptive CDF summary."""

from __future__ import annotations

from dataclasses import dataclass

LEAST_SIZE = 6


@dataclass(frozen=True)
class AcsConfig:
    """`k` buckets and how they adapt. Defaults are the tuned values; 'analysis' settings are those a proof needs."""

    k: int = 100
    interp: str = "pchip"  # pchip, linear, step or a registered curve
    heuristic: str = "curv2"  # curv2, curv3, none, length, count
    filter: str = "mg"  # mg or none
    gamma: float = 1.5
    c_bound: float = 3.0
    epoch: float = 1.25
    join_cap: float = 0.75
    min_split: float | str = 0.01  # share of the size bound, or 'analysis': 2 n / k
    rel_len: float = 1e-8
    axis: str = "f64"  # f64 or i64
    buffer_mult: int = 512  # items a buffer holds for each bucket
    batching: str = "whole"  # whole, or 'analysis': slices of half the size bound
    fold: str = "rounds"  # rounds or heap
    ties: str = "fence"  # fence or drop
    size_rule: str = "larger_n"  # larger_n or max_k
    inverse: str = "newton"  # newton or bisect

    def __post_init__(self):
        if self.k < LEAST_SIZE:
            raise ValueError(f"a summary has at least {LEAST_SIZE} buckets")
        for name, allowed in (("heuristic", ("curv2", "curv3", "none", "length", "count")), ("filter", ("mg", "none")), ("axis", ("f64", "i64")), ("fold", ("rounds", "heap")), ("ties", ("fence", "drop")), ("size_rule", ("larger_n", "max_k")), ("inverse", ("newton", "bisect")), ("batching", ("whole", "analysis"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {', '.join(allowed)}")
