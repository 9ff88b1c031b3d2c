"""The adaptive CDF summary of one bag of numbers.

A state keeps thresholds with cumulative ranks, a weighted buffer and, if the filter is on, the frequent items. Since
the rank of any point during a fold is one fixed function F (the old curve plus the buffered weight at or below the
point), a fold only has to choose the next thresholds; their ranks are F at them. So nothing drifts, the last rank is
the weight of the buckets, and choosing is vectorised over all buckets of a round.
"""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass, field, replace

import numpy as np

from rankfit.config import LEAST_SIZE, AcsConfig
from rankfit.functions.curves import Curve, gaps
from rankfit.operators.frequent import FrequentItems, compact

MOST_DOUBLINGS = 6
MOST_ROUNDS = 400
MOST_EPOCHS = 3
#: Values for each bucket from which on a first fold adapts: the counts of fewer are noise.
ENOUGH = 5


def axis_dtype(cfg: AcsConfig):
    return np.int64 if cfg.axis == "i64" else np.float64


def _none(cfg: AcsConfig) -> np.ndarray:
    return np.zeros(0, axis_dtype(cfg))


@dataclass
class State:
    cfg: AcsConfig
    n: int = 0
    n_null: int = 0
    n_nan: int = 0
    t: np.ndarray = None
    r: np.ndarray = None
    locked: np.ndarray = None
    own: np.ndarray = None  # thresholds at which the curve's ranks jump by one item
    epoch_end: float = 0.0
    c_bound: float = 0.0
    zeta: float = float("inf")
    buf_v: list = field(default_factory=list)
    buf_w: list = field(default_factory=list)
    buffered: int = 0
    items: FrequentItems = None
    k: int = 0
    finished: bool = False
    meta: Counter = field(default_factory=Counter)

    def __post_init__(self):
        cfg = self.cfg
        self.k = self.k or cfg.k
        if self.t is None:
            self.t, self.r, self.locked = _none(cfg), np.zeros(0), np.zeros(0, bool)
        if self.own is None:
            self.own = np.zeros(len(self.t), bool)
        self.c_bound = self.c_bound or cfg.c_bound
        if self.items is None:
            self.items = FrequentItems(self.k, _none(cfg))

    @property
    def room(self) -> int:
        return max(self.cfg.buffer_mult * self.k, 5 * self.k)

    @property
    def buffer(self) -> tuple[np.ndarray, np.ndarray]:
        if len(self.buf_v) > 1:
            self.buf_v, self.buf_w = [np.concatenate(self.buf_v)], [np.concatenate(self.buf_w)]
        return (self.buf_v[0], self.buf_w[0]) if self.buf_v else (_none(self.cfg), np.zeros(0, np.int64))

    def hold(self, v: np.ndarray, w: np.ndarray) -> None:
        self.buf_v, self.buf_w, self.buffered = ([v], [w], len(v)) if len(v) else ([], [], 0)

    @property
    def vmin(self):
        ends = [a[:1] for a in (self.t, self.items.v)] + [np.array([b.min()]) for b in self.buf_v if len(b)]
        return min((e[0] for e in ends if len(e)), default=None)

    @property
    def vmax(self):
        ends = [a[-1:] for a in (self.t, self.items.v)] + [np.array([b.max()]) for b in self.buf_v if len(b)]
        return max((e[0] for e in ends if len(e)), default=None)

    @property
    def bucket_weight(self) -> float:
        return float(self.r[-1]) if len(self.r) else 0.0


# Update ------------------------------------------------------------------------------------------------------------


def update(state: State, v: np.ndarray, w: np.ndarray | None = None) -> State:
    """Add values, with whole weights if given (0 is ignored, below 0 an error). Folds whenever the buffer is full."""
    v = np.asarray(v)
    if state.cfg.axis == "f64":
        v = v.astype(np.float64, copy=False)
        fine = np.isfinite(v)
        if not fine.all():
            state.n_nan += int((~fine).sum() if w is None else np.asarray(w)[~fine].sum())
            v, w = v[fine], None if w is None else np.asarray(w)[fine]
    else:
        v = v.astype(np.int64, copy=False)
    w = np.ones(len(v), np.int64) if w is None else np.asarray(w, np.int64)
    if len(w) and w.min() < 0:
        raise ValueError("a weight is below zero")
    if len(w) and not w.all():
        v, w = v[w > 0], w[w > 0]
    state.finished = False
    if state.cfg.filter == "none" and state.cfg.axis == "f64" and len(v):
        size = np.abs(v)
        size = size[size > 0]
        state.zeta = min(state.zeta, float(size.min()) if len(size) else np.inf)
    at = 0
    while at < len(v):
        step = max(1, state.room - state.buffered)
        state.buf_v.append(v[at : at + step])
        state.buf_w.append(w[at : at + step])
        taken = len(v[at : at + step])
        state.buffered += taken
        state.n += int(w[at : at + step].sum())
        at += taken
        if state.buffered >= state.room:
            fold(state)
    return state


def preset(cfg: AcsConfig, thresholds) -> State:
    """A state that begins with thresholds from a prior; their counts begin at zero."""
    t = np.unique(np.asarray(thresholds, axis_dtype(cfg)))[: cfg.k]
    return State(cfg, t=t, r=np.zeros(len(t)), locked=np.zeros(len(t), bool))


# Choosing thresholds -----------------------------------------------------------------------------------------------


def curvature(t: np.ndarray, b: np.ndarray, heuristic: str = "curv2", length: np.ndarray | None = None) -> np.ndarray:
    """Score of each bucket: by default the larger one-sided second difference of the density times length squared."""
    length = bucket_lengths(t) if length is None else length
    if heuristic == "none":
        return np.zeros(len(b))
    if heuristic == "length":
        return length
    if heuristic == "count":
        return b.astype(float)
    left_b, left_l = np.concatenate((b[:1], b[:-1])), np.concatenate((length[:1], length[:-1]))
    right_b, right_l = np.append(b[1:], 0.0), np.append(length[1:], length[-1])
    return _sided(b, length, left_b, left_l, right_b, right_l, heuristic)


def _sided(b, length, left_b, left_l, right_b, right_l, heuristic="curv2"):
    with np.errstate(all="ignore"):
        left = np.abs(b - left_b * (length / left_l)) * (length / (length + left_l))
        right = np.abs(b - right_b * (length / right_l)) * (length / (length + right_l))
        if heuristic == "curv3":
            # Change of the density's slope over the span of three midpoints, times length cubed.
            signed_left = (b - left_b * (length / left_l)) * (length / (length + left_l))
            signed_right = (right_b * (length / right_l) - b) * (length / (length + right_l))
            return np.nan_to_num(np.abs(signed_right - signed_left) * 2 * length / (length + (left_l + right_l) / 2))
        out = np.maximum(left, right)
        out[np.isnan(out)] = 0
        return out


def bucket_lengths(t: np.ndarray) -> np.ndarray:
    """Lengths of buckets; the first, a point, takes the second's."""
    if len(t) < 2:
        return np.ones(len(t))
    rest = np.maximum(gaps(t[1:], t[:-1]), 1e-300)
    return np.concatenate((rest[:1], rest))


def pair_scores(t: np.ndarray, b: np.ndarray, heuristic: str = "curv2", length: np.ndarray | None = None) -> np.ndarray:
    """Score the bucket would have that joins i and i + 1, at place i for i in 1..k-2; infinite elsewhere."""
    k = len(b)
    out = np.full(k, np.inf)
    if k < 3:
        return out
    length = bucket_lengths(t) if length is None else length
    jb, jl = b[1:-1] + b[2:], length[1:-1] + length[2:]
    if heuristic == "none":
        out[1:-1] = jb * 1e-12
    elif heuristic == "length":
        out[1:-1] = jl
    elif heuristic == "count":
        out[1:-1] = jb
    else:
        out[1:-1] = _sided(jb, jl, b[:-2], length[:-2], np.append(b[3:], 0.0), np.append(length[3:], length[-1]), heuristic)
    return out


def middles(t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Midpoint of each bucket but the first (which has none), and whether it lies strictly inside."""
    low, high = t[:-1], t[1:]
    mid = low + (high.astype(np.uint64) - low.astype(np.uint64)).astype(np.uint64).__rshift__(np.uint64(1)).astype(np.int64) if t.dtype.kind == "i" else low / 2 + high / 2
    return np.concatenate((t[:1], mid)), np.concatenate(([False], (mid > low) & (mid < high)))


class Chooser:
    """Rounds of disjoint splits and joins over a candidate threshold list, under a fixed rank function."""

    def __init__(self, state: State, rank_at, raw: np.ndarray):
        self.s, self.cfg, self.rank_at, self.raw = state, state.cfg, rank_at, raw
        self.heuristic = state.cfg.heuristic

    def bound(self, weight: float) -> float:
        return self.s.c_bound * weight / self.s.k

    def joinable(self, b: np.ndarray, locked: np.ndarray, bound: float) -> np.ndarray:
        """At place i: whether thresholds i's buckets i and i + 1 may be joined."""
        out = np.zeros(len(b), bool)
        if len(b) > 2:
            out[1:-1] = (b[1:-1] + b[2:] <= self.cfg.join_cap * bound) & ~locked[1:-1]
        return out

    def long_enough(self, t: np.ndarray) -> np.ndarray:
        mid, inside = middles(t)
        if self.cfg.filter == "none" and self.cfg.axis == "f64":
            least = self.cfg.rel_len * np.maximum(np.maximum(np.abs(t[1:]), np.abs(t[:-1])), self.s.zeta if np.isfinite(self.s.zeta) else 0)
            inside[1:] &= gaps(t[1:], t[:-1]) >= least
        return inside

    def cut(self, low, high, mid, rank_low, rank_high, at):
        """The cut of a bucket and its rank: its midpoint's (`at`), or the buffered value's nearest to it that leaves both halves a count."""
        if rank_low < at < rank_high:
            return mid, at
        own = self.raw[np.searchsorted(self.raw, low, "right") : np.searchsorted(self.raw, high, "left")]
        if len(own):
            ranks = self.rank_at(own)
            own = own[(ranks > rank_low) & (ranks < rank_high)]
        if not len(own):
            return None
        best = own[np.argmin(np.abs(gaps(own, np.full(len(own), mid, own.dtype))))]
        return best, float(self.rank_at(np.array([best]))[0])

    def reduce(self, t: np.ndarray, locked: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Join the best pairs until `size` thresholds are left: half of the excess in each round."""
        rank = self.rank_at(t) if len(t) > size else None
        while len(t) > size and len(t) > 2:
            b = np.diff(rank, prepend=0.0)
            score = pair_scores(t, b, self.heuristic)
            free = ~locked[1:-1]
            if not free.any():
                locked = np.zeros(len(t), bool)
                self.s.meta["unlocked"] += 1
                continue
            empty = np.where((b[1:-1] <= 0) | (b[2:] <= 0), -1.0, score[1:-1])
            order = 1 + np.argsort(np.where(free, empty, np.inf), kind="stable")
            excess = len(t) - size
            want = excess if excess < 8 else excess // 2
            used, drop = np.zeros(len(t) + 1, bool), []
            for i in order.tolist():
                if len(drop) == want or locked[i]:
                    break
                if not (used[i] or used[i + 1]):
                    used[i] = used[i + 1] = True
                    drop.append(i)
            keep = np.ones(len(t), bool)
            keep[drop] = False
            t, locked, rank = t[keep], locked[keep], rank[keep]
            self.s.meta["joins"] += len(drop)
        return t, locked

    def grow(self, t: np.ndarray, locked: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Split until there are `size` thresholds: over-full buckets first, then by score."""
        for _ in range(MOST_ROUNDS):
            lack = size - len(t)
            if lack <= 0 or len(t) < 2:
                break
            rank = self.rank_at(t)
            b = np.diff(rank, prepend=0.0)
            mid, fine = middles(t)
            fine &= self.long_enough(t) & (b > 0)
            middle = self.rank_at(mid)
            order = np.lexsort((-curvature(t, b, self.heuristic), b <= self.bound(rank[-1])))
            new = []
            for i in order[fine[order]].tolist():
                cut = self.cut(t[i - 1], t[i], mid[i], rank[i - 1], rank[i], middle[i])
                if cut is not None:
                    new.append(cut[0])
                if len(new) == min(lack, max(1, len(t) // 4)):
                    break
            if not new:
                break
            t, locked = _inserted(t, locked, new, ())
            self.s.meta["splits"] += len(new)
        return t, locked

    def rounds(self, t: np.ndarray, locked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Splits paid by joins, in rounds of disjoint ones, until a round changes nothing."""
        doublings = 0
        rank = self.rank_at(t)
        for _ in range(MOST_ROUNDS):
            self.s.meta["rounds"] += 1
            b = np.diff(rank, prepend=0.0)
            bound, length = self.bound(rank[-1]), bucket_lengths(t)
            mid, fine = middles(t)
            fine &= self.long_enough(t)
            middle = self.rank_at(mid)
            joinable = self.joinable(b, locked, bound)
            pair = np.where(joinable, pair_scores(t, b, self.heuristic, length), np.inf)
            order = np.argsort(pair, kind="stable")[: int(joinable.sum())].tolist()
            forced = [i for i in np.flatnonzero((b > bound * (1 + 1e-12)) & fine).tolist()]
            used = np.zeros(len(t) + 1, bool)
            splits, drops, cuts = [], [], {}
            for i in sorted(forced, key=lambda i: -b[i]):
                cut = self.cut(t[i - 1], t[i], mid[i], rank[i - 1], rank[i], middle[i])
                if cut is not None:
                    cuts[i] = cut
            forced = list(cuts)
            used[forced] = True
            at = 0
            while at < len(order) and len(drops) < len(forced):
                i = order[at]
                at += 1
                if not (used[i] or used[i + 1]):
                    used[i] = used[i + 1] = True
                    drops.append(i)
            splits = forced[: len(drops)]
            if forced and not drops:
                if doublings < MOST_DOUBLINGS:
                    doublings += 1
                    self.s.c_bound *= 2
                    self.s.meta["doublings"] += 1
                    continue
                if locked.any():
                    locked = np.zeros(len(t), bool)
                    self.s.meta["unlocked"] += 1
                    doublings = 0
                    continue
            least = 2 * rank[-1] / self.s.k if self.cfg.min_split == "analysis" else self.cfg.min_split * bound
            if len(order) >= self.s.k / 3 + 2 and self.heuristic != "none":
                score = curvature(t, b, self.heuristic, length)
                left = np.flatnonzero(fine & (b > least) & ~used[:-1])
                for i in left[np.argsort(-score[left], kind="stable")].tolist():
                    if used[i]:
                        continue
                    while at < len(order) and (used[order[at]] or used[order[at] + 1]):
                        at += 1
                    ahead = at
                    while ahead < len(order) and (used[order[ahead]] or used[order[ahead] + 1] or order[ahead] in (i, i - 1)):
                        ahead += 1
                    if ahead == len(order) or not score[i] > self.cfg.gamma * pair[order[ahead]]:
                        break
                    cut = self.cut(t[i - 1], t[i], mid[i], rank[i - 1], rank[i], middle[i])
                    if cut is None:
                        continue
                    j = order[ahead]
                    used[[i, j, j + 1]] = True
                    cuts[i] = cut
                    splits.append(i)
                    drops.append(j)
            if not splits:
                break
            self.s.meta["splits"] += len(splits)
            self.s.meta["joins"] += len(drops)
            ends = np.zeros(len(t), bool)
            ends[splits] = True
            ends[[i - 1 for i in splits]] = True
            keep = np.ones(len(t), bool)
            keep[[d for d in drops]] = False
            new = np.array([cuts[i][0] for i in splits], t.dtype)
            every = np.concatenate((t[keep], new))
            order = np.argsort(every, kind="stable")
            rank = np.concatenate((rank[keep], [cuts[i][1] for i in splits]))[order]
            locked = np.concatenate(((locked | ends)[keep], np.ones(len(new), bool)))[order]
            t = every[order]
        return t, locked

    def settle(self, t: np.ndarray, locked: np.ndarray, new_weight: float, whole: float) -> tuple[np.ndarray, np.ndarray]:
        """Fold's choice; a buffer worth several epochs of items is several epochs' work, with locks released between."""
        choose = self.heap if self.cfg.fold == "heap" else self.rounds
        t, locked = choose(t, locked)
        before = max(whole - new_weight, 1.0)
        epochs = MOST_EPOCHS if before < new_weight else int(np.log(whole / before) / np.log(self.cfg.epoch))
        for _ in range(min(epochs, MOST_EPOCHS)):
            again, locked = choose(t, np.zeros(len(t), bool))
            if len(again) == len(t) and (again == t).all():
                break
            t = again
        return t, locked

    def heap(self, t: np.ndarray, locked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """As `rounds`, one split and join at a time from priority queues; slow, to test the other against."""
        rank = dict(zip(t.tolist(), self.rank_at(t).tolist(), strict=True))
        order = t.tolist()
        lock = dict(zip(order, locked.tolist(), strict=True))
        doublings = 0
        for _ in range(MOST_ROUNDS * len(order)):
            now = np.array(order, self.s.t.dtype)
            b = np.diff(np.array([rank[x] for x in order]), prepend=0.0)
            weight, length = rank[order[-1]], bucket_lengths(now)
            bound = self.bound(weight)
            mid, fine = middles(now)
            fine &= self.long_enough(now)
            middle = self.rank_at(mid)
            score, pair = curvature(now, b, self.heuristic, length), pair_scores(now, b, self.heuristic, length)
            can = self.joinable(b, np.array([lock[x] for x in order]), bound)
            pairs = [(pair[i], i) for i in np.flatnonzero(can).tolist()]
            heapq.heapify(pairs)
            over = sorted(((-b[i], i) for i in np.flatnonzero((b > bound * (1 + 1e-12)) & fine).tolist()))
            least = 2 * weight / self.s.k if self.cfg.min_split == "analysis" else self.cfg.min_split * bound
            free = sorted(((-score[i], i) for i in np.flatnonzero(fine & (b > least)).tolist())) if len(pairs) >= self.s.k / 3 + 2 and self.heuristic != "none" else []
            done = False
            for forced, (_, i) in [*((True, x) for x in over), *((False, x) for x in free[:8])]:
                best = next((p for p in heapq.nsmallest(4, pairs) if i not in (p[1], p[1] + 1)), None)
                if best is None or not forced and not score[i] > self.cfg.gamma * best[0]:
                    continue
                cut = self.cut(now[i - 1], now[i], mid[i], rank[order[i - 1]], rank[order[i]], middle[i])
                if cut is None:
                    continue
                cut = cut[0].item()
                lock[order[i - 1]] = lock[order[i]] = True
                gone = order[best[1]]
                rank[cut], lock[cut] = float(self.rank_at(np.array([cut], self.s.t.dtype))[0]), True
                order.insert(i, cut)
                order.remove(gone)
                self.s.meta["splits"] += 1
                self.s.meta["joins"] += 1
                done = True
                break
            if not done:
                if over and not pairs and doublings < MOST_DOUBLINGS:
                    doublings += 1
                    self.s.c_bound *= 2
                    self.s.meta["doublings"] += 1
                    continue
                break
        return np.array(order, self.s.t.dtype), np.array([lock[x] for x in order])


def _inserted(t: np.ndarray, locked: np.ndarray, cuts: list, lock_new) -> tuple[np.ndarray, np.ndarray]:
    every = np.concatenate((t, np.array(cuts, t.dtype)))
    flags = np.concatenate((locked, np.full(len(cuts), lock_new is None)))
    order = np.argsort(every, kind="stable")
    return every[order], flags[order]


# Folding -----------------------------------------------------------------------------------------------------------


def init_thresholds(v: np.ndarray, w: np.ndarray, k: int, ties: str = "fence", rel_len: float = 1e-8) -> np.ndarray:
    """Start thresholds from distinct ordered values: k places spread evenly over the items; ties may be fenced in."""
    total = int(w.sum())
    places = np.ceil(np.arange(k) * (total - 1) / (k - 1)).astype(np.int64)
    t = np.unique(v[np.searchsorted(np.cumsum(w), places, "right")])
    if ties == "drop":
        return t
    # Restore k: a threshold just below a value that took several places keeps it apart from what stands before it.
    while len(t) < min(k, len(v)):
        at = np.searchsorted(v, t)
        ends = np.cumsum(w)[at]
        weight = np.diff(ends, prepend=0)
        several = np.flatnonzero(np.diff(at, prepend=-1) > 1)
        heaviest = several[np.argsort(-weight[several], kind="stable")][: k - len(t)]
        new = []
        for i in heaviest.tolist():
            low, high = (at[i - 1] if i else -1), at[i]
            # Fence the value at the end if it is most of the bucket, else halve the rest.
            new.append(high - 1 if w[high] * 2 > weight[i] else min(high - 1, max(low + 1, int(np.searchsorted(np.cumsum(w), ends[i] - weight[i] / 2)))))
        t = np.unique(np.concatenate((t, v[new])))
    return t


def init_buckets(v: np.ndarray, w: np.ndarray | None, k: int, ties: str = "drop") -> tuple[np.ndarray, np.ndarray]:
    """(thresholds, cumulative ranks) of the first fold."""
    v, w = compact(np.asarray(v), np.ones(len(v), np.int64) if w is None else np.asarray(w))
    t = init_thresholds(v, w, k, ties)
    return t, np.cumsum(w)[np.searchsorted(v, t)].astype(float)


def _merging_curve(state: State):
    """The curve of a state for a sum of many: strictly inside a bucket, without the one item at its upper threshold.

    A curve that spreads this item over the bucket is half an item too high on average, which adds up over many states.
    """
    curve = Curve(state.t, state.r, state.cfg.interp)
    if not state.own.any():
        return curve

    def rank_at(x: np.ndarray) -> np.ndarray:
        out = curve(x)
        at = np.searchsorted(state.t, x, "left")
        high = np.minimum(at, len(state.t) - 1)
        inside = np.flatnonzero((at > 0) & (at < len(state.t)) & (x != state.t[high]) & state.own[high])
        low = state.r[high[inside] - 1]
        out[inside] -= (out[inside] - low) / np.maximum(state.r[high[inside]] - low, 1.0)
        return out

    return rank_at


def _still_own(t: np.ndarray, *states: State) -> np.ndarray:
    return np.isin(t, np.concatenate([s.t[s.own] for s in states]))


def _rank_function(curves: list[Curve], v: np.ndarray, w: np.ndarray):
    sums = np.concatenate(([0], np.cumsum(w))).astype(float)

    def rank_at(x: np.ndarray) -> np.ndarray:
        out = sums[np.searchsorted(v, x, "right")] if len(v) else np.zeros(len(x))
        for curve in curves:
            out = out + curve(x)
        return out

    return rank_at


def fold(state: State) -> State:
    """Move the buffer into the filter and the buckets."""
    v, w = compact(*state.buffer)
    if state.n > state.epoch_end:
        state.locked = np.zeros(len(state.t), bool)
        state.c_bound = state.cfg.c_bound
        state.epoch_end = state.cfg.epoch * max(state.epoch_end, state.n)
        state.meta["epochs"] += 1
    if state.cfg.filter == "mg":
        v, w = state.items.absorb(v, w)
    if state.cfg.batching == "analysis" and len(state.t):
        share = max(1, int(state.cfg.c_bound / 2 * max(state.bucket_weight, 1) / state.k))
        part = (np.cumsum(w) - 1) // share
        for i in np.unique(part).tolist():
            state.hold(v[part == i], w[part == i])
            _fold_buckets(state)
        return state
    state.hold(v, w)
    return _fold_buckets(state)


def _fold_buckets(state: State) -> State:
    v, w = compact(*state.buffer)
    cfg = state.cfg
    state.meta["folds"] += 1
    if not len(v):
        return state
    if not len(state.t):
        if len(v) <= state.k and cfg.filter == "mg" or len(v) < LEAST_SIZE:
            state.hold(v, w)  # still raw, and exact
            return state
        t = init_thresholds(v, w, min(state.k, len(v)), cfg.ties, cfg.rel_len)
        rank_at = _rank_function([], v, w)
        locked, weight = np.zeros(len(t), bool), float(w.sum())
        if len(v) >= ENOUGH * state.k and len(t) > 2:
            t, locked = Chooser(state, rank_at, v).settle(t, locked, weight, weight)
        at = np.minimum(np.searchsorted(v, t), len(v) - 1)
        state.own = (v[at] == t) & (w[at] == 1)
        return _settled(state, t, locked, rank_at, t[state.own])
    rank_at = _rank_function([Curve(state.t, state.r, cfg.interp)], v, w)
    chooser, own = Chooser(state, rank_at, v), state.t[state.own]
    t, locked = state.t, state.locked
    ends = [x for x in (v[0] if v[0] < t[0] else None, v[-1] if v[-1] > t[-1] else None) if x is not None]
    if ends:
        t, locked = _inserted(t, locked, ends, ())
        t, locked = chooser.reduce(t, locked, max(state.k, 2))
    if len(t) < state.k:
        t, locked = chooser.grow(t, locked, min(state.k, len(t) + len(v)))
    t, locked = chooser.settle(t, locked, float(w.sum()), state.bucket_weight + float(w.sum()))
    return _settled(state, t, locked, rank_at, own)


def _settled(state: State, t: np.ndarray, locked: np.ndarray, rank_at, own: np.ndarray) -> State:
    """`own`: the thresholds whose rank jumps by one item, as far as they are still among `t`."""
    r = rank_at(t)
    full = np.diff(r, prepend=0.0) > 0
    full[-1] = True
    if not full[0] and full.any():
        full[0] = True  # a preset's first threshold may have no item
    state.t, state.r, state.locked = t[full], r[full], locked[full]
    state.own = np.isin(state.t, own)
    state.hold(_none(state.cfg), np.zeros(0, np.int64))
    return state


def finish(state: State, compress: bool = True) -> State:
    """Fold what is buffered, drop the locks and, unless it is a partial, move the filter's small items to buckets."""
    if state.buffered:
        fold(state)
    if compress and state.cfg.filter == "mg" and len(state.items.v):
        v, w = state.items.compress(state.n)
        held = len(state.items.v)
        if len(v):
            bv, bw = state.buffer
            state.hold(*compact(np.concatenate([bv, v]), np.concatenate([bw, w])))
            _fold_buckets(state)
        size = max(state.k - held, state.k // 2, LEAST_SIZE)
        if held and len(state.t) > size:
            _resized(state, size)
    if state.buffered and compress:
        _raw_to_buckets(state)
    state.locked = np.zeros(len(state.t), bool)
    state.finished = True
    return state


def _raw_to_buckets(state: State) -> None:
    """A raw buffer of few values becomes one bucket for each."""
    v, w = compact(*state.buffer)
    if not len(state.t) and len(v) <= state.k:
        state.t, state.r, state.locked, state.own = v, np.cumsum(w).astype(float), np.zeros(len(v), bool), w == 1
        state.hold(v[:0], w[:0])
    else:
        _fold_buckets(state)


def _resized(state: State, size: int) -> None:
    v, w = compact(*state.buffer)
    rank_at = _rank_function([Curve(state.t, state.r, state.cfg.interp)], v, w)
    chooser = Chooser(state, rank_at, v)
    t, locked = state.t, state.locked
    if abs(size - len(t)) > 0.25 * len(t):
        locked = np.zeros(len(t), bool)
    t, locked = chooser.reduce(t, locked, size) if size < len(t) else chooser.grow(t, locked, size)
    state.t, state.r, state.locked, state.own = t, rank_at(t), locked, _still_own(t, state)
    if len(v):
        state.hold(v[:0], w[:0])


def resize(state: State, k: int) -> State:
    """Change the number of buckets."""
    state.cfg = replace(state.cfg, k=k)
    state.k = k
    if state.items is not None and state.cfg.filter == "mg":
        state.items.k = k
        if len(state.items.v) >= k:
            v, w = state.items.absorb(_none(state.cfg), np.zeros(0, np.int64))
            bv, bw = state.buffer
            state.hold(*compact(np.concatenate([bv, v]), np.concatenate([bw, w])))
    if len(state.t):
        held = len(state.items.v) if state.finished else 0
        size = max(k - held, k // 2, LEAST_SIZE) if held else k
        if size < len(state.t) or len(state.t) >= LEAST_SIZE:
            _resized(state, size)
    elif state.buffered > k:
        fold(state)
    return state


# Merging -----------------------------------------------------------------------------------------------------------


def merge(a: State, b: State) -> State:
    """The summary of both inputs' items; consumes its arguments."""
    if not b.n or not a.n:
        whole, other = (a, b) if a.n else (b, a)
        whole.n_null, whole.n_nan = a.n_null + b.n_null, a.n_nan + b.n_nan
        return whole
    big, small = (a, b) if a.n >= b.n else (b, a)
    k = max(a.k, b.k) if big.cfg.size_rule == "max_k" else big.k
    big.n_null, big.n_nan = a.n_null + b.n_null, a.n_nan + b.n_nan
    big.zeta = min(a.zeta, b.zeta)
    big.meta.update(small.meta)
    big.meta["merges"] += 1
    big.finished = False
    big.n += small.n
    big.k = k
    big.items.k = k
    bv, bw = big.buffer
    sv, sw = small.buffer
    parts_v, parts_w = [bv, sv], [bw, sw]
    if big.cfg.filter == "mg":
        ev, ew = big.items.merge(small.items)
        parts_v.append(ev)
        parts_w.append(ew)
    v, w = compact(np.concatenate(parts_v), np.concatenate(parts_w))
    over = big.n > big.epoch_end
    if over:
        big.c_bound = big.cfg.c_bound
        big.epoch_end = big.cfg.epoch * max(big.epoch_end, big.n)
    if len(big.t) and len(small.t):
        curves = [_merging_curve(x) for x in (big, small)]
        t = np.union1d(big.t, small.t)
        locked = np.isin(t, big.t[big.locked]) if not over else np.zeros(len(t), bool)
    elif len(big.t) or len(small.t):
        side = big if len(big.t) else small
        curves, t = [_merging_curve(side)], side.t
        locked = np.zeros(len(t), bool) if over or side is small else side.locked
    else:
        big.hold(v, w)
        if len(v) > big.room:
            _fold_buckets(big)
        return big
    rank_at, own = _rank_function(curves, v, w), np.concatenate([x.t[x.own] for x in (big, small)])
    chooser = Chooser(big, rank_at, v)
    if len(v):
        ends = [x for x in (v[0] if v[0] < t[0] else None, v[-1] if v[-1] > t[-1] else None) if x is not None]
        if ends:
            t, locked = _inserted(t, locked, ends, ())
    t, locked = chooser.reduce(t, locked, k) if len(t) > k else chooser.grow(t, locked, k) if len(t) >= 2 else (t, locked)
    t, locked = chooser.heap(t, locked) if big.cfg.fold == "heap" else chooser.rounds(t, locked)
    return _settled(big, t, locked, rank_at, own)


def merge_many(states: list[State]) -> State:
    """As `merge` for many finished states at once: one union of thresholds, one reduction. Consumes its arguments."""
    states = [s for s in states if s.n] or states[:1]
    big = max(states, key=lambda s: s.n)
    if len(states) == 1:
        return big
    parts = [s.buffer for s in states]
    curves, own = [_merging_curve(s) for s in states if len(s.t)], np.concatenate([s.t[s.own] for s in states])
    thresholds = [s.t for s in states if len(s.t)]
    for s in states:
        if s is not big:
            big.n, big.n_null, big.n_nan, big.zeta = big.n + s.n, big.n_null + s.n_null, big.n_nan + s.n_nan, min(big.zeta, s.zeta)
            big.meta.update(s.meta)
            if big.cfg.filter == "mg":
                parts.append(big.items.merge(s.items))
    big.meta["merges"] += len(states) - 1
    big.finished = False
    big.epoch_end, big.c_bound = big.cfg.epoch * big.n, big.cfg.c_bound
    v, w = compact(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]).astype(np.int64))
    if not curves:
        big.hold(v, w)
        return fold(big) if len(v) > big.room else big
    ends = [v[:1], v[-1:]] if len(v) else []
    t = np.unique(np.concatenate([*thresholds, *ends]))
    rank_at = _rank_function(curves, v, w)
    chooser = Chooser(big, rank_at, v)
    t, locked = chooser.reduce(t, np.zeros(len(t), bool), big.k)
    t, locked = chooser.rounds(t, locked)
    return _settled(big, t, locked, rank_at, own)


# Queries -----------------------------------------------------------------------------------------------------------


class Answers:
    """Rank and quantile answers of a state, with prefix sums made once."""

    def __init__(self, state: State):
        self.s = state
        self.curve = Curve(state.t, state.r, state.cfg.interp)
        v, w = compact(*state.buffer)
        self.points, weights = compact(np.concatenate([v, state.items.v]), np.concatenate([w, state.items.chat]).astype(np.int64))
        self.sums = np.concatenate(([0], np.cumsum(weights))).astype(float)

    def rank(self, x) -> np.ndarray:
        """Estimated number of items at or below each x."""
        x = np.asarray(x, axis_dtype(self.s.cfg)).reshape(-1)
        return self.curve(x) + self.sums[np.searchsorted(self.points, x, "right")]

    def quantile(self, q) -> np.ndarray:
        """Smallest x whose estimated rank reaches max(1, ceil(q n)); NaN of an empty summary."""
        q = np.asarray(q, float).reshape(-1)
        if not self.s.n:
            return np.full(len(q), np.nan)
        return self.value_at(np.clip(np.ceil(q * self.s.n - 1e-9), 1, self.s.n))

    def value_at(self, r: np.ndarray) -> np.ndarray:
        """Smallest x whose estimated rank reaches r."""
        points = np.union1d(self.s.t, self.points)
        ranks = np.maximum.accumulate(self.rank(points))
        at = np.minimum(np.searchsorted(ranks, r - 1e-9 * np.maximum(r, 1), "left"), len(points) - 1)
        out = points[at].astype(axis_dtype(self.s.cfg))
        if len(self.s.t) < 2:
            return out
        # Between two points only the curve rises; a jump at the right point is the point itself.
        steps = self.sums[np.searchsorted(self.points, points, "left")][at]
        below = self.curve(points[at]) + steps
        inside = (at > 0) & (r <= below)
        bucket = np.searchsorted(self.s.t, points[at], "left") - 1
        inside &= (bucket >= 0) & (bucket < len(self.s.t) - 1) & (points[at] > self.s.t[0])
        if inside.any():
            i = bucket[inside]
            u = self.curve.place(i, r[inside] - steps[inside], self.s.cfg.inverse)
            low, width = self.s.t[i], self.curve.width[i]
            found = low + np.minimum(np.ceil(u * width), width).astype(low.dtype) if low.dtype.kind == "i" else low + u * width
            out[inside] = np.minimum(np.maximum(found, points[at[inside] - 1]), points[at[inside]])
        return out


def rank(state: State, x) -> np.ndarray:
    return Answers(state).rank(x)


def quantile(state: State, q) -> np.ndarray:
    return Answers(state).quantile(q)


def quantile_by_rank(rank_of, r: np.ndarray, low: float, high: float, steps: int = 60) -> np.ndarray:
    """Smallest values whose rank reaches r, by bisection of all of them at once."""
    a, b = np.full(len(r), low, float), np.full(len(r), high, float)
    for _ in range(steps):
        m = a / 2 + b / 2
        reached = rank_of(m) >= r
        a, b = np.where(reached, a, m), np.where(reached, m, b)
    return b


def invariants(state: State) -> dict[str, bool]:
    """Structural rules of a state, each with whether it holds."""
    b = np.diff(state.r, prepend=0.0)
    weight = state.bucket_weight
    held = sum(int(w.sum()) for w in state.buf_w) + state.items.weight
    fine = Chooser(state, None, None).long_enough(state.t) if len(state.t) > 1 else np.zeros(len(state.t), bool)
    return {
        "mass": abs(weight + held - state.n) <= 1e-6 * max(state.n, 1),
        "no_empty_bucket": bool((b[1:] > 0).all()),
        "increasing": bool((state.t[1:] > state.t[:-1]).all()) if len(state.t) > 1 else True,
        "size": len(state.t) <= state.k,
        "bound": bool((b[fine] <= state.c_bound * weight / max(min(state.k, len(state.t)), 1) * (1 + 1e-6) + 1).all()) if len(state.t) else True,
    }


def summarize(values, cfg: AcsConfig, weights=None, whole: bool = True) -> State:
    """The finished summary of one array, in its order."""
    return finish(update(State(cfg), np.asarray(values), weights), whole)
