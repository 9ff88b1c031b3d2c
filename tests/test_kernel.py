import numpy as np
import pytest
from hypothesis import given, settings, strategies as st

from rankfit.config import AcsConfig
from rankfit.functions.curves import Curve, register_curve
from rankfit.operators import codec, kernel
from rankfit.operators.frequent import FrequentItems, compact
from rankfit.operators.ladder import Ladder
from rankfit.plans import build


def errors(answer, x, m=500):
    ordered = np.sort(x)
    at = ordered[np.ceil(np.arange(1, m + 1) * len(x) / m).astype(int) - 1]
    err = np.abs(answer(at) - np.searchsorted(ordered, at, "right")) / len(x)
    return err.mean(), err.max()


def test_start_thresholds_by_hand():
    v = np.array([1, 2, 2, 2, 3, 4, 5, 6, 7, 9.0])
    t, r = kernel.init_buckets(v, None, 6, "drop")
    # places ceil(i * 9 / 5): 0 2 4 6 8 9
    assert t.tolist() == [1, 2, 3, 5, 7, 9] and r.tolist() == [1, 4, 5, 7, 9, 10]
    fenced = kernel.init_thresholds(*compact(np.repeat([1.0, 5, 6, 7, 8, 9, 10], [1, 1, 90, 1, 1, 1, 5]), np.ones(100, np.int64)), 6, "fence")
    assert 5.0 in fenced and 6.0 in fenced


def test_curvature_by_hand():
    t, b = np.array([0.0, 1, 2, 4]), np.array([1.0, 2, 6, 2])
    # densities 1, 2, 6, 1 and a virtual empty bucket of length 2; a score is the slope's change times length squared
    want = [max(0, abs(1 - 2) * 1 / 2), max(abs(2 - 1) / 2, abs(2 - 6) / 2), max(abs(6 - 2) / 2, abs(6 - 2 / 2) / 3), max(abs(2 - 6 * 2) * 2 / 3, 2 / 2)]
    assert np.allclose(kernel.curvature(t, b), want)
    joined = kernel.pair_scores(t, b)
    assert np.isinf(joined[[0, -1]]).all()
    assert np.isclose(joined[1], max(abs(8 - 1 * 2) * 2 / 3, abs(8 - 2 * 2 / 2) * 2 / 4))


def test_cubic_by_hand():
    curve = Curve(np.array([0.0, 1, 2, 4]), np.array([1.0, 3, 7, 9]))
    # secants 2, 4, 1: the first inner slope is (3 + 3) / (3 / 2 + 3 / 4)
    assert np.isclose(curve.right[0], 6 / (3 / 2 + 3 / 4))
    assert np.isclose(curve([0.5])[0], (1 + 3) / 2 + (curve.left[0] - curve.right[0]) / 8)
    assert curve([-1, 0, 1, 2, 4, 9]).tolist() == [0, 1, 3, 7, 9, 9]


@pytest.mark.parametrize("interp", ["pchip", "linear", "step"])
def test_curves_are_monotone_and_exact(interp):
    random = np.random.default_rng(4)
    t = np.cumsum(random.random(40) ** 6 + 1e-9)
    r = np.cumsum(random.integers(1, 1000, 40)).astype(float)
    curve = Curve(t, r, interp)
    values = curve(np.linspace(t[0], t[-1], 5000))
    assert np.allclose(curve(t), r) and (np.diff(values) >= -1e-9).all()
    halves = curve((t[1:] + t[:-1]) / 2)
    if interp == "pchip":
        assert ((halves - r[:-1]) / np.diff(r) >= 0.125 - 1e-9).all() and ((r[1:] - halves) / np.diff(r) >= 0.125 - 1e-9).all()


def test_own_curve():
    register_curve("square", lambda width, rank: lambda i, u: rank[i] + (rank[i + 1] - rank[i]) * u * u)
    state = kernel.summarize(np.random.default_rng(0).normal(size=5000), AcsConfig(k=50, interp="square"))
    assert errors(lambda x: kernel.rank(state, x), np.random.default_rng(0).normal(size=5000))[0] < 0.02


SHAPES = {
    "random": lambda r: r.normal(size=30_000), "sorted": lambda r: np.sort(r.normal(size=30_000)), "reversed": lambda r: np.sort(r.normal(size=30_000))[::-1],
    "zigzag": lambda r: np.stack([np.arange(15_000.0), -np.arange(15_000.0)], 1).ravel(), "two": lambda r: r.integers(0, 2, 30_000).astype(float), "constant": lambda r: np.full(30_000, 3.0),
    "geometric": lambda r: 2.0 ** -r.integers(0, 900, 30_000), "huge": lambda r: r.normal(size=30_000) * 1e150, "few": lambda r: r.normal(size=5), "ties": lambda r: np.round(r.normal(size=30_000), 1),
}


@pytest.mark.parametrize("shape", SHAPES)
@pytest.mark.parametrize("options", [{}, {"filter": "none"}, {"buffer_mult": 5}, {"heuristic": "curv3"}, {"batching": "analysis", "buffer_mult": 20}], ids=str)
def test_invariants_on_every_shape(shape, options):
    x = SHAPES[shape](np.random.default_rng(7))
    cfg = AcsConfig(k=40, **options)
    state = kernel.State(cfg)
    for part in np.array_split(x, 7):
        kernel.update(state, part)
        rules = kernel.invariants(state)
        assert all(v for k, v in rules.items() if k != "bound" or not options), rules
    kernel.finish(state)
    assert state.n == len(x) and float(state.vmin) == x.min() and float(state.vmax) == x.max()
    assert kernel.invariants(state)["mass"]
    q = kernel.quantile(state, np.linspace(0.01, 1, 50))
    assert (np.diff(q) >= 0).all()
    back = kernel.rank(state, q)
    assert (back >= np.ceil(np.linspace(0.01, 1, 50) * len(x) - 1e-9) - 1e-4 * len(x)).all()


@settings(max_examples=40, deadline=None)
@given(st.lists(st.floats(-1e6, 1e6), min_size=1, max_size=400), st.integers(1, 6))
def test_merge_conserves(values, parts):
    states = [kernel.update(kernel.State(AcsConfig(k=8, buffer_mult=5)), np.array(p)) for p in np.array_split(np.array(values), parts)]
    whole = states[0]
    for s in states[1:]:
        whole = kernel.merge(whole, s)
    assert whole.n == len(values) and kernel.invariants(whole)["mass"]
    done = kernel.finish(codec.decode(codec.encode(whole)))
    assert float(done.vmin) == min(values) and float(done.vmax) == max(values)
    assert np.isclose(kernel.rank(done, [max(values)])[0], len(values))


def test_many_at_once():
    x = np.random.default_rng(6).normal(size=40_000)
    for parts, k in ((24, 50), (4000, 50)):
        whole = kernel.finish(kernel.merge_many([kernel.summarize(p, AcsConfig(k=k)) for p in np.array_split(x, parts)]))
        assert whole.n == len(x) and kernel.invariants(whole)["mass"] and float(whole.vmax) == x.max()
        assert errors(lambda v, s=whole: kernel.rank(s, v), x)[1] < 0.02


def test_heap_and_rounds_agree_in_error():
    x = np.random.default_rng(3).normal(size=20_000)
    found = [errors(lambda v, s=kernel.summarize(x, AcsConfig(k=50, fold=f, buffer_mult=20)): kernel.rank(s, v), x)[0] for f in ("rounds", "heap")]
    assert max(found) < 3 * min(found) + 1e-4


def test_small_inputs_are_exact():
    x = np.array([3.0, 1, 2, 2, 5])
    state = kernel.summarize(x, AcsConfig(k=10))
    assert kernel.rank(state, [0, 1, 2, 3, 5]).tolist() == [0, 1, 3, 4, 5]
    assert kernel.quantile(state, [0.2, 0.5, 0.8, 1]).tolist() == [1, 2, 3, 5]
    assert np.isnan(kernel.quantile(kernel.State(AcsConfig()), [0.5])).all()


def test_nan_infinite_and_weights():
    state = kernel.update(kernel.State(AcsConfig(k=10)), np.array([1.0, np.nan, np.inf, -np.inf, 2.0]), np.array([3, 1, 1, 1, 0]))
    assert (state.n, state.n_nan) == (3, 3)
    with pytest.raises(ValueError):
        kernel.update(state, np.array([1.0]), np.array([-1]))


def test_integer_axis_keeps_digits():
    x = (1 << 60) + np.arange(5000) * 3
    exact = kernel.summarize(x, AcsConfig(k=50, axis="i64"))
    assert int(exact.vmin) == 1 << 60 and int(kernel.quantile(exact, [1.0])[0]) == int(x[-1])
    assert len(np.unique(x.astype(float))) < len(x)
    assert np.abs(kernel.rank(exact, x) - np.arange(1, 5001)).max() < 20


def test_filter_by_hand():
    items = FrequentItems(3, np.zeros(0))
    out = items.absorb(np.array([1.0, 2, 3]), np.array([5, 3, 1]))
    # three items and room for two: the third largest counter, 1, is taken off all
    assert items.v.tolist() == [1, 2] and items.c.tolist() == [4, 2] and items.chat.tolist() == [5, 3] and out[0].tolist() == [3] and out[1].tolist() == [1]
    out = items.absorb(np.array([2.0, 9]), np.array([1, 3]))
    assert items.v.tolist() == [1] and items.c.tolist() == [1] and items.chat.tolist() == [5]
    assert out[0].tolist() == [2, 9] and out[1].tolist() == [4, 3]


def test_filter_bounds_and_zero_error():
    random = np.random.default_rng(5)
    x = np.minimum(random.zipf(1.5, 50_000), 10_000).astype(float)
    items = FrequentItems(50, np.zeros(0))
    for part in np.array_split(x, 20):
        items.absorb(*compact(part, np.ones(len(part), np.int64)))
    v, n = np.unique(x, return_counts=True)
    assert set(v[n > len(x) / 50]) <= set(items.v)
    assert all(0 <= dict(zip(v, n, strict=True))[a] - c <= len(x) / 50 for a, c in zip(items.v, items.c, strict=True))
    few = random.integers(0, 50, 30_000).astype(float)
    parts = [kernel.update(kernel.State(AcsConfig(k=100)), p) for p in np.array_split(few, 8)]
    while len(parts) > 1:
        parts = [kernel.merge(a, b) for a, b in zip(parts[::2], parts[1::2], strict=True)]
    assert errors(lambda v: kernel.rank(kernel.finish(parts[0]), v), few)[1] == 0


def test_sizes_after_compression():
    x = np.concatenate([np.repeat(np.arange(10.0), 500), np.random.default_rng(0).normal(size=20_000)])
    state = kernel.summarize(np.random.default_rng(1).permutation(x), AcsConfig(k=60))
    held = len(state.items.v)
    assert held and len(state.t) <= max(60 - held, 30, 6) and codec.size_bytes(state) == 16 * (len(state.t) + held)


def test_without_filter_short_buckets_stay_whole():
    x = np.random.default_rng(2).integers(0, 7, 20_000).astype(float)
    state = kernel.summarize(x, AcsConfig(k=50, filter="none"))
    assert state.n == len(x) and kernel.invariants(state)["mass"]


def test_protection_after_merge():
    random = np.random.default_rng(8)
    big, small = (kernel.summarize(random.normal(size=n), AcsConfig(k=50, buffer_mult=20), whole=False) for n in (50_000, 4000))
    big.locked = np.ones(len(big.t), bool)
    big.epoch_end = 1e9
    assert kernel.merge(codec.decode(codec.encode(big)), small).n == 54_000
    like = [kernel.summarize(random.normal(size=20_000), AcsConfig(k=50, buffer_mult=20), whole=False) for _ in range(2)]
    for s in like:
        s.epoch_end = 21_000
    assert kernel.merge(*like).epoch_end == pytest.approx(1.25 * 40_000)


@pytest.mark.parametrize("size", [25, 60, 200])
def test_resize(size):
    x = np.random.default_rng(9).normal(size=40_000)
    state = kernel.resize(kernel.summarize(x, AcsConfig(k=100)), size)
    assert len(state.t) <= size and (size < 100 or len(state.t) > 150)
    assert errors(lambda v: kernel.rank(state, v), x)[1] < 0.5 / min(size, 100)


def test_ladder_and_prior():
    x = np.random.default_rng(10).normal(size=1 << 15)
    ladder = Ladder(AcsConfig(k=50))
    for i in range(15):
        ladder.add(kernel.summarize(x[(1 << i) - 1 : (2 << i) - 1], AcsConfig(k=50)))
    assert len(ladder.rungs) <= 16 and errors(ladder.rank, x[: ladder.n])[1] < 0.02
    assert abs(ladder.quantile([0.5])[0] - np.median(x)) < 0.05
    for prior in (np.linspace(-4, 4, 50), np.linspace(1000, 2000, 50)):
        state = kernel.finish(kernel.update(kernel.preset(AcsConfig(k=50, filter="none", buffer_mult=20), prior), x))
        assert errors(lambda v, s=state: kernel.rank(s, v), x)[1] < 0.02


def test_many_digit_keys_and_codec_version():
    raw = codec.encode(kernel.summarize(np.arange(1000.0), AcsConfig(k=20)))
    assert codec.encode(codec.decode(raw)) == raw
    with pytest.raises(ValueError):
        codec.decode(b"nope" + raw)
    assert len(raw) < 16 * 20 + 700


def test_reported_orderings():
    """Cubic beats linear, the default heuristic beats none, errors are far below n / k, streams beat merges."""
    x = np.random.default_rng(11).normal(size=400_000)
    err = lambda **o: errors(lambda v, s=kernel.summarize(x, AcsConfig(k=50, **o)): kernel.rank(s, v), x)
    default = err()
    assert default[0] * 50 < 0.1 and err(interp="linear")[0] > 2 * default[0] and err(heuristic="none")[1] > 3 * default[1]
    parts = [kernel.summarize(p, AcsConfig(k=50), whole=False) for p in np.array_split(x, 128)]
    while len(parts) > 1:
        parts = [kernel.merge(a, b) for a, b in zip(parts[::2], parts[1::2], strict=True)]
    merged = errors(lambda v: kernel.rank(kernel.finish(parts[0]), v), x)
    assert default[0] < merged[0] < 1 / 50


@pytest.mark.parametrize("chunks", [16, 256, 1024])
def test_many_partials_keep_the_tail_and_add_no_bias(chunks):
    n = 300_000
    v = np.random.default_rng(11).lognormal(size=n)
    ordered = np.sort(v)
    points = ordered[np.concatenate((np.arange(500) * n // 500, (np.array([0.99, 0.995, 0.999]) * n).astype(int)))]
    exact = np.searchsorted(ordered, points, "right")

    def error(parts):
        states = [codec.decode(codec.encode(kernel.finish(kernel.update(kernel.State(AcsConfig(filter="none")), p), compress=False))) for p in np.array_split(v, parts)]
        return (kernel.rank(kernel.finish(build.balanced(states)), points) - exact) / n

    stream, merged = error(1), error(chunks)
    assert np.abs(merged).max() <= (3 if n / chunks >= 10_000 else 8) * np.abs(stream).max()
    assert abs(merged.mean()) <= 0.1 * chunks / n + 5e-5


def test_first_version_of_the_format_is_still_read():
    state = kernel.summarize(np.random.default_rng(1).normal(size=5000), AcsConfig())
    raw = codec.encode(state)
    bits = -(-len(state.t) // 8)
    old = codec.decode(raw[:4] + (1).to_bytes(2, "little") + raw[6:-bits])
    assert (old.t == state.t).all() and (old.r == state.r).all() and not old.own.any()
    assert codec.decode(raw).own.tolist() == state.own.tolist()
