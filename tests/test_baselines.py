import numpy as np
import pytest

from rankfit.config import AcsConfig
from rankfit.operators import codec, kernel
from rankfit.operators.baselines import BASELINES, Moments
from rankfit.plans import bounds

SIZES = {"moments": 12, "compactor": 130, "rank_bounds": 67}
LIMIT = {"centroids": 0.02, "compactor": 0.04, "moments": 0.02, "rank_bounds": 0.15, "log_bucket": 0.03, "dyadic": 0.03, "equi_width": 0.02, "equi_depth": 0.03}


@pytest.mark.parametrize("name", BASELINES)
def test_ranks_quantiles_and_merges(name):
    x = np.random.default_rng(1).normal(size=40_000)
    ordered = np.sort(x)
    at = ordered[np.arange(99, 40_000, 100)]
    kind, size = BASELINES[name], SIZES.get(name, 100)
    single = kind(size).update(x)
    merged = kind(size).update(x[:100])
    for part in np.array_split(x[100:], 5):
        merged = merged.merge(kind.decode(kind(size).update(part).encode()))
    for s in (single, merged):
        assert s.n == len(x) and s.low == ordered[0] and s.high == ordered[-1]
        err = np.abs(s.rank(at) - np.searchsorted(ordered, at, "right")) / len(x)
        assert err.max() < LIMIT[name], (name, err.max())
        assert s.rank([ordered[0] - 1, ordered[-1]]).tolist() == [0, len(x)]
        q = s.quantile(np.array([0.1, 0.5, 0.9]))
        assert np.abs(np.searchsorted(ordered, q, "right") / len(x) - [0.1, 0.5, 0.9]).max() < LIMIT[name]
    assert single.bytes > 0


def test_moments_report_failure():
    random = np.random.default_rng(2)
    wide = np.where(random.random(5000) < 0.5, -1, 1) * 10 ** (random.random(5000) * 300 - 150)
    assert np.isnan(Moments(12).update(wide).rank(wide[:3])).all()


def test_adaptive_beats_comparison_based_at_equal_bytes():
    x = np.random.default_rng(3).normal(size=300_000)
    ordered = np.sort(x)
    at = ordered[np.arange(299, 300_000, 300)]
    truth = np.searchsorted(ordered, at, "right")
    ours = kernel.summarize(x, AcsConfig(k=100))
    err = np.abs(kernel.rank(ours, at) - truth).mean()
    for name, size, factor in (("centroids", 190, 2), ("compactor", 100, 10), ("rank_bounds", 67, 10)):
        other = BASELINES[name](size).update(x)
        assert np.abs(other.rank(at) - truth).mean() > factor * err, name
        assert other.bytes <= 1.2 * codec.size_bytes(ours)


def test_reference_curves():
    assert bounds.stream(1000, 10, 4) == 200 and bounds.balanced(1000, 10, 4) > 200 and bounds.optimal(100, [(50, 0.02), (10, 0.2)]) == 0.01
