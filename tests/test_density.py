import numpy as np
import pytest

from tallygrid.functions import density as de
from tallygrid.functions.statistics import beta_quantile, location
from tallygrid.operators import joint, tuning


@pytest.mark.parametrize("draw", [lambda g, n: g.gamma(3, 20, n), lambda g, n: g.exponential(50, n), lambda g, n: g.normal(300, 40, n)])
def test_fit_is_a_density_and_optimal(draw):
    x, m = np.unique(draw(np.random.default_rng(0), 3000).round(), return_counts=True)
    s = de.fit_logconcave(x, m, trim=0)
    at = np.linspace(s.t[0], s.t[-1], 200_001)
    assert np.trapezoid(np.exp(s(at)), at) == pytest.approx(1, abs=1e-4)
    assert (np.diff(np.diff(s.phi) / np.diff(s.t)) <= 1e-9).all() and 2 <= len(s.t) <= 40
    # No small kink anywhere raises the likelihood.
    f = np.exp(s(at))
    for knot in np.linspace(s.t[0], s.t[-1], 25):
        gain = np.trapezoid(np.maximum(0, at - knot) * f, at) - np.maximum(0, x - knot) @ m / m.sum()
        assert gain < 1e-3 * (s.t[-1] - s.t[0])


def test_mle_against_scan():
    g = np.random.default_rng(1)
    x, m = np.unique(g.gamma(4, 10, 5000).round(), return_counts=True)
    s = de.fit_logconcave(x, m).extended()
    v = 50 + g.choice(x, (40, 4))
    for row, est in zip(v, de.mle(v, s), strict=True):
        grid = np.arange(0, row.min() + 0.01, 0.1)
        assert s(row - est).sum() >= max(s(row - t).sum() for t in grid) - 1e-9


def test_mle_of_a_falling_density_is_the_minimum():
    s = de.LogSpline(np.asarray([0.0, 10.0, 40.0]), np.asarray([-1.0, -2.0, -8.0]))
    v = np.random.default_rng(2).integers(5, 90, (30, 5))
    assert (de.mle(v, s) == v.min(axis=1)).all()


def test_mle_moves_with_its_counters():
    s = de.LogSpline(np.asarray([0.0, 10.0, 40.0]), np.asarray([-4.0, -2.0, -8.0]))
    v = np.random.default_rng(3).integers(5, 90, (30, 5))
    assert de.mle(v + 17, s) == pytest.approx(de.mle(v, s) + 17)


def test_beta_quantile():
    draws = np.sort(np.random.default_rng(0).random((200_000, 5)), axis=1)
    for i in (1, 2, 5):
        assert beta_quantile(0.9, i, 5) == pytest.approx(np.quantile(draws[:, i - 1], 0.9), abs=5e-3)


def test_posterior():
    s = de.LogSpline(np.asarray([0.0, 10.0, 40.0]), np.asarray([-4.0, -2.0, -8.0]))
    n, p = de.posterior(np.asarray([30, 42]), s)
    full = np.exp([s(np.asarray([30 - k, 42 - k])).sum() for k in range(31)])
    assert p == pytest.approx((full / full.sum())[n.astype(int)])
    assert full[int(de.bayes(n, p, "01"))] == pytest.approx(full.max())  # a plateau: the smallest of the best
    low, high = de.credible(n, p, 0.9)
    assert low <= de.bayes(n, p, "l1") <= high


def test_location():
    v = np.asarray([[1.0, 2, 3, 100]])
    assert location(v, "l1")[0] == 2.5 and location(v, "l2")[0] == 26.5 and 2 < location(v, "huber")[0] < 10


def test_conv_power():
    f = np.asarray([0.5, 0.3, 0.2] + [0.0] * 7)
    want = f
    for _ in range(3):
        want = np.convolve(want, f)[:10]
    assert de.conv_power(f, 4) == pytest.approx(want)
    poisson = np.exp(-2.0) * np.cumprod(np.append(1.0, 2.0 / np.arange(1, 12)))  # its root is Poisson again
    assert de.conv_power(poisson, 0.5)[:3] == pytest.approx(np.exp(-1.0) * np.asarray([1, 1, 0.5]))


def test_depth_prediction_matches_rebuilt_grids():
    g = np.random.default_rng(0)
    c = g.negative_binomial(30, 0.2, 4000)
    line = np.bincount(g.integers(0, 2000, 4000), weights=c, minlength=2000)
    base = np.bincount(line.astype(int), minlength=20_000) / 2000
    rows = {d: w for d, _, w in tuning.depth_widths(base, [1, 2, 4], [0.9])}
    for depth, width in rows.items():
        real = np.sort(np.concatenate([np.bincount(g.integers(0, 2000 // depth, 4000), weights=c, minlength=2000 // depth) for _ in range(60)]))
        assert width == pytest.approx(real[int(np.ceil(beta_quantile(0.9, 1, depth) * len(real))) - 1], rel=0.08)


def test_logconcave_condition():
    g = np.asarray([0.9, 0.09, 0.009, 0.0009])
    assert tuning.compound_is_logconcave(g, 1.0) and not tuning.compound_is_logconcave(g, 0.01)


def _small(seed=0, items=150, heavy=15, r=4, k=64):
    g = np.random.default_rng(seed)
    c = np.minimum(g.zipf(2.0, items), 5000).astype(float)
    c[::-1].sort()
    cells = g.integers(0, k, (items, r)) + np.arange(r) * k
    values = np.bincount(cells.ravel(), weights=np.repeat(c, r), minlength=r * k)
    return c[:heavy], cells[:heavy], values, cells, c


def test_least_squares_is_exact_when_all_items_are_known():
    _, _, values, cells, c = _small()
    assert joint.least_squares(cells, values) == pytest.approx(c, abs=1e-4)


def test_joint_likelihood_beats_least_squares():
    ls, jm = [], []
    for seed in range(8):
        truth, cells, values, *_ = _small(seed, items=3000)
        start = np.maximum(0, values[cells].min(axis=1) - np.median(values))
        ls.append(((joint.least_squares(cells, values) - truth) ** 2).mean())
        theta, _ = joint.joint_mle(cells, values, start)
        jm.append(((theta - truth) ** 2).mean())
    assert np.mean(jm) < np.mean(ls)
