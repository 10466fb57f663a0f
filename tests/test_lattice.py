"""Laws on the integers, signed and levelled counters, products: against brute force and simulation."""

import numpy as np
import pytest

from tallygrid.functions.density import posterior
from tallygrid.functions.lattice import fit_logconcave_discrete, fit_zero_atom, symmetric_mle
from tallygrid.functions.density import fit_logconcave
from tallygrid.operators import logcounters
from tallygrid.operators.errors import Law
from tallygrid.operators.variants import product_law


def masses(spline, low, high):
    x = np.arange(low, high + 1)
    return x, np.exp(np.interp(x, spline.t, spline.phi))


@pytest.mark.parametrize("seed", range(4))
def test_discrete_fit_is_a_concave_mass_function_no_worse_than_others(seed):
    rng = np.random.default_rng(seed)
    x, m = np.unique(rng.negative_binomial(4, 0.2, 3000), return_counts=True)
    s = fit_logconcave_discrete(x, m, trim=0.0)
    at, p = masses(s, x[0], x[-1])
    assert abs(p.sum() - 1) < 1e-6
    assert (np.diff(np.diff(s.phi) / np.diff(s.t)) <= 1e-8).all()
    assert abs(at @ p - x @ m / m.sum()) < 1e-4 * (x @ m / m.sum())  # tilting it does not help
    true = np.cumprod(np.append(0.2**4, (np.arange(x[-1]) + 4) / (np.arange(x[-1]) + 1) * 0.8))
    log_true = np.log(true / true[x[0] :].sum())
    assert m @ np.interp(x, s.t, s.phi) >= m @ log_true[x]


def test_discrete_fit_of_one_value_and_of_a_wide_lattice():
    assert fit_logconcave_discrete(np.asarray([7]), np.asarray([3])).t[0] == 7
    x = np.arange(0, 100_000, 7)
    s = fit_logconcave_discrete(x, np.ones(len(x)), trim=0.0, most_points=500)
    assert abs(masses(s, 0, 99_995)[1].sum() - 1) < 0.01


def test_zero_atom_keeps_the_share_of_zeros():
    law = fit_zero_atom(np.asarray([0, 1, 2, 3, 4]), np.asarray([60, 10, 20, 8, 2]), trim=0.0)
    assert np.exp(law(np.asarray([0.0])))[0] == pytest.approx(0.6)
    assert law(np.asarray([-1.0]))[0] == -np.inf
    n, p = posterior(np.asarray([5, 5, 9]), law)
    assert n[np.argmax(p)] == 5
    assert fit_zero_atom(np.asarray([0]), np.asarray([4])).share == 1.0


def test_symmetric_mle_against_a_fine_search():
    rng = np.random.default_rng(2)
    x, m = np.unique(np.rint(rng.normal(0, 20, 4000)), return_counts=True)
    s = fit_logconcave(x, m, trim=0.0)
    v = rng.normal(50, 20, (20, 4))
    fine = np.linspace(-50, 150, 4001)

    def log(off):
        left, right = (s.phi[1] - s.phi[0]) / (s.t[1] - s.t[0]), (s.phi[-1] - s.phi[-2]) / (s.t[-1] - s.t[-2])
        return np.interp(off, s.t, s.phi) + left * np.minimum(0, off - s.t[0]) + right * np.maximum(0, off - s.t[-1])

    for row, est in zip(v, symmetric_mle(v, s), strict=True):
        assert sum(log(y - est) for y in row) >= max(sum(log(y - fine) for y in row)) - 1e-6


def test_levels_against_simulation():
    draw, base = np.random.default_rng(4), 1.2
    seen = np.bincount([logcounters.raised(200, base, draw) for _ in range(4000)], minlength=41)[:41] / 4000
    told = logcounters.level_table(np.asarray([200.0]), 40, base)[0]
    assert np.abs(np.cumsum(seen) - np.cumsum(told)).max() < 0.06


def test_level_likelihood_is_near_the_count_without_errors():
    draw, base = np.random.default_rng(5), 1.1
    v = np.asarray([[logcounters.raised(300, base, draw) for _ in range(8)] for _ in range(40)])
    est = logcounters.level_mle(v, Law(np.zeros(1), np.ones(1, dtype=np.int64)), base)
    assert abs(est.mean() - 300) < 30


def test_level_likelihood_is_whole_and_leaves_other_items_alone():
    draw, base = np.random.default_rng(6), 1.1
    law = Law(np.asarray([0.0, 3, 40, 700, 5000]), np.asarray([5, 4, 3, 2, 1]))
    few = np.asarray([[logcounters.raised(n, base, draw) for _ in range(8)] for n in (2, 14, 49, 300, 2400)])
    alone = logcounters.level_mle(few, law, base)
    hot = np.asarray([[logcounters.raised(1_000_000, base, draw) for _ in range(8)]])
    assert logcounters.level_mle(np.concatenate([few, hot]), law, base)[:5].tolist() == alone.tolist()
    levels = int(few.max()) + 1
    chance = np.zeros((6000, levels + 1))
    for e, w in zip(law.x, law.m / law.n, strict=True):
        chance += w * logcounters.level_table(np.arange(6000) + e, levels, base)
    told = sum(np.log(chance[:, few[:, a]]) for a in range(8))
    reached = told[alone.astype(int), np.arange(5)]
    assert (alone == np.rint(alone)).all() and (reached >= told.max(axis=0) - 1e-5).all()


def test_product_law_against_draws():
    x, y = Law(np.asarray([0.0, 2, 5, 9]), np.asarray([4, 3, 2, 1])), Law(np.asarray([0.0, 1, 7]), np.asarray([1, 1, 2]))
    zero, values, share = product_law(x.x, x.m, y.x, y.m)
    draws = x.draws((50_000,), 1) * y.draws((50_000,), 2)
    assert zero == pytest.approx((draws == 0).mean(), abs=0.01)
    assert zero + share.sum() == pytest.approx(1)
    assert zero + share[values < 20].sum() == pytest.approx((draws < 20).mean(), abs=0.02)
