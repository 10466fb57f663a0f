"""What the experiments report: which estimator wins, and how measures move."""

import numpy as np

from tallygrid.functions.hashing import GridSpec
from tallygrid.operators import tuning
from tallygrid.plans import experiments, simulation, workloads
from tallygrid.sources import tables


def test_debiased_likelihood_is_best_or_near_on_heavy_tails(spark):
    rows = workloads.power_law_sweep(spark, 10_000, (2.0,), (0.0,), [GridSpec(4, 500)], most=500).collect()
    eff = {r["method"]: r["rel_eff"] for r in rows}
    assert eff["debiased_mle"] == 1 and min(eff.values()) >= 0.9 and eff["min"] > 1.1 and eff["debiased_mean"] > 2


def test_power_law_is_the_discrete_law(spark):
    c = tables.power_law(spark, 20_000, 2.5, 3.0).toPandas().c.to_numpy()
    law = (3.0 + np.arange(1, 1_000_001)) ** -2.5
    for x in (1, 2, 5):
        assert abs((c == x).mean() - law[x - 1] / law.sum()) < 0.012


def test_intervals_cover_at_their_level_and_shrunken_ones_less(spark):
    rows = experiments.coverage_study(tables.power_law(spark, 3000, 2.0), 4, 150, salts=24, most=1000, levels=[0.8, 0.9]).collect()
    for r in rows:
        assert r["coverage"] >= r["level"] - 0.03, r
        if r["method"] == "mle" and r["level"] == 0.9:
            assert r["shrunk"] < r["coverage"]


def test_regression_helps_in_a_small_grid_only():
    counts = simulation.zipf(40_000, 2.0, seed=1)
    told = {}
    for k in (1024, 65_536):
        rows = [x for seed in range(2) for x in simulation.regression_of_salt(counts, [256], 4, k, seed)]
        told[k] = {m: np.sqrt(np.mean([e for _, _, name, e in rows if name == m])) for m in {x[2] for x in rows}}
        assert rows[0][1] > 0.2
    small, wide = told[1024], told[65_536]
    assert small["least_squares"] > small["debiased_min"] and small["joint_mle"] < 1.02 * small["debiased_mle"]
    assert abs(wide["joint_mle"] - wide["debiased_mle"]) <= 0.5 * wide["debiased_mle"] + 1.0


def test_errors_grow_as_told(spark):
    rows = sorted((r["load"], r["min"], r["conservative"], r["mle_debiased"]) for r in experiments.growth_study(spark, "/root/testdata/sf0.01").collect())
    low, high = rows[0], rows[-1]  # sixteen times the load
    assert high[1] / low[1] > 8 and high[2] / low[2] > 6 and high[3] / low[3] < 0.75 * high[1] / low[1]
    assert all(r[2] <= r[1] for r in rows)


def test_widths_told_are_widths_rebuilt():
    g = np.random.default_rng(0)
    counts = g.negative_binomial(30, 0.01, 4000)
    line = np.bincount(g.integers(0, 8000, 4000), weights=counts, minlength=8000).astype(int)
    told = {d: w for d, _, w in tuning.depth_widths(np.bincount(line, minlength=16 * (line.max() + 1)) / 8000, [1, 2, 4], [0.9])}
    for depth, width in simulation.depth_widths(counts.astype(float), 8000, [1, 2, 4], 0.9):
        assert abs(told[depth] - width) <= 0.08 * width + 60
