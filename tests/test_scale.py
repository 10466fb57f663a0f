"""Kept grids, laws and posteriors at size, own counters left out, joint solutions, and streams that stop and start again."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallygrid.functions.density import LogSpline, bayes, fit_logconcave, posterior
from tallygrid.functions.hashing import GridSpec
from tallygrid.functions.lattice import fit_zero_atom
from tallygrid.functions.statistics import t_mean, t_median, t_min
from tallygrid.operators import errors, estimates, grid, joint, likelihood, store, variants
from tallygrid.plans import base
from tallygrid.sources import tables
from tallygrid.streaming import grids as streams

SPEC = GridSpec(3, 40, "poly4")


def cells(g):
    return {(r["rep"], r["idx"]): r["v"] for r in g.df.collect() if r["v"]}


def test_a_grid_is_kept_with_its_spec(spark, sf, tmp_path):
    g = grid.build_grid(tables.parts(spark, sf), SPEC)
    store.save_grid(g, f"{tmp_path}/g", "bigint")
    again = store.load_grid(spark, f"{tmp_path}/g", SPEC, "bigint")
    assert cells(again) == cells(g) and again.spec == SPEC
    for spec, item in ((GridSpec(3, 40, "poly4", 12), "bigint"), (GridSpec(3, 41, "poly4"), "bigint"), (SPEC, "string")):
        with pytest.raises(ValueError):
            store.load_grid(spark, f"{tmp_path}/g", spec, item)


def test_an_answer_reads_its_source_once(spark, sf):
    """The plan of the debiased minimum holds kept files only; each replicate's cells come from their own folder."""
    s = base.Setting(spark, sf)
    plan = estimates.debiased_min(s.probed, estimates.grid_law(s.grid), 4)._jdf.queryExecution().executedPlan().toString()
    assert "lineitem" not in plan and "l_partkey" not in plan and plan.count("BroadcastHashJoin") == 4 and "Python" not in plan and "Arrow" not in plan
    assert all("rep#" in line and "PartitionFilters: [isnotnull(rep" in line for line in plan.splitlines() if "grid-" in line and "FileScan" in line)


def test_dense_build_in_levels(spark, sf, monkeypatch):
    monkeypatch.setattr(grid, "FAN", 2)
    rows = tables.parts(spark, sf).repartition(9)
    assert cells(grid.build_grid_dense(rows, SPEC)) == cells(grid.build_grid(rows, SPEC))


def test_running_sums_in_two_levels(spark):
    g = np.random.default_rng(0)
    v = np.unique(np.concatenate([g.integers(-500, 500, 300), g.integers(10**9, 10**9 + 10**6, 300), [0]]))
    m = g.integers(1, 9, len(v))
    df = spark.createDataFrame([(int(a), int(b)) for a, b in zip(v, m, strict=True)], "v long, m long").repartition(5)
    got = sorted((r["v"], r["cum"]) for r in errors.cumulated(df, "m").collect())
    assert [c for _, c in got] == np.cumsum(m).tolist()


def test_a_law_of_eight_million_counters(spark):
    hist = spark.range(8_000_000).select((F.col("id") * 3).alias("v"), F.lit(1).cast("long").alias("m"))
    f = errors.law(hist)
    assert f.n == 8_000_000 and f.quantile(0.5) == 3 * 3_999_999 and f.order_mean(1, 4) == pytest.approx(3 * 8e6 / 5, rel=1e-3)
    few = errors.law(hist.where("v < 3000000"), most=1000)
    assert 900 <= len(few.x) <= 1001 and few.n == 1_000_000 and few.quantile(0.25) == pytest.approx(750_000, abs=3_000) and few.mean() == pytest.approx(3 * 999_999 / 2)


def test_a_posterior_at_a_billion():
    s = LogSpline(np.asarray([0.0, 50.0, 400.0]), np.asarray([-6.0, -2.0, -20.0]))
    v = np.asarray([10**9, 10**9 + 40, 10**9 + 90], dtype=float)
    n, p = posterior(v, s)
    small, q = posterior(v - 10**9 + 5000, s)
    assert n.tolist() == (small + 10**9 - 5000).tolist() and p == pytest.approx(q) and len(n) < 2000
    flat = LogSpline(np.asarray([0.0, 1e8]), np.asarray([-18.0, -20.0]))
    n, p = posterior(np.asarray([6e8, 6.2e8]), flat)
    assert len(n) <= 32_768 and p.sum() == pytest.approx(1)
    every = np.linspace(0, 6e8, 200_001)
    w = np.exp(flat(6e8 - every) + flat(6.2e8 - every) + 36)
    assert n @ p == pytest.approx(every @ w / w.sum(), rel=1e-3)


def test_posterior_with_an_atom_and_a_prior_against_all_counts():
    g = np.random.default_rng(3)
    x, m = np.unique(np.where(g.random(400) < 0.4, 0, g.gamma(2, 20, 400).astype(int)), return_counts=True)
    f = fit_zero_atom(x, m)
    prior = lambda n: -2 * np.log(n + 1)
    for v in ([30.0, 55, 200], [7, 7, 90], [0, 3, 4]):
        n = np.arange(min(v) + 1)
        told = sum(f(a - n) for a in v) + prior(n)
        w = np.exp(told - told.max())
        got = dict(zip(*posterior(np.asarray(v), f, prior), strict=True))
        want = {k: x for k, x in zip(n, w / w.sum(), strict=True) if x > 1e-14}
        assert got.keys() >= want.keys() and all(got[k] == pytest.approx(x, abs=1e-9) for k, x in want.items())


def test_capped_loss_against_all_pairs():
    g = np.random.default_rng(1)
    n, p = np.sort(g.choice(500, 60, replace=False)).astype(float), g.random(60)
    p /= p.sum()
    for c in (0.5, 3.0, 40.0, 1e4):
        cost = np.minimum(np.abs(n[:, None] - n), c) @ p
        assert bayes(n, p, "capped", c) == n[np.flatnonzero(cost <= cost.min() + 1e-12)[0]]


def test_own_counters_left_out_against_the_law_without_them():
    g = np.random.default_rng(2)
    values = g.poisson(6, 400).astype(float)
    f = errors.Law(*np.unique(values, return_counts=True))
    own = estimates.OwnOut(f, 4)
    v = values[g.integers(0, 400, (50, 4))]
    for i in range(50):
        if any((v[i] == x).sum() > f.m[f.x == x][0] for x in v[i]):
            continue
        rest = f.without(v[i])
        assert own.means(v[i : i + 1])[0] == pytest.approx(rest.order_mean(1, 4)) and own.quantiles(v[i : i + 1], 0.3)[0] == rest.quantile(0.3)


# --- joint


def system(seed, items=2, k=12, r=3, noise=30):
    g = np.random.default_rng(seed)
    counts = np.concatenate([g.integers(50, 200, items), g.integers(0, 12, noise)]).astype(float)
    own = g.integers(0, k, (len(counts), r)) + np.arange(r) * k
    return own[:items], np.bincount(own.ravel(), weights=np.repeat(counts, r), minlength=r * k), counts[:items]


@pytest.mark.parametrize("loss", ["l1", "l2", "likelihood"])
def test_constrained_against_exhaustive_search(loss):
    for seed in range(4):
        own, values, truth = system(seed)
        s = fit_logconcave(*np.unique(values, return_counts=True)).extended()
        seen, at = np.unique(own, return_inverse=True)
        at, v = at.reshape(own.shape), values[seen]
        cost = {"l1": lambda e: np.abs(e).sum(), "l2": lambda e: (e**2).sum(), "likelihood": lambda e: -s(np.maximum(0, e)).sum()}[loss]

        def residual(t, at=at, v=v, seen=seen):
            return v - np.bincount(at.ravel(), weights=np.repeat(t, 3), minlength=len(seen))

        tops = [int(values[row].min()) for row in own]
        best = min(cost(e) for t in itertools.product(*[range(0, n + 1, 2) for n in tops]) if (e := residual(np.asarray(t, float))).min() >= 0)
        got = joint.constrained(own, values, np.asarray(tops, float) / 2, loss, s)
        assert got.min() >= 0 and residual(got).min() >= -1e-9 and cost(residual(got)) <= best + 0.02 * abs(best) + 1e-6


def test_joint_likelihood_keeps_its_best_on_items_that_share_cells():
    """Items in the same cells overshoot together: what is returned is no worse than the start, and within the cells."""
    own = np.asarray([[0, 12, 24], [0, 12, 25], [0, 13, 24]])
    values = np.concatenate([np.full(36, 5.0)])
    values[[0, 12, 24, 13, 25]] = [305, 205, 208, 104, 103]
    s = fit_logconcave(*np.unique(values[values < 50], return_counts=True), trim=0).extended() if len(np.unique(values[values < 50])) > 1 else LogSpline(np.asarray([0.0, 5.0, 20.0]), np.asarray([-4.0, -1.0, -9.0]))
    left = lambda t: values - np.bincount(own.ravel(), weights=np.repeat(t, 3), minlength=36)
    told = lambda t: s(np.maximum(0, left(t))).sum()
    start = np.asarray([100.0, 100.0, 100.0])
    got, _ = joint.joint_mle(own, values, start, spline=s, update=False, rounds=30)
    assert told(got) >= told(start) - 1e-9 and got.min() >= 0


def test_joint_on_the_cluster_is_near_the_drivers(spark, sf):
    s = base.Setting(spark, sf, tables.users, GridSpec(4, 60, "poly4"))
    items, own, values = joint.system(s.items, s.grid)
    spline = likelihood.density(estimates.grid_law(s.grid))
    start = np.maximum(0, values[own].min(axis=1) - estimates.grid_law(s.grid).order_mean(1, 4))
    here = start.copy()
    for _ in range(2):
        rest = values - np.bincount(own.ravel(), weights=np.repeat(here, 4), minlength=len(values))
        v = rest[own] + here[:, None]
        here = 0.5 * (here + np.clip(joint._steps(v, spline), 0, np.maximum(0, v.min(axis=1))))
    there = {r["item"]: r["est"] for r in joint.joint_mle_cluster(s.items, s.grid, 2, spline=spline).collect()}
    assert [there[i] for i in items] == pytest.approx(here.tolist(), abs=1e-6)


# --- streams


def batches(spark, sf, n=4):
    rows = tables.users(spark, sf).withColumn("k", F.monotonically_increasing_id() % n)
    return [rows.where(F.col("k") == i).select("item", "c") for i in range(n)]


def test_stores_go_on_after_a_restart(spark, sf, tmp_path):
    """Every batch with a store made anew, one batch twice, compaction in between: the same as all at once."""
    want = cells(grid.build_grid(tables.users(spark, sf), SPEC))
    for k, part in enumerate(batches(spark, sf)):
        for _ in range(1 + (k == 2)):
            streams.BatchGrids(str(tmp_path), SPEC, name="a", compact=2).absorb(part, k)
            streams.ConservativeGrid(str(tmp_path), SPEC, name="a").absorb(part, k)
            streams.TopItems(str(tmp_path), SPEC, 5, name="t").absorb(part, k)
            streams.AutoEstimator(str(tmp_path), SPEC, {"min": t_min, "mean": t_mean, "median": t_median}, name="u").absorb(part, k)
            streams.LazyDensity(str(tmp_path), SPEC, 0.2, name="l").absorb(part, k)
    kept = streams.BatchGrids(str(tmp_path), SPEC, name="a", compact=2)
    assert cells(kept.grid(spark)) == want and [p.split("/")[-2] for p in kept.sets(spark)] == ["merged"]
    careful = cells(streams.ConservativeGrid(str(tmp_path), SPEC, name="a").grid(spark))
    assert all(careful[c] <= want[c] for c in careful)
    assert streams.TopItems(str(tmp_path), SPEC, 5, name="t").items(spark).count() == 5
    assert streams.AutoEstimator(str(tmp_path), SPEC, {}, name="u").choices(spark).count() == 4
    steps = streams.LazyDensity(str(tmp_path), SPEC, 0.2, name="l").steps(spark).orderBy("batch").collect()
    assert [r["batch"] for r in steps] == [0, 1, 2, 3] and steps[0]["refitted"] and all(r["refitted"] == (r["ks"] >= 0.2) for r in steps)


def test_empty_streams(spark, tmp_path):
    for kept in (streams.BatchGrids(str(tmp_path), SPEC), streams.ConservativeGrid(str(tmp_path), SPEC)):
        assert kept.grid(spark).df.count() == 0
    assert streams.TopItems(str(tmp_path), SPEC, 5).items(spark).count() == 0


def test_signed_probes_from_a_kept_grid(spark, sf):
    t = tables.users(spark, sf)
    g = variants.build_signed(t, SPEC)
    a, b = (sorted((r["item"], tuple(r["v"])) for r in variants.probe_signed(t.select("item").distinct(), x).collect()) for x in (g, store.kept(g)))
    assert a == b
