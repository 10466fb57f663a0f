"""Further laws, priors, likelihoods and measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions.density import fit_logconcave, mle
from ..functions.lattice import fit_logconcave_discrete, fit_zero_atom, symmetric_mle
from ..functions.statistics import beta_quantile, t_median
from ..operators import errors, estimates, grid, joint, likelihood, logcounters, metrics, variants
from ..sources import tables
from .base import LEVEL, ORACLE_SQL, PINNED, QUERIES, SPEC, SQL_HIST, Setting, add, sql_base
from .methods import SQL_MEASURED, SQL_POST, _measured, _pair
from .studies import _both_signs, frame

# --- Intervals --------------------------------------------------------------------------------------------------------------------------------


@add("ci_boot_mc")
def ci_boot_mc(spark, d):
    """The interval of a statistic that has no closed law: the midrange, its law drawn from the error law."""
    s = Setting(spark, d)
    draws = estimates.grid_law(s.grid).draws((50_000, SPEC.r), 11)
    x, m = np.unique((draws.min(axis=1) + draws.max(axis=1)) / 2, return_counts=True)
    midrange = lambda v: (F.array_min(v) + F.array_max(v)) / 2
    return estimates.debiased(s.probed, midrange, errors.Law(x, m), LEVEL)


_NEED = f"ceil({beta_quantile(0.95, 1, SPEC.r)!r} * {SPEC.cells - SPEC.r} - 1e-9)"


@add("ci_excl", f"{sql_base()}, {SQL_HIST}, o AS (SELECT p.item, p.s, hc.v, hc.cum - len(list_filter(p.s, lambda x: x <= hc.v)) AS cum FROM p, hc) SELECT item, any_value(s)[1] AS est, greatest(0, any_value(s)[1] - min(CASE WHEN cum >= {_NEED} THEN v END)) AS lo, any_value(s)[1] AS hi FROM o GROUP BY item")
def ci_excl(spark, d):
    s = Setting(spark, d)
    return estimates.min_interval_own_out(s.probed, estimates.grid_law(s.grid), SPEC.r)


# --- Densities and priors -----------------------------------------------------------------------------------------------------------------------


@add("density_fit_discrete")
def density_fit_discrete(spark, d):
    """Knots of the mass function on the integers."""
    f = estimates.grid_law(Setting(spark, d).grid)
    s = fit_logconcave_discrete(f.x, f.m)
    return frame(spark, list(zip(s.t.tolist(), s.phi.tolist(), strict=True)), "t double, phi double")


@add("density_zero_atom")
def density_zero_atom(spark, d):
    """Posterior means on a wide grid, where many cells are empty: an atom at 0 beside a density."""
    s = Setting(spark, d, spec=SPEC.__class__(4, 4000, "poly4"))
    f = estimates.grid_law(s.grid)
    return likelihood.bayes_estimates(s.probed, fit_zero_atom(f.x, f.m))


@add("bayes_posterior", f"{sql_base()}, {SQL_POST} SELECT item, n, round(q, 6) AS p FROM po WHERE q >= 0.001")
def bayes_posterior(spark, d):
    return likelihood.posteriors(Setting(spark, d).probed, PINNED, 0.001).select("item", "n", F.round("p", 6).alias("p"))


add("bayes_prior_flat", ORACLE_SQL["bayes_mean"])(QUERIES["bayes_mean"])


@add("bayes_prior_empirical")
def bayes_prior_empirical(spark, d):
    """The prior is the counts of a tenth of the items, chosen by hash."""
    s = Setting(spark, d)
    return likelihood.bayes_estimates(s.probed, PINNED, log_prior=likelihood.empirical_prior(variants.coordinated_sample(s.tuples, 0.1)))


@add("joint_scope")
def joint_scope(spark, d):
    """Joint estimates with the objective over all cells, and over the items' own cells alone."""
    s = Setting(spark, d)
    items, cells, values = joint.system(variants.top_items(s.tuples, 100).select("item"), s.grid)
    start = np.maximum(0, values[cells].min(axis=1) - estimates.grid_law(s.grid).order_mean(1, SPEC.r))
    both = {scope: joint.joint_mle(cells, values, start, scope=scope)[0] for scope in ("all", "own")}
    return frame(spark, [(i, float(a), float(b)) for i, a, b in zip(items, both["all"], both["own"], strict=True)], "item long, all_cells double, own_cells double")


# --- Other grids --------------------------------------------------------------------------------------------------------------------------------


@add("signed_mle")
def signed_mle(spark, d):
    t = tables.parts(spark, d)
    g = variants.build_signed(t, SPEC)
    spline = fit_logconcave(*_both_signs(estimates.grid_law(g)), trim=0.0)
    probed = variants.probe_signed(t.select("item").distinct(), g)
    return likelihood.by_item(probed, lambda v: [np.maximum(0, symmetric_mle(v, spline))], "est")


@add("logcounter_mle")
def logcounter_mle(spark, d):
    """(item, truth, est): likelihood over levels."""
    t, base = tables.parts(spark, d), 1.1
    levels = logcounters.build_logcounters(t, SPEC, base)
    f = estimates.grid_law(logcounters.values(levels, base))
    probed = grid.probe(t.select("item").distinct(), levels)
    found = likelihood.by_item(probed, lambda v: [logcounters.level_mle(v, f, base)], "est")
    return found.join(t.groupBy("item").agg(F.sum("c").alias("truth")), "item")


@add("distinct_debiased")
def distinct_debiased(spark, d):
    """Debiased minimum over cells that hold cardinality sketches: their own errors are part of the law."""
    rows = tables.table(spark, d, "lineitem").select(F.col("l_partkey").alias("item"), F.col("l_suppkey").alias("element"))
    g = variants.build_distinct(rows, SPEC, exact=False)
    truth = rows.groupBy("item").agg(F.countDistinct("element").alias("truth"))
    return estimates.debiased_min(grid.probe(truth.select("item"), g), estimates.grid_law(g), SPEC.r, mode="exact").join(truth, "item")


@add("ip_logconv")
def ip_logconv(spark, d):
    """Quantiles of the law of a product of two independent counters."""
    u, w = (estimates.grid_law(g) for g in _pair(spark, d))
    zero, x, share = variants.product_law(u.x, u.m, w.x, w.m)
    cum = zero + np.cumsum(share)
    at = lambda p: 0.0 if p <= zero else float(x[min(len(x) - 1, np.searchsorted(cum, p))])
    return frame(spark, [(p, at(p)) for p in (0.05, 0.25, 0.5, 0.75, 0.95)], "p double, product double")


# --- Measures -----------------------------------------------------------------------------------------------------------------------------------


@add("mse", f"{SQL_MEASURED} SELECT method, round(mse, 4) AS mse FROM a")
def mse(spark, d):
    return metrics.accuracy(_measured(spark, d)).select("method", F.round("mse", 4).alias("mse"))


@add("bias", f"{SQL_MEASURED} SELECT method, round(bias, 4) AS bias FROM a")
def bias(spark, d):
    return metrics.accuracy(_measured(spark, d)).select("method", F.round("bias", 4).alias("bias"))


@add("ci_width", f"{SQL_MEASURED} SELECT method, round(avg(hi - lo), 4) AS mean_width, round(median(hi - lo), 4) AS median_width FROM x GROUP BY method")
def ci_width(spark, d):
    width = F.col("hi") - F.col("lo")
    return _measured(spark, d).groupBy("method").agg(F.round(F.avg(width), 4).alias("mean_width"), F.round(F.median(width), 4).alias("median_width"))


add("ks_distance", ORACLE_SQL["err_ks"])(QUERIES["err_ks"])
add("fit_seconds")(QUERIES["n_knots"])
