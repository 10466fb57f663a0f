"""Further queries: simulations, streams, remaining variants, measures and workloads."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.density import LogSpline, conv_power, fit_logconcave, mle
from ..functions.hashing import GridSpec, cell_sql
from ..functions.statistics import beta_quantile, t_mean, t_median, t_min
from ..operators import errors, estimates, grid, joint, likelihood, logcounters, metrics, tuning, variants
from ..sources import tables
from ..sources.shared import keep, shared_folder
from ..streaming import grids as streams
from . import workloads
from .base import LEVEL, ORACLE_SQL, PINNED, QUERIES, SPEC, SQL_HIST, TUPLES_SQL, Setting, add, r6, sql_base, sql_grid, sql_probe, sql_rank
from .methods import SQL_IP, SQL_POST, _flag, _measured, _pair, _signed, _signed_probe_sql, _signed_sql

HALF = GridSpec(4, 250, "poly4")


def frame(spark, rows, schema) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# --- Likelihood and Bayes ---------------------------------------------------------------------------------------------------------------------


@add("density_tails")
def density_tails(spark, d):
    s = likelihood.density(estimates.grid_law(Setting(spark, d).grid))
    at = np.linspace(0, 1.5 * float(s.t[-1]), 60)
    return frame(spark, [(float(a), float(b)) for a, b in zip(at, s(at), strict=True)], "x double, log_density double")


@add("density_other")
def density_other(spark, d):
    """Mean log density of held-back counters under the log-concave fit, an exponential, a normal and a smoothed histogram."""
    f = estimates.grid_law(Setting(spark, d).grid)
    draws = f.draws((4000,), 5)
    fit, test = np.unique(draws[:2000], return_counts=True), draws[2000:]
    mean, sd = float(draws[:2000].mean()), float(draws[:2000].std()) + 1e-9
    kernel = np.exp(-((test[:, None] - fit[0][None, :]) ** 2) / (2 * (0.5 * sd) ** 2)) @ (fit[1] / 2000) / (0.5 * sd * np.sqrt(2 * np.pi))
    scores = {
        "log_concave": np.maximum(fit_logconcave(*fit, trim=0).extended()(test), -50).mean(), "exponential": (-np.log(mean + 1e-9) - test / (mean + 1e-9)).mean(),
        "normal": (-np.log(sd * np.sqrt(2 * np.pi)) - (test - mean) ** 2 / (2 * sd**2)).mean(), "kernel": np.log(np.maximum(kernel, 1e-20)).mean(),
    }
    return frame(spark, [(k, float(v)) for k, v in scores.items()], "density string, mean_log double")


# --- Joint ------------------------------------------------------------------------------------------------------------------------------------


@add("heavy_hitter_subtract", f"{sql_base()}, top AS (SELECT item, CAST(sum(c) AS BIGINT) AS c FROM t GROUP BY item ORDER BY c DESC, item LIMIT 50), u AS (SELECT item, c FROM t UNION ALL SELECT item, -c FROM top), {sql_grid('gr', 'u')}, rest AS (SELECT * FROM items WHERE item NOT IN (SELECT item FROM top)), {sql_probe('q', 'rest', 'gr')} SELECT item, s[1] * 1.0 AS est FROM q")
def heavy_hitter_subtract(spark, d):
    s = Setting(spark, d)
    top = variants.top_items(s.tuples, 50)
    rest = s.items.join(top, "item", "left_anti")
    return estimates.classical(grid.probe(rest, grid.subtract(s.grid, top)))


def _joint(spark, d, **how):
    s = Setting(spark, d)
    items, cells, values = joint.system(variants.top_items(s.tuples, 100).select("item"), s.grid)
    f = estimates.grid_law(s.grid)
    start = np.maximum(0, values[cells].min(axis=1) - f.order_mean(1, SPEC.r))
    if "spline" in how:
        how["spline"] = likelihood.density(f)
    theta, rounds = joint.joint_mle(cells, values, start, **how)
    return frame(spark, [(i, float(x), rounds) for i, x in zip(items, theta, strict=True)], "item long, est double, rounds int")


add("joint_mle_fixed_f")(lambda spark, d: _joint(spark, d, spline=True, update=False))
# --- Other grids ------------------------------------------------------------------------------------------------------------------------------


def _both_signs(f: errors.Law):
    x, at = np.unique(np.concatenate([f.x, -f.x]), return_inverse=True)
    return x, np.bincount(at, weights=np.concatenate([f.m, f.m])).astype(np.int64)


@add("ip_signed", f"WITH t AS (SELECT CAST(l_partkey AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM lineitem WHERE l_returnflag = 'R'), u AS (SELECT CAST(l_partkey AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM lineitem WHERE l_returnflag = 'A')" + "".join(_signed_sql().split("g AS (")[1].join([f", {n} AS (", ""]).replace("FROM t)", f"FROM {s})").replace("FROM t UNION", f"FROM {s} UNION") for n, s in (("g", "t"), ("w", "u"))) + " SELECT g.rep, CAST(sum(g.v * w.v) AS BIGINT) AS product FROM g JOIN w ON g.rep = w.rep AND g.idx = w.idx GROUP BY g.rep")
def ip_signed(spark, d):
    rows = tables.table(spark, d, "lineitem")
    u, w = (variants.build_signed(grid.tuples(rows.where(F.col("l_returnflag") == f), F.col("l_partkey")), SPEC) for f in ("R", "A"))
    return variants.inner_products(u, w).select("rep", "product")


@add("logcounter_build")
def logcounter_build(spark, d):
    return logcounters.build_logcounters(tables.parts(spark, d), SPEC).df


@add("logcounter_est")
def logcounter_est(spark, d):
    t = tables.parts(spark, d)
    g = logcounters.values(logcounters.build_logcounters(t, SPEC), 1.1)
    return estimates.debiased_min(grid.probe(t.select("item").distinct(), g), estimates.grid_law(g), SPEC.r, mode="exact")


@add("builtin_freq_sketch")
def builtin_freq_sketch(spark, d):
    """Spark's own frequency sketch, for timing: its cells can't be read, so it has the classical estimate only."""
    return tables.parts(spark, d).agg(F.count_min_sketch("item", F.lit(0.01), F.lit(0.95), F.lit(7)).alias("sketch")).select(F.octet_length("sketch").alias("bytes"))


# --- Tuning and simulation ------------------------------------------------------------------------------------------------------------------


@add("conv_power")
def conv_power_query(spark, d):
    """Predicted and rebuilt laws: the narrow grid's distribution from the wide one's, and their largest gap."""
    wide = grid.build_grid(tables.parts(spark, d), GridSpec(1, 2000, "poly4"))
    f = estimates.grid_law(wide)
    rows = []
    for factor in (2, 4, 8):
        real = estimates.grid_law(grid.fold(wide, factor))
        told = np.cumsum(conv_power(tuning.mass(f, int(real.x.max()) + 1), factor))
        rows.append((factor, float(np.abs(told[real.x.astype(int)] - np.cumsum(real.m) / real.n).max())))
    return frame(spark, rows, "factor int, ks double")


@add("tune_power")
def tune_power(spark, d):
    t = tables.parts(spark, d)
    f = estimates.grid_law(grid.build_grid(t, GridSpec(1, 4000, "poly4")))
    base, items = tuning.mass(f, 64 * (int(f.x.max()) + 1)), t.select("item").distinct().count()
    return frame(spark, [(float(w), tuning.budget_for(base, items / 4000, items, 4, 0.95, w)) for w in (20, 50, 100, 200)], "target double, cells long")


@add("tune_extrapolate")
def tune_extrapolate(spark, d):
    """Widths predicted from one grid against those of rebuilt grids."""
    t = tables.parts(spark, d)
    f = estimates.grid_law(grid.build_grid(t, GridSpec(1, 2000, "poly4")))
    told = {dp: w for dp, _, w in tuning.depth_widths(tuning.mass(f, 16 * (int(f.x.max()) + 1)), [2, 4, 8], [0.95])}
    rows = [(r, w, estimates.grid_law(grid.build_grid(t, GridSpec(r, 2000 // r, "poly4"))).quantile(beta_quantile(0.95, 1, r))) for r, w in told.items()]
    return frame(spark, rows, "r int, predicted double, rebuilt double")


@add("size_defaults")
def size_defaults(spark, d):
    f = estimates.grid_law(grid.build_grid(tables.parts(spark, d), GridSpec(1, 2000, "poly4")))
    base = tuning.mass(f, 32 * (int(f.x.max()) + 1))
    best = tuning.best_depth(base, 16, 0.95)
    return frame(spark, [("best", best[0], best[1])] + [("preset", dp, w) for dp, _, w in tuning.depth_widths(base, list(tuning.DEPTH_PRESETS), [0.95])], "kind string, depth int, width double")




def _rmse(est: np.ndarray, truth: float = 0.0) -> float:
    return float(np.sqrt(((est - est.mean()) ** 2).mean()))


def gap_laws(spark, d) -> dict[float, errors.Law]:
    """{a: law}: errors whose density starts as y^(a - 1), off the times between a user's events: squared, as they are, and to the next event but one, in seconds."""
    at = F.unix_seconds(F.col("ts").cast("timestamp"))
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    ahead = tables.table(spark, d, "events").where("ts IS NOT NULL").select(*[(F.lead(at, n).over(by) - at).alias(f"gap{n}") for n in (1, 2)])
    gaps = ahead.select(F.expr("stack(2, 1, gap1, 2, gap2) AS (n, v)"))
    told = keep(gaps.where("v IS NOT NULL").groupBy("n", "v").agg(F.count("*").alias("m")), "gaps")
    one, two = (errors.law(errors.cumulated(told.where(F.col("n") == n).select("v", "m"), "m")) for n in (1, 2))
    return {0.5: errors.Law(one.x**2, one.m), 1.0: one, 2.0: two}


@add("regimes")
def regimes(spark, d):
    """Spread of min, mean and median over the errors' mean when their density starts as y^(a - 1), by draws from the laws of all gaps between events."""
    rows = []
    for a, f in gap_laws(spark, d).items():
        for r in (4, 16, 64):
            e = f.draws((4000, r), seed=r) / f.mean()
            rows.append((a, r, _rmse(e.min(axis=1)), _rmse(e.mean(axis=1)), _rmse(np.median(e, axis=1))))
    return frame(spark, rows, "a double, r int, min double, mean double, median double")


def _compound(g, load: float, alpha: float, n: int) -> np.ndarray:
    return np.asarray([np.minimum(g.zipf(alpha, k), 10_000).sum() for k in g.poisson(load, n)], dtype=np.float64)


@add("w10_density")
def w10_density(spark, d):
    """Log mass of a compound Poisson law and its fit at three trims."""
    g = np.random.default_rng(0)
    x, m = np.unique(_compound(g, 64, 3.0, 20_000), return_counts=True)
    fits = {t: fit_logconcave(x, m, t).extended() for t in (0.001, 0.01, 0.05)}
    return frame(spark, [(float(a), float(np.log(n / m.sum())), t, float(s(np.asarray([a]))[0])) for t, s in fits.items() for a, n in zip(x, m, strict=True)], "x double, log_mass double, trim double, log_fit double")


# --- Measures and workloads -------------------------------------------------------------------------------------------------------------------


@add("n_knots")
def n_knots(spark, d):
    f = estimates.grid_law(Setting(spark, d).grid)
    began = time.perf_counter()
    s = fit_logconcave(f.x, f.m)
    return frame(spark, [(len(s.t), time.perf_counter() - began)], "knots int, seconds double")


@add("space_cells", f"{sql_base()} SELECT CAST(4 AS INTEGER) AS r, CAST(250 AS INTEGER) AS k, CAST(1000 AS INTEGER) AS cells, CAST(8000 AS INTEGER) AS bytes, count(*) FILTER (WHERE v <> 0) AS used FROM g")
def space_cells(spark, d):
    """What a grid takes when all its cells are held, and how many of them the parts use."""
    used = F.count(F.when(F.col("v") != 0, 1)).alias("used")
    return grid.build_grid(tables.parts(spark, d), SPEC).df.agg(*[F.lit(n).alias(c) for c, n in (("r", SPEC.r), ("k", SPEC.k), ("cells", SPEC.cells), ("bytes", 8 * SPEC.cells))], used)


# --- Streams ----------------------------------------------------------------------------------------------------------------------------------


def _events(spark, d) -> DataFrame:
    return tables.stream(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), F.col("ts").cast("timestamp").alias("ts"), "event_id")


def _folder(spark) -> str:
    return shared_folder(spark)


SMALL = GridSpec(2, 16, "poly4")


def _window_sql() -> str:
    each = " UNION ALL ".join(f"SELECT w, {a} AS rep, {cell_sql('item', a, SMALL)} AS idx FROM t" for a in range(2))
    return f"WITH t AS (SELECT CAST(user_id AS BIGINT) AS item, date_trunc('day', ts) AS w FROM events) SELECT CAST(epoch(w) AS BIGINT) AS start, CAST(rep AS INTEGER) AS rep, idx, count(*) AS v FROM ({each}) GROUP BY w, rep, idx"


@add("stream_tumbling", _window_sql())
def stream_tumbling(spark, d):
    grids = streams.drained(streams.window_grids(_events(spark, d), SMALL, "1 day", late="3650 days"), _folder(spark))
    return grids.select(F.unix_timestamp("window.start").alias("start"), "rep", "idx", "v")


@add("stream_dedup", f"WITH t AS ({TUPLES_SQL['users']}), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def stream_dedup(spark, d):
    once = _events(spark, d).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["event_id"])
    return streams.drained(streams.stream_grid(once, SPEC), _folder(spark))
