"""Queries of the methods: grids, error laws, estimates and intervals, likelihood, joint estimates, baselines, inner products, tuning, measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.density import LogSpline
from ..functions.hashing import GridSpec, cell_sql, sign_sql
from ..functions.statistics import beta_quantile, t_mean, t_median, t_min
from ..operators import errors, estimates, grid, joint, likelihood, metrics, tuning, variants
from ..sources import tables
from ..sources.shared import keep, shared_folder
from ..streaming import grids as streams
from .base import LEVEL, LINE, ORACLE_SQL, PINNED, PINNED_SQL, QUERIES, SPEC, SQL_HIST, STATS, TUPLES_SQL, WORD_SPEC, Setting, add, r6, sql_base, sql_columns, sql_grid, sql_law, sql_probe, sql_rank

# --- Grids and linear algebra ----------------------------------------------------------------------------------------------------------


@add("hash_cells", f"{sql_base()} SELECT item, {', '.join(f'{cell_sql("item", a, SPEC)} AS i{a}' for a in range(4))} FROM items")
def hash_cells(spark, d):
    s = Setting(spark, d)
    return s.items.select("item", *[grid.cell(F.col("item"), a, SPEC).alias(f"i{a}") for a in range(4)])


@add("grid_build", f"{sql_base()} SELECT rep, idx, v FROM g")
def grid_build(spark, d):
    return Setting(spark, d).grid.df


@add("grid_build_dense", f"{sql_base()} SELECT rep, idx, v FROM g WHERE v <> 0")
def grid_build_dense(spark, d):
    return grid.build_grid_dense(tables.parts(spark, d), SPEC).df


@add("grid_build_words", f"WITH t AS ({TUPLES_SQL['words']}), {sql_grid('g', 't', WORD_SPEC)} SELECT rep, idx, v FROM g")
def grid_build_words(spark, d):
    return grid.build_grid(tables.words(spark, d), WORD_SPEC).df


@add("grid_depth1", f"WITH t AS ({TUPLES_SQL['quantities']}), {sql_grid('g', 't', LINE)} SELECT rep, idx, v FROM g")
def grid_depth1(spark, d):
    return grid.build_grid(tables.part_quantities(spark, d), LINE).df


@add("grid_merge", f"WITH t AS ({TUPLES_SQL['parts']} UNION ALL {TUPLES_SQL['users']}), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def grid_merge(spark, d):
    return grid.merge(grid.build_grid(tables.parts(spark, d), SPEC), grid.build_grid(tables.users(spark, d), SPEC)).df


@add("grid_subtract", f"WITH t AS ({TUPLES_SQL['parts']}), k AS (SELECT item, -c AS c FROM t WHERE item <= 100), u AS (SELECT * FROM t UNION ALL SELECT * FROM k), {sql_grid('g', 'u')} SELECT rep, idx, v FROM g")
def grid_subtract(spark, d):
    t = tables.parts(spark, d)
    return grid.subtract(grid.build_grid(t, SPEC), t.where("item <= 100")).df


@add("grid_scale", f"{sql_base()} SELECT rep, idx, 3 * v AS v FROM g")
def grid_scale(spark, d):
    return grid.scale(Setting(spark, d).grid, 3).df


@add("grid_fold", f"{sql_base()} SELECT rep, idx % 125 AS idx, CAST(sum(v) AS BIGINT) AS v FROM g GROUP BY rep, idx % 125")
def grid_fold(spark, d):
    return grid.fold(Setting(spark, d).grid, 2).df


@add("probe", f"{sql_base()} SELECT item, v0, v1, v2, v3 FROM p")
def probe(spark, d):
    return Setting(spark, d).probed.select("item", *[F.col("v")[a].alias(f"v{a}") for a in range(4)])


@add("incidence", f"{sql_base()} " + " UNION ALL ".join(f"SELECT item, CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, SPEC)} AS idx FROM items" for a in range(4)))
def incidence(spark, d):
    return grid.incidence(Setting(spark, d).items, SPEC)


SQL_INC = "inc AS (" + " UNION ALL ".join(f"SELECT item, CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, SPEC)} AS idx FROM items" for a in range(4)) + ")"


@add("collisions", f"{sql_base()}, {SQL_INC} SELECT rep, idx, count(*) AS load FROM inc GROUP BY rep, idx")
def collisions(spark, d):
    return grid.cell_load(Setting(spark, d).items, SPEC)


@add("error_vector", f"{sql_base()}, {SQL_INC}, truth AS (SELECT item, CAST(sum(c) AS BIGINT) AS c FROM t GROUP BY item) SELECT inc.item, inc.rep, g.v - truth.c AS error FROM inc JOIN truth USING (item) JOIN g ON g.rep = inc.rep AND g.idx = inc.idx")
def error_vector(spark, d):
    s = Setting(spark, d)
    return grid.true_errors(s.grid, s.truth)


@add("set_query", f"{sql_base()} SELECT p_brand AS brand, CAST(sum(s[1]) AS BIGINT) AS est FROM p JOIN part ON p_partkey = item GROUP BY p_brand")
def set_query(spark, d):
    s = Setting(spark, d)
    sets = tables.table(spark, d, "part").select(F.col("p_partkey").alias("item"), F.col("p_brand").alias("brand"))
    return s.probed.join(sets, "item").groupBy("brand").agg(F.sum(F.array_min("v")).alias("est"))


RANGES = [(1, 10), (5, 37), (17, 17), (0, 63)]
DYADIC_SPEC = GridSpec(4, 64, "poly4")


def _range_sql() -> str:
    cover = ", ".join(f"({low}, {high}, CAST({x} AS BIGINT))" for low, high in RANGES for x in grid.dyadic_cover(low, high, 6))
    spread = " UNION ALL ".join(f"SELECT {l} * 64 + (q >> {l}) AS item, CAST(1 AS BIGINT) AS c FROM b" for l in range(6))
    return f"WITH b AS (SELECT CAST(l_quantity AS BIGINT) AS q FROM lineitem), t AS ({spread}), cover(low, high, item) AS (VALUES {cover}), {sql_grid('g', 't', DYADIC_SPEC)}, {sql_probe('p', 'cover', 'g', DYADIC_SPEC)} SELECT CAST(low AS BIGINT) AS low, CAST(high AS BIGINT) AS high, CAST(sum(s[1]) AS BIGINT) AS est FROM p GROUP BY low, high"


@add("range_query", _range_sql())
def range_query(spark, d):
    t = tables.table(spark, d, "lineitem").select(F.col("l_quantity").cast("long").alias("item"), F.lit(1).cast("long").alias("c"))
    g = grid.build_grid(grid.dyadic(t, 6), DYADIC_SPEC)
    cover = spark.createDataFrame([(low, high, x) for low, high in RANGES for x in grid.dyadic_cover(low, high, 6)], "low long, high long, item long")
    return grid.probe(cover, g).groupBy("low", "high").agg(F.sum(F.array_min("v")).alias("est"))


# --- Error laws ----------------------------------------------------------------------------------------------------------------------------


@add("err_hist", f"{sql_base()}, {SQL_HIST} SELECT v, m, cum FROM hc")
def err_hist(spark, d):
    return errors.error_hist(Setting(spark, d).grid)


@add("err_hist_excl", f"{sql_base()}, own AS ({' UNION '.join(f'SELECT {a} AS rep, {cell_sql("item", a, SPEC)} AS idx FROM items WHERE item <= 20' for a in range(4))}), n AS (SELECT v FROM g WHERE NOT EXISTS (SELECT 1 FROM own WHERE own.rep = g.rep AND own.idx = g.idx)), h AS (SELECT v, CAST(sum(m) AS BIGINT) AS m FROM (SELECT v, count(*) AS m FROM n GROUP BY v UNION ALL SELECT 0, {SPEC.cells} - (SELECT count(*) FROM n) - (SELECT count(*) FROM own)) GROUP BY v HAVING sum(m) > 0) SELECT v, m, CAST(sum(m) OVER (ORDER BY v) AS BIGINT) AS cum FROM h")
def err_hist_excl(spark, d):
    s = Setting(spark, d)
    return errors.error_hist(s.grid, s.items.where("item <= 20"))


@add("err_quantile", f"{sql_base()}, {SQL_HIST} SELECT (SELECT min(v) FROM hc WHERE cum >= ceil(0.25 * {SPEC.cells})) AS q")
def err_quantile(spark, d):
    return errors.hist_quantile(errors.error_hist(Setting(spark, d).grid), F.lit(0.25))


@add("err_cdf", f"{sql_base()}, {SQL_HIST} SELECT v, round(cum / {SPEC.cells}.0, 9) AS f, round((cum - m) / {SPEC.cells}.0, 9) AS f_left FROM hc")
def err_cdf(spark, d):
    h = errors.error_hist(Setting(spark, d).grid)
    return h.select("v", F.round(F.col("cum") / SPEC.cells, 9).alias("f"), F.round((F.col("cum") - F.col("m")) / SPEC.cells, 9).alias("f_left"))


@add("err_column_stats", f"{sql_base()}, {sql_columns()} SELECT idx, round(s[1] * 1.0, 6) AS low, round(list_sum(s) / 4.0, 6) AS mean, round((s[2] + s[3]) / 2.0, 6) AS median FROM k")
def err_column_stats(spark, d):
    v = F.col("v")
    return errors.columns(Setting(spark, d).grid).select("idx", r6(t_min(v)).alias("low"), r6(t_mean(v)).alias("mean"), r6(t_median(v)).alias("median"))


@add("err_mc_boot")
def err_mc_boot(spark, d):
    draws = estimates.grid_law(Setting(spark, d).grid).draws((20_000, SPEC.r), seed=1).min(axis=1)
    x, m = np.unique(draws, return_counts=True)
    return spark.createDataFrame([(float(a), int(b)) for a, b in zip(x, m, strict=True)], "v double, m long")


@add("beta_quantile", "SELECT r, round(1 - pow(1 - 0.95, 1.0 / r), 9) AS q FROM (SELECT DISTINCT CAST(count(*) AS INTEGER) AS r FROM orders WHERE o_custkey IS NOT NULL GROUP BY o_custkey)")
def beta_quantiles(spark, d):
    """The 0.95 quantile of the least of as many uniforms as a customer has orders, for each such number."""
    depths = tables.customers(spark, d).groupBy("item").agg(F.sum("c").cast("int").alias("r")).select("r").distinct()

    def quantiles(frames):
        for pdf in frames:
            yield pdf.assign(q=[round(beta_quantile(0.95, 1, int(r)), 9) for r in pdf["r"]])

    return depths.mapInPandas(quantiles, "r int, q double")


SQL_EXACT_MIN = f"(SELECT sum(v * (pow(1 - (cum - m) / {SPEC.cells}.0, 4) - pow(1 - cum / {SPEC.cells}.0, 4))) FROM hc)"


@add("order_mean", f"{sql_base()}, {SQL_HIST} SELECT round({SQL_EXACT_MIN}, 6) AS exact, round({sql_rank(1 / 5)} * 1.0, 6) AS plugin, round({sql_rank(1 / 4)} * 1.0, 6) AS rank")
def order_mean(spark, d):
    f = estimates.grid_law(Setting(spark, d).grid)
    return spark.createDataFrame([tuple(round(f.order_mean(1, 4, m), 6) for m in ("exact", "plugin", "rank"))], "exact double, plugin double, rank double")


@add("err_ks", f"WITH t AS ({TUPLES_SQL['parts']}), u AS ({TUPLES_SQL['parts']} WHERE l_returnflag <> 'N'), {sql_grid('g', 't')}, {sql_grid('gu', 'u')}, {SQL_HIST}, hu AS (SELECT v, sum(m) AS m FROM (SELECT v, count(*) AS m FROM gu GROUP BY v UNION ALL SELECT 0, {SPEC.cells} - count(*) FROM gu) GROUP BY v), b AS (SELECT coalesce(h.v, hu.v) AS v, coalesce(h.m, 0) AS a, coalesce(hu.m, 0) AS b FROM h FULL OUTER JOIN hu ON h.v = hu.v) SELECT round(max(abs(x)), 9) AS ks FROM (SELECT (sum(a) OVER (ORDER BY v) - sum(b) OVER (ORDER BY v)) / {SPEC.cells}.0 AS x FROM b)")
def err_ks(spark, d):
    some = grid.tuples(tables.table(spark, d, "lineitem").where("l_returnflag <> 'N'"), F.col("l_partkey"))
    a, b = Setting(spark, d).grid, grid.build_grid(some, SPEC)
    return errors.ks(errors.error_hist(a), errors.error_hist(b)).select(F.round("ks", 9).alias("ks"))


# --- Statistics, debiased estimates, intervals --------------------------------------------------------------------------------------------


def _add_statistic(name: str) -> None:
    statistic, sql = STATS[name]
    add(f"est_{name}", f"{sql_base()} SELECT item, round({sql}, 6) AS est FROM p")(lambda spark, d: estimates.classical(Setting(spark, d).probed, statistic).select("item", r6("est").alias("est")))
    if name == "min":
        return
    low, high = (sql_rank(q, SPEC.k, "lc") for q in ((1 - LEVEL) / 2, (1 + LEVEL) / 2))

    def run(spark, d):
        s = Setting(spark, d)
        e = estimates.debiased(s.probed, statistic, estimates.statistic_law(s.grid, statistic), LEVEL)
        return e.select("item", *[r6(c).alias(c) for c in ("est", "lo", "hi")])

    add(f"deb_{name}", f"{sql_base()}, {sql_law(sql)} SELECT item, round(greatest(0, {sql} - mu), 6) AS est, round(greatest(0, {sql} - {high}), 6) AS lo, round({sql} - {low}, 6) AS hi FROM p, mu")(run)


for _name in STATS:
    _add_statistic(_name)


def _add_debiased_min(name: str, mode: str, bias: str, truncate: bool = True) -> None:
    high = sql_rank(beta_quantile(0.95, 1, SPEC.r))
    zero = "greatest(0, {})" if truncate else "({})"

    def run(spark, d):
        s = Setting(spark, d)
        e = estimates.debiased_min(s.probed, estimates.grid_law(s.grid), SPEC.r, 0.95, mode, truncate)
        return e.select("item", *[r6(c).alias(c) for c in ("est", "lo", "hi")])

    add(name, f"{sql_base()}, {SQL_HIST} SELECT item, round({zero.format(f's[1] - {bias}')} * 1.0, 6) AS est, round({zero.format(f's[1] - {high}')} * 1.0, 6) AS lo, round(s[1] * 1.0, 6) AS hi FROM p")(run)


_add_debiased_min("deb_min", "plugin", sql_rank(1 / 5))
_add_debiased_min("deb_min_rank", "rank", sql_rank(1 / 4))
_add_debiased_min("deb_min_exact", "exact", SQL_EXACT_MIN)
_add_debiased_min("ci_min_onesided", "exact", SQL_EXACT_MIN)
_add_debiased_min("deb_untruncated", "exact", SQL_EXACT_MIN, truncate=False)

SQL_OWN_OUT = f"o AS (SELECT p.item, p.s, hc.v, (hc.cum - len(list_filter(p.s, lambda x: x <= hc.v))) / {SPEC.cells - SPEC.r}.0 AS f FROM p, hc), q AS (SELECT item, s, v, f, lag(f, 1, 0) OVER (PARTITION BY item ORDER BY v) AS fl FROM o)"


@add("deb_exact_excl", f"{sql_base()}, {SQL_HIST}, {SQL_OWN_OUT} SELECT item, round(greatest(0, any_value(s)[1] - sum(v * (pow(1 - fl, 4) - pow(1 - f, 4)))), 5) AS est FROM q GROUP BY item")
def deb_exact_excl(spark, d):
    s = Setting(spark, d)
    return estimates.debiased_min_own_out(s.probed, estimates.grid_law(s.grid), SPEC.r).select("item", F.round("est", 5).alias("est"))


@add("deb_mc")
def deb_mc(spark, d):
    s = Setting(spark, d)
    x, m = np.unique(np.median(estimates.grid_law(s.grid).draws((20_000, SPEC.r), seed=2), axis=1), return_counts=True)
    return estimates.debiased(s.probed, t_median, errors.Law(x, m), LEVEL)


@add("ci_order_twosided", f"{sql_base()}, {SQL_HIST} SELECT item, round(greatest(0, s[2] - {sql_rank(beta_quantile(0.95, 2, 4))}) * 1.0, 6) AS lo, round((s[2] - {sql_rank(beta_quantile(0.05, 2, 4))}) * 1.0, 6) AS hi FROM p")
def ci_order_twosided(spark, d):
    s = Setting(spark, d)
    return estimates.debiased_order(s.probed, estimates.grid_law(s.grid), 2, SPEC.r, LEVEL).select("item", r6("lo").alias("lo"), r6("hi").alias("hi"))


@add("ci_boot", ORACLE_SQL["deb_median"])
def ci_boot(spark, d):
    return QUERIES["deb_median"](spark, d)


@add("ci_as_bound", f"WITH e AS ({ORACLE_SQL['deb_median']}) SELECT item, round((lo + hi) / 2, 6) AS centre, round((hi - lo) / 2, 6) AS delta FROM e")
def ci_as_bound(spark, d):
    return estimates.as_error_bound(QUERIES["deb_median"](spark, d)).select("item", r6("centre").alias("centre"), r6("delta").alias("delta"))


@add("ci_markov", f"{sql_base()} SELECT item, round(s[1] * 1.0, 6) AS est, round(greatest(0, s[1] - (SELECT sum(c) FROM t) * pow(0.1, -0.25) / 250), 4) AS lo FROM p")
def ci_markov(spark, d):
    s = Setting(spark, d)
    n = float(s.tuples.agg(F.sum("c")).first()[0])
    return estimates.markov_ci(s.probed, n, 4, 250, LEVEL).select("item", r6("est").alias("est"), F.round("lo", 4).alias("lo"))


@add("ci_markov_opt", "SELECT round(1000 / ln(10), 6) AS k, round(exp(1) * ln(10) * count(*) / 1000, 6) AS width FROM lineitem")
def ci_markov_opt(spark, d):
    n = tables.parts(spark, d).agg(F.sum("c")).first()[0]
    k, w = estimates.markov_best(float(n), 1000, LEVEL)
    return spark.createDataFrame([(round(k, 6), round(w, 6))], "k double, width double")


@add("ci_topheavy", "SELECT round(count(*) / (250 * (pow(0.1, 0.25) - 20 / 250.0)), 6) AS width FROM lineitem WHERE l_partkey NOT IN (SELECT l_partkey FROM lineitem GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 20)")
def ci_topheavy(spark, d):
    t = tables.parts(spark, d)
    rest = t.agg(F.sum("c")).first()[0] - variants.top_items(t, 20).agg(F.sum("c")).first()[0]
    return spark.createDataFrame([(round(estimates.top_heavy_width(float(rest), 20, 4, 250, LEVEL), 6),)], "width double")


CLASSIC = GridSpec(*estimates.size_classic(0.001, 0.01), "poly4")


@add("ci_classic_guarantee", f"{sql_base('parts', CLASSIC)}, n AS (SELECT item, sum(c) AS c FROM t GROUP BY item), total AS (SELECT CAST(0.001 AS DOUBLE) * sum(c) AS room FROM n) SELECT CAST(ceil(ln(1 / 0.01)) AS INTEGER) AS r, CAST(ceil(exp(1) / 0.001) AS INTEGER) AS k, count(*) AS items, count(*) FILTER (WHERE s[1] - c > room) AS beyond FROM p JOIN n USING (item), total")
def ci_classic_guarantee(spark, d):
    """The grid of the classical size over all parts, and how many of their minima are off by more than the share of the total that it allows."""
    s = Setting(spark, d, spec=CLASSIC)
    room = 0.001 * float(s.truth.agg(F.sum("c")).first()[0] or 0)
    off = F.array_min("v") - F.col("c")
    beyond = F.count(F.when(off > F.lit(room), 1)).alias("beyond")
    return grid.probe(s.truth, s.grid).agg(F.lit(CLASSIC.r).alias("r"), F.lit(CLASSIC.k).alias("k"), F.count("*").alias("items"), beyond)


@add("size_classic", f"SELECT CAST(ceil(ln(1 / 0.01)) AS INTEGER) AS r, CAST(ceil(exp(1) / (CAST(1000 AS DOUBLE) / sum(c))) AS BIGINT) AS k FROM ({TUPLES_SQL['quantities']})")
def size_classic(spark, d):
    """The classical size at which summed quantities of parts are at most 1,000 off with a chance of 0.99."""
    total = tables.part_quantities(spark, d).agg(F.sum("c")).first()[0] or 1
    return spark.createDataFrame([estimates.size_classic(1000 / total, 0.01)], "r int, k long")


@add("ci_coverage_nominal", f"{sql_base()}, {sql_law(STATS['median'][1])} SELECT round(sum(m) / 250.0, 9) AS coverage FROM l WHERE v BETWEEN {sql_rank((1 - LEVEL) / 2, 250, 'lc')} AND {sql_rank((1 + LEVEL) / 2, 250, 'lc')}")
def ci_coverage_nominal(spark, d):
    g = estimates.statistic_law(Setting(spark, d).grid, t_median)
    return spark.createDataFrame([(round(estimates.nominal_coverage(g, LEVEL), 9),)], "coverage double")


@add("ci_width_ratio", f"{sql_base()}, {SQL_HIST} SELECT round((SELECT sum(c) FROM t) * pow(0.1, -0.25) / 250 / greatest(1, {sql_rank(beta_quantile(0.9, 1, 4))}), 6) AS ratio")
def ci_width_ratio(spark, d):
    f = estimates.grid_law(Setting(spark, d).grid)
    ratio = estimates.markov_width(float(f.x @ f.m / 4), 4, 250, LEVEL) / max(1.0, f.quantile(beta_quantile(LEVEL, 1, 4)))
    return spark.createDataFrame([(round(ratio, 6),)], "ratio double")


_MEDIAN = STATS["median"][1]
_LOW, _HIGH = (sql_rank(q, SPEC.k, "lc") for q in ((1 - LEVEL) / 2, (1 + LEVEL) / 2))


@add("ci_shrunk", f"{sql_base()}, {sql_law(_MEDIAN)} SELECT item, round(greatest(0, {_MEDIAN} - mu), 6) AS est, round(greatest(0, {_MEDIAN} - {_HIGH} + 0.5), 6) AS lo, round({_MEDIAN} - {_LOW} - 0.5, 6) AS hi FROM p, mu")
def ci_shrunk(spark, d):
    s = Setting(spark, d)
    e = estimates.debiased(s.probed, t_median, estimates.statistic_law(s.grid, t_median), LEVEL, shrink=0.5)
    return e.select("item", *[r6(c).alias(c) for c in ("est", "lo", "hi")])


def _auto_sql() -> str:
    one = lambda n: f"SELECT '{n}' AS method, (SELECT min(v) FROM c_{n} WHERE cum >= ceil(CAST({(1 + LEVEL) / 2!r} AS DOUBLE) * {SPEC.k} - 1e-9)) - (SELECT min(v) FROM c_{n} WHERE cum >= ceil(CAST({(1 - LEVEL) / 2!r} AS DOUBLE) * {SPEC.k} - 1e-9)) AS width"
    names = ("min", "mean", "median", "trimmed")
    laws = ", ".join(f"c_{n} AS (SELECT v, sum(count(*)) OVER (ORDER BY v) AS cum FROM (SELECT {STATS[n][1]} AS v FROM k) GROUP BY v)" for n in names)
    return f"{sql_base()}, {sql_columns()}, {laws}, w AS ({' UNION ALL '.join(map(one, names))}) SELECT method, round(width, 6) AS width, method = (SELECT method FROM w ORDER BY width, method LIMIT 1) AS chosen FROM w"


@add("auto_simple", _auto_sql())
def auto_simple(spark, d):
    best, widths = estimates.narrowest(Setting(spark, d).grid, {n: STATS[n][0] for n in ("min", "mean", "median", "trimmed")}, LEVEL)
    return spark.createDataFrame([(n, round(float(w), 6), n == best) for n, w in sorted(widths.items())], "method string, width double, chosen boolean")


# --- Likelihood ------------------------------------------------------------------------------------------------------------------------------


@add("density_fit")
def density_fit(spark, d):
    spline = likelihood.density(estimates.grid_law(Setting(spark, d).grid))
    return spark.createDataFrame([(float(a), float(b)) for a, b in zip(spline.t, spline.phi, strict=True)], "t double, phi double")


@add("density_trim")
def density_trim(spark, d):
    f = estimates.grid_law(Setting(spark, d).grid)
    rows = [(trim, float(a), float(b)) for trim in (0.001, 0.01, 0.05) for s in (likelihood.density(f, trim),) for a, b in zip(s.t, s.phi, strict=True)]
    return spark.createDataFrame(rows, "trim double, t double, phi double")


SQL_MLE = f"z AS (SELECT item, s, least(vv - kk, s[1]) * 1.0 AS th FROM (SELECT item, s, unnest(s) AS vv FROM p) CROSS JOIN (VALUES (0), (100), (200), (400)) n(kk)), c AS (SELECT DISTINCT item, s, th FROM (SELECT * FROM z UNION ALL SELECT item, s, s[1] * 1.0 FROM p)), e AS (SELECT item, th, sum({PINNED_SQL}) AS o FROM (SELECT item, th, unnest(s) - th AS x FROM c) GROUP BY item, th), b AS (SELECT item, th, o, max(o) OVER (PARTITION BY item) AS top FROM e), ml AS (SELECT item, (min(th) + max(th)) / 2 AS raw FROM b WHERE o >= top - 1e-9 * greatest(1, abs(top)) GROUP BY item)"


@add("mle", f"{sql_base()}, {SQL_MLE} SELECT item, round(greatest(0, raw), 6) AS est FROM ml")
def mle(spark, d):
    return likelihood.max_likelihood(Setting(spark, d).probed, PINNED).select("item", r6("est").alias("est"))


@add("mle_decreasing", f"{sql_base()} SELECT item, s[1] * 1.0 AS est FROM p")
def mle_decreasing(spark, d):
    return likelihood.max_likelihood(Setting(spark, d).probed, LogSpline(np.asarray([0.0, 20.0, 60.0]), np.asarray([-1.0, -2.0, -6.0])))


@add("mle_fitted")
def mle_fitted(spark, d):
    s = Setting(spark, d)
    return likelihood.max_likelihood(s.probed, likelihood.density(estimates.grid_law(s.grid)))


def _mle_sql(name: str, of: str, key: str) -> str:
    """(key, raw): likelihood estimates under the pinned density, not cut at 0, for rows (key, s)."""
    return f"z{name} AS (SELECT {key}, s, least(vv - kk, s[1]) * 1.0 AS th FROM (SELECT {key}, s, unnest(s) AS vv FROM {of}) CROSS JOIN (VALUES (0), (100), (200), (400)) n(kk)), d{name} AS (SELECT DISTINCT {key}, s, th FROM (SELECT * FROM z{name} UNION ALL SELECT {key}, s, s[1] * 1.0 FROM {of})), e{name} AS (SELECT {key}, th, sum({PINNED_SQL}) AS o FROM (SELECT {key}, th, unnest(s) - th AS x FROM d{name}) GROUP BY {key}, th), b{name} AS (SELECT {key}, th, o, max(o) OVER (PARTITION BY {key}) AS top FROM e{name}), {name} AS (SELECT {key}, (min(th) + max(th)) / 2 AS raw FROM b{name} WHERE o >= top - 1e-9 * greatest(1, abs(top)) GROUP BY {key})"


SQL_MLE_LAW = f"{sql_base()}, {sql_columns()}, {_mle_sql('ml', 'p', 'item')}, {_mle_sql('mk', 'k', 'idx')}, lc AS (SELECT raw AS v, sum(count(*)) OVER (ORDER BY raw) AS cum FROM mk GROUP BY raw)"


@add("mle_debiased", f"{SQL_MLE_LAW} SELECT item, round(greatest(0, raw - (SELECT avg(raw) FROM mk)), 5) AS est FROM ml")
def mle_debiased(spark, d):
    s = Setting(spark, d)
    return likelihood.debiased_mle(s.probed, s.grid, PINNED, LEVEL).select("item", F.round("est", 5).alias("est"))


@add("mle_ci", f"{SQL_MLE_LAW} SELECT item, round(greatest(0, raw - {_HIGH}), 6) AS lo, round(raw - {_LOW}, 6) AS hi FROM ml")
def mle_ci(spark, d):
    s = Setting(spark, d)
    return likelihood.debiased_mle(s.probed, s.grid, PINNED, LEVEL).select("item", r6("lo").alias("lo"), r6("hi").alias("hi"))


@add("mle_debiased_fitted")
def mle_debiased_fitted(spark, d):
    """The whole method: density from the grid, estimates and intervals debiased by the law over its columns."""
    s = Setting(spark, d)
    return likelihood.debiased_mle(s.probed, s.grid, likelihood.density(estimates.grid_law(s.grid)), LEVEL)


SQL_EVALS = f"{sql_base()}, {SQL_MLE}, n AS (SELECT item, count(*) AS evaluations FROM e GROUP BY item), g2 AS (SELECT item, count(*) > 1 AS tied FROM b WHERE o >= top - 1e-9 * greatest(1, abs(top)) GROUP BY item)"


@add("mle_gradient", f"{SQL_EVALS} SELECT item, evaluations, tied FROM n JOIN g2 USING (item)")
def mle_gradient(spark, d):
    """What the kernel did for each item: counts at which it evaluated the objective, and whether several were best."""
    return likelihood.kernel_counts(Setting(spark, d).probed, PINNED)


@add("evals_per_count", f"{SQL_EVALS} SELECT count(*) AS items, round(avg(evaluations), 6) AS evaluations FROM n")
def evals_per_count(spark, d):
    return likelihood.kernel_counts(Setting(spark, d).probed, PINNED).agg(F.count("*").alias("items"), F.round(F.avg("evaluations"), 6).alias("evaluations"))


SQL_POST = f"n AS (SELECT item, s, unnest(range(0, s[1] + 1)) AS n FROM p), w AS (SELECT item, n, sum({PINNED_SQL}) AS o FROM (SELECT item, n, unnest(s) - n AS x FROM n) GROUP BY item, n), x AS (SELECT item, n, exp(o - max(o) OVER (PARTITION BY item)) AS q FROM w), po AS (SELECT item, n, q / sum(q) OVER (PARTITION BY item) AS q FROM x)"


@add("bayes_mean", f"{sql_base()}, {SQL_POST} SELECT item, round(sum(n * q), 5) AS est FROM po GROUP BY item")
def bayes_mean(spark, d):
    return likelihood.bayes_estimates(Setting(spark, d).probed, PINNED).select("item", F.round("est", 5).alias("est"))


SQL_CUM = f"{SQL_POST}, cu AS (SELECT item, n, q, sum(q) OVER (PARTITION BY item ORDER BY n) AS f FROM po)"
SQL_CREDIBLE = f"ci AS (SELECT item, min(n) FILTER (WHERE f >= {(1 - LEVEL) / 2!r}) AS lo, coalesce(min(n) FILTER (WHERE f >= {(1 + LEVEL) / 2!r}), max(n)) AS hi, min(n) FILTER (WHERE f >= 0.5 - 1e-12) AS middle FROM cu GROUP BY item)"
_BEST = {
    "bayes_median": ("l1", f"{SQL_CUM}, {SQL_CREDIBLE}", "SELECT item, middle * 1.0 AS est, lo * 1.0 AS lo, hi * 1.0 AS hi FROM ci"),
    "bayes_map": ("01", f"{SQL_CUM}, {SQL_CREDIBLE}, mo AS (SELECT item, min(n) AS m FROM (SELECT item, n, q, max(q) OVER (PARTITION BY item) AS top FROM po) WHERE q >= top * (1 - 1e-9) GROUP BY item)", "SELECT item, m * 1.0 AS est, lo * 1.0 AS lo, hi * 1.0 AS hi FROM ci JOIN mo USING (item)"),
    "bayes_bounded": ("capped", f"{SQL_CUM}, {SQL_CREDIBLE}, co AS (SELECT a.item, a.n, sum(least(abs(a.n - b.n), 10) * b.q) AS cost FROM po a JOIN po b ON a.item = b.item GROUP BY a.item, a.n), be AS (SELECT item, min(n) AS m FROM (SELECT item, n, cost, min(cost) OVER (PARTITION BY item) AS least FROM co) WHERE cost <= least + 1e-12 GROUP BY item)", "SELECT item, m * 1.0 AS est, lo * 1.0 AS lo, hi * 1.0 AS hi FROM ci JOIN be USING (item)"),
}
for _name, (_loss, _with, _select) in _BEST.items():
    add(_name, f"{sql_base()}, {_with} {_select}")(lambda spark, d, loss=_loss: likelihood.bayes_estimates(Setting(spark, d).probed, PINNED, loss))
add("bayes_credible", ORACLE_SQL["bayes_median"])(QUERIES["bayes_median"])
SQL_ZIPF = SQL_POST.replace(f"sum({PINNED_SQL}) AS o", f"sum({PINNED_SQL}) - 2 * ln(n + 1) AS o")
add("bayes_prior_zipf", f"{sql_base()}, {SQL_ZIPF} SELECT item, round(sum(n * q), 5) AS est FROM po GROUP BY item")(lambda spark, d: likelihood.bayes_estimates(Setting(spark, d).probed, PINNED, power=2.0).select("item", F.round("est", 5).alias("est")))
add("est_location")(lambda spark, d: likelihood.location_estimates(Setting(spark, d).probed))


# --- Joint estimates -------------------------------------------------------------------------------------------------------------------------


def _system(spark: SparkSession, d: str, most: int = 200):
    s = Setting(spark, d)
    items = variants.top_items(s.tuples, most).select("item")
    return s, *joint.system(items, s.grid)


@add("joint_ls")
def joint_ls(spark, d):
    _, items, cells, values = _system(spark, d)
    return spark.createDataFrame([(i, float(x)) for i, x in zip(items, joint.least_squares(cells, values), strict=True)], "item long, est double")


WIDE = GridSpec(4, 4000, "poly4")


@add("joint_ls_exact", f"SELECT item, CAST(sum(c) AS DOUBLE) AS est FROM ({TUPLES_SQL['users']}) GROUP BY item")
def joint_ls_exact(spark, d):
    """All users known and more cells than users, at every size of the table: counts come out exactly."""
    counts = keep(tables.users(spark, d).groupBy("item").agg(F.sum("c").alias("c")), "counts")
    return joint.least_squares_blocks(counts, WIDE).select("item", F.round("est", 6).alias("est"))


@add("joint_mle")
def joint_mle(spark, d):
    s, items, cells, values = _system(spark, d)
    start = np.maximum(0, values[cells].min(axis=1) - estimates.grid_law(s.grid).order_mean(1, SPEC.r))
    theta, _ = joint.joint_mle(cells, values, start)
    return spark.createDataFrame([(i, float(x)) for i, x in zip(items, theta, strict=True)], "item long, est double")


BOUNDS_SPEC = GridSpec(3, 128, "poly4")


def _bounds_sql(rounds: int) -> str:
    inc = " UNION ALL ".join(f"SELECT item, {a} AS rep, {cell_sql('item', a, BOUNDS_SPEC)} AS idx FROM items" for a in range(3))
    sql = f"WITH t AS ({TUPLES_SQL['users']}), items AS (SELECT DISTINCT item FROM t), {sql_grid('g', 't', BOUNDS_SPEC)}, inc AS (SELECT i.*, g.v FROM ({inc}) i JOIN g ON g.rep = i.rep AND g.idx = i.idx), b0 AS (SELECT item, CAST(0 AS BIGINT) AS lo, min(v) AS up FROM inc GROUP BY item)"
    for k in range(rounds):
        sql += f", u{k} AS (SELECT item, min(v - (s - lo)) AS room FROM (SELECT inc.*, lo, sum(lo) OVER (PARTITION BY rep, idx) AS s FROM inc JOIN b{k} USING (item)) GROUP BY item), m{k} AS (SELECT item, lo, least(up, room) AS up FROM b{k} JOIN u{k} USING (item)), l{k} AS (SELECT item, max(v - (s - up)) AS room FROM (SELECT inc.*, up, sum(up) OVER (PARTITION BY rep, idx) AS s FROM inc JOIN m{k} USING (item)) GROUP BY item), b{k + 1} AS (SELECT item, greatest(lo, room) AS lo, up FROM m{k} JOIN l{k} USING (item))"
    return f"{sql} SELECT item, CAST(lo AS BIGINT) AS lo, CAST(up AS BIGINT) AS up FROM b{rounds}"


@add("bound_propagation", _bounds_sql(2))
def bound_propagation(spark, d):
    s = Setting(spark, d, tables.users, BOUNDS_SPEC)
    return joint.propagate_bounds(s.items, s.grid, 2)


# --- Earlier estimators and other grids ----------------------------------------------------------------------------------------------------


@add("base_zero_probe", f"{sql_base()}, absent AS (SELECT 1000000 + i AS item FROM range(50) x(i)), {sql_probe('z', 'absent')} SELECT item, round(greatest(0, s[1] - (SELECT avg(s[1]) FROM z)), 6) AS est FROM p")
def base_zero_probe(spark, d):
    s = Setting(spark, d)
    absent = grid.probe(spark.range(1_000_000, 1_000_050).withColumnRenamed("id", "item"), s.grid)
    return variants.zero_probe_min(s.probed, absent).select("item", r6("est").alias("est"))


@add("base_noise_median", f"{sql_base()}, {SQL_HIST} SELECT item, round(greatest(0, (s[2] + s[3]) / 2.0 - {sql_rank(0.5)}), 6) AS est FROM p")
def base_noise_median(spark, d):
    s = Setting(spark, d)
    return variants.noise_debiased(s.probed, t_median, estimates.grid_law(s.grid).quantile(0.5)).select("item", r6("est").alias("est"))


@add("base_noise_mean", f"{sql_base()}, {SQL_HIST} SELECT item, round(greatest(0, list_sum(s) / 4.0 - (SELECT sum(v * m) / {SPEC.cells}.0 FROM h)), 6) AS est FROM p")
def base_noise_mean(spark, d):
    s = Setting(spark, d)
    return variants.noise_debiased(s.probed, t_mean, estimates.grid_law(s.grid).mean()).select("item", r6("est").alias("est"))


@add("base_collision_debias", f"{sql_base()}, {SQL_INC}, w AS (SELECT rep, idx, count(*) AS w FROM inc GROUP BY rep, idx), beta AS (SELECT (SELECT sum(c) FROM t) * 1.0 / (SELECT count(*) FROM items) AS b), c AS (SELECT inc.item, g.v - b * (w - 1) AS x FROM inc JOIN g ON g.rep = inc.rep AND g.idx = inc.idx JOIN w ON w.rep = inc.rep AND w.idx = inc.idx, beta) SELECT item, round(median(x), 5) AS est FROM c GROUP BY item")
def base_collision_debias(spark, d):
    s = Setting(spark, d)
    return variants.collision_debiased(s.items, s.items, s.grid).select("item", F.round("est", 5).alias("est"))


def _signed_sql() -> str:
    each = " UNION ALL ".join(f"SELECT CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, SPEC)} AS idx, {sign_sql('item', a, SPEC)} * c AS c FROM t" for a in range(4))
    return f"WITH t AS ({TUPLES_SQL['parts']}), items AS (SELECT DISTINCT item FROM t), g AS (SELECT rep, idx, CAST(sum(c) AS BIGINT) AS v FROM ({each}) GROUP BY rep, idx)"


def _signed_probe_sql() -> str:
    joins = " ".join(f"LEFT JOIN g g{a} ON g{a}.rep = {a} AND g{a}.idx = {cell_sql('i.item', a, SPEC)}" for a in range(4))
    vals = ", ".join(f"coalesce(g{a}.v, 0) * {sign_sql('i.item', a, SPEC)}" for a in range(4))
    return f"{_signed_sql()}, p AS (SELECT i.item, list_sort([{vals}]) AS s FROM items i {joins})"


@add("signed_build", f"{_signed_sql()} SELECT rep, idx, v FROM g")
def signed_build(spark, d):
    return variants.build_signed(tables.parts(spark, d), SPEC).df


def _signed(spark: SparkSession, d: str, statistic) -> DataFrame:
    t = tables.parts(spark, d)
    return estimates.classical(variants.probe_signed(t.select("item").distinct(), variants.build_signed(t, SPEC)), statistic).select("item", r6("est").alias("est"))


add("signed_median", f"{_signed_probe_sql()} SELECT item, round((s[2] + s[3]) / 2.0, 6) AS est FROM p")(lambda spark, d: _signed(spark, d, t_median))
add("signed_mean", f"{_signed_probe_sql()} SELECT item, round(list_sum(s) / 4.0, 6) AS est FROM p")(lambda spark, d: _signed(spark, d, t_mean))

SMALL = GridSpec(3, 40, "poly4")


def _conservative_sql() -> str:
    sql = "WITH t AS (SELECT CAST(user_id AS BIGINT) AS item, event_id % 3 AS batch FROM events)"
    for b in range(3):
        sql += f", o{b} AS (SELECT item, count(*) AS c FROM t WHERE batch = {b} GROUP BY item)"
        if b:
            joins = " ".join(f"LEFT JOIN g{b - 1} x{a} ON x{a}.rep = {a} AND x{a}.idx = {cell_sql('o.item', a, SMALL)}" for a in range(3))
            sql += f", n{b} AS (SELECT o.item, c + least({', '.join(f'coalesce(x{a}.v, 0)' for a in range(3))}) AS v FROM o{b} o {joins})"
        else:
            sql += ", n0 AS (SELECT item, c AS v FROM o0)"
        each = " UNION ALL ".join(f"SELECT CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, SMALL)} AS idx, v FROM n{b}" for a in range(3)) + (f" UNION ALL SELECT rep, idx, v FROM g{b - 1}" if b else "")
        sql += f", g{b} AS (SELECT rep, idx, max(v) AS v FROM ({each}) GROUP BY rep, idx)"
    return f"{sql} SELECT rep, idx, v FROM g2"


@add("conservative_batch", _conservative_sql())
def conservative_batch(spark, d):
    t = tables.table(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), (F.col("event_id") % 3).alias("batch"))
    return variants.conservative_batches(t, SMALL, 3).df


@add("conservative_seq")
def conservative_seq(spark, d):
    t = tables.table(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), F.col("event_id").alias("seq"))
    return variants.conservative_serial(t, SMALL).df


@add("decayed_build", f"WITH t AS (SELECT CAST(o_custkey AS BIGINT) AS item, CAST(round(1000000 * pow(2.0, -date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') / 365.0)) AS BIGINT) AS c FROM orders), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def decayed_build(spark, d):
    o = tables.table(spark, d, "orders").select(F.col("o_custkey").alias("item"), F.lit(1).cast("long").alias("c"), F.datediff(F.lit("2000-01-01").cast("date"), F.col("o_orderdate").cast("date")).alias("age"))
    return variants.build_decayed(o, SPEC, F.col("age"), 365.0).df


@add("distinct_cells", "WITH t AS (SELECT DISTINCT CAST(l_partkey AS BIGINT) AS item, l_suppkey, CAST(1 AS BIGINT) AS c FROM lineitem), " + sql_grid("g", "t") + " SELECT rep, idx, v FROM g")
def distinct_cells(spark, d):
    return variants.build_distinct(tables.flows(spark, d), SPEC).df


@add("distinct_est", f"WITH t AS (SELECT DISTINCT CAST(l_partkey AS BIGINT) AS item, l_suppkey, CAST(1 AS BIGINT) AS c FROM lineitem), items AS (SELECT DISTINCT item FROM t), {sql_grid('g', 't')}, {sql_probe('p', 'items')}, {SQL_HIST} SELECT item, round(greatest(0, s[1] - {SQL_EXACT_MIN}), 6) AS est FROM p")
def distinct_est(spark, d):
    f = tables.flows(spark, d)
    g = variants.build_distinct(f, SPEC)
    return estimates.debiased_min(grid.probe(f.select("item").distinct(), g), estimates.grid_law(g), SPEC.r, mode="exact").select("item", r6("est").alias("est"))


# --- Inner products --------------------------------------------------------------------------------------------------------------------------


def _flag(flag: str) -> str:
    return f"SELECT CAST(l_partkey AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM lineitem WHERE l_returnflag = '{flag}'"


SQL_IP = f"WITH t AS ({_flag('R')}), u AS ({_flag('A')}), {sql_grid('g', 't')}, {sql_grid('w', 'u')}, ip AS (SELECT g.rep, CAST(sum(g.v * w.v) AS BIGINT) AS product FROM g JOIN w ON g.rep = w.rep AND g.idx = w.idx GROUP BY g.rep), tot AS (SELECT (SELECT count(*) FROM t) * 1.0 * (SELECT count(*) FROM u) AS st)"


def _pair(spark: SparkSession, d: str):
    rows = tables.table(spark, d, "lineitem")
    return [grid.build_grid(grid.tuples(rows.where(F.col("l_returnflag") == f), F.col("l_partkey")), SPEC) for f in ("R", "A")]


@add("ip_exact", f"SELECT CAST(sum(a.c * b.c) AS BIGINT) AS product FROM (SELECT item, sum(c) AS c FROM ({_flag('R')}) GROUP BY item) a JOIN (SELECT item, sum(c) AS c FROM ({_flag('A')}) GROUP BY item) b USING (item)")
def ip_exact(spark, d):
    rows = tables.table(spark, d, "lineitem")
    a, b = (grid.tuples(rows.where(F.col("l_returnflag") == f), F.col("l_partkey")).groupBy("item").agg(F.sum("c").alias(n)) for f, n in (("R", "a"), ("A", "b")))
    return a.join(b, "item").agg(F.sum(F.col("a") * F.col("b")).alias("product"))


@add("ip_min", f"{SQL_IP} SELECT min(product) AS product FROM ip")
def ip_min(spark, d):
    return variants.inner_products(*_pair(spark, d)).agg(F.min("product").alias("product"))


@add("ip_unbiased", f"{SQL_IP} SELECT rep, round(250 / 249.0 * (product - st / 250), 3) AS product FROM ip, tot")
def ip_unbiased(spark, d):
    return variants.inner_products(*_pair(spark, d)).select("rep", F.round("unbiased", 3).alias("product"))


@add("ip_self", f"WITH t AS ({_flag('R')}), {sql_grid('g', 't')} SELECT rep, CAST(sum(v * v) AS BIGINT) AS product FROM g GROUP BY rep")
def ip_self(spark, d):
    u, _ = _pair(spark, d)
    return variants.inner_products(u, u).select("rep", "product")


@add("ip_surrogate", f"{SQL_IP} SELECT g.rep, CAST(s AS INTEGER) AS shift, CAST(sum(g.v * w.v) AS BIGINT) AS product FROM range(1, 21) x(s), g JOIN w ON g.rep = w.rep WHERE w.idx = (g.idx + s) % 250 GROUP BY g.rep, s")
def ip_surrogate(spark, d):
    return variants.surrogate_products(*_pair(spark, d), 20)


# --- Tuning ------------------------------------------------------------------------------------------------------------------------------------


@add("downsample_coord", f"SELECT item, c FROM ({TUPLES_SQL['parts']}) WHERE CAST(concat('0x', substr(md5(concat('5:', CAST(item AS VARCHAR))), 1, 13)) AS BIGINT) < {int(0.2 * (1 << 52))}")
def downsample_coord(spark, d):
    return variants.coordinated_sample(tables.parts(spark, d), 0.2)


@add("downsample_bottomk", f"WITH t AS ({TUPLES_SQL['parts']}) SELECT item, c FROM t WHERE item IN (SELECT item FROM (SELECT DISTINCT item FROM t) ORDER BY substr(md5(concat('5:', CAST(item AS VARCHAR))), 1, 13), item LIMIT 50)")
def downsample_bottomk(spark, d):
    return variants.bottom_k_sample(tables.parts(spark, d), 50)


TUNE_SPEC = GridSpec(1, 2000, "poly4")


@add("tune_curve")
def tune_curve(spark, d):
    f = estimates.grid_law(grid.build_grid(tables.parts(spark, d), TUNE_SPEC))
    base = tuning.mass(f, 16 * (int(f.x.max()) + 1))
    return spark.createDataFrame(tuning.depth_widths(base, list(range(1, 17)), [0.5, 0.9, 0.95]), "depth int, level double, width double")


@add("tune_depth")
def tune_depth(spark, d):
    f = estimates.grid_law(grid.build_grid(tables.parts(spark, d), TUNE_SPEC))
    depth, width = tuning.best_depth(tuning.mass(f, 16 * (int(f.x.max()) + 1)), 16, 0.95)
    return spark.createDataFrame([(depth, TUNE_SPEC.k // depth, width)], "depth int, k int, width double")


# --- Measures and workloads ------------------------------------------------------------------------------------------------------------------


def _measured(spark: SparkSession, d: str) -> DataFrame:
    s = Setting(spark, d)
    truth = s.truth.withColumnRenamed("c", "truth")
    f = estimates.grid_law(s.grid)
    a = estimates.debiased_min(s.probed, f, SPEC.r, 0.95, "exact").withColumn("method", F.lit("debiased_min"))
    b = estimates.classical(s.probed).select("item", "est", F.lit(0.0).alias("lo"), F.col("est").alias("hi")).withColumn("method", F.lit("min"))
    return a.unionByName(b).join(truth, "item")


SQL_MEASURED = f"{sql_base()}, {SQL_HIST}, truth AS (SELECT item, sum(c) AS truth FROM t GROUP BY item), e AS (SELECT item, 'debiased_min' AS method, greatest(0, s[1] - {SQL_EXACT_MIN}) AS est, greatest(0, s[1] - {sql_rank(beta_quantile(0.95, 1, 4))}) AS lo, s[1] AS hi FROM p UNION ALL SELECT item, 'min', s[1], 0, s[1] FROM p), x AS (SELECT * FROM e JOIN truth USING (item)), a AS (SELECT method, count(*) AS n, avg((est - truth) ** 2) AS mse, avg(est - truth) AS bias FROM x GROUP BY method)"


@add("rmse", f"{SQL_MEASURED} SELECT method, n, round(mse, 4) AS mse, round(sqrt(mse), 4) AS rmse, round(bias, 4) AS bias FROM a")
def rmse(spark, d):
    m = metrics.accuracy(_measured(spark, d))
    return m.select("method", "n", *[F.round(c, 4).alias(c) for c in ("mse", "rmse", "bias")])


@add("rel_efficiency", f"{SQL_MEASURED} SELECT method, round(mse / (SELECT mse FROM a WHERE method = 'debiased_min'), 4) AS rel_eff FROM a")
def rel_efficiency(spark, d):
    return metrics.relative_efficiency(_measured(spark, d), "debiased_min").select("method", F.round("rel_eff", 4).alias("rel_eff"))


@add("coverage", f"{SQL_MEASURED} SELECT method, round(avg(CASE WHEN lo <= truth AND truth <= hi THEN 1.0 ELSE 0.0 END), 6) AS coverage, round(avg(hi - lo), 4) AS width FROM x GROUP BY method")
def coverage(spark, d):
    return metrics.coverage(_measured(spark, d)).select("method", r6("coverage").alias("coverage"), F.round("width", 4).alias("width"))


@add("mass_share", "SELECT round(sum(CASE WHEN place <= 100 THEN n ELSE 0 END) * 1.0 / sum(n), 9) AS share FROM (SELECT n, row_number() OVER (ORDER BY n DESC, item) AS place FROM (SELECT l_partkey AS item, count(*) AS n FROM lineitem GROUP BY 1))")
def mass_share(spark, d):
    t = tables.parts(spark, d)
    return variants.top_items(t, 100).agg(F.sum("c").alias("s")).crossJoin(t.agg(F.sum("c").alias("n"))).select(F.round(F.col("s") / F.col("n"), 9).alias("share"))


# --- Streams -----------------------------------------------------------------------------------------------------------------------------------


@add("stream_grid", f"WITH t AS ({TUPLES_SQL['users']}), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def stream_grid(spark, d):
    stream = tables.stream(spark, d, "events")
    return streams.drained(streams.stream_grid(grid.tuples(stream, F.col("user_id")), SPEC), shared_folder(spark))
