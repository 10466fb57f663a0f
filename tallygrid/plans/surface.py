"""The methods in SQL: views of a grid, functions over own counters, and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.density import LogSpline, bayes, mle, posterior
from ..functions.hashing import GridSpec, coefficients
from ..functions.statistics import beta_quantile
from ..operators import errors, estimates, grid, tuning
from ..operators.grid import CounterGrid
from ..sources import tables
from .base import PINNED, SPEC, SQL_HIST, TUPLES_SQL, Setting, add, sql_base, sql_grid, sql_probe
from .methods import SQL_MLE, SQL_POST, TUNE_SPEC

#: A counter's value in Python, for the portable integer family.
PRIME = (1 << 31) - 1


def python_cell(item: int, rep: int, spec: GridSpec) -> int:
    out = 0
    for c in coefficients(spec, rep):
        out = (out * item + c) % PRIME
    return out % spec.k


def register(spark: SparkSession, kept: CounterGrid | None = None, items: DataFrame | None = None, spline: LogSpline | None = None, curve: list[tuple[int, float, float]] | None = None) -> None:
    """Functions and views for SQL text.

    Always: tg_min(v), tg_order(v, i), tg_median(v), tg_trimmed(v, n) over arrays of own counters, tg_ks(v, w), the largest gap between the distributions of two columns of a
    group, and the table function dyadic_cover(low, high). With a grid: views grid and error_law, and the table function grid_cells(item, c) of its spec
    (poly4); with items too, the view grid_probe. With a density: tg_mle(v) and tg_bayes(v). With rows (depth, level, width): the table function depth_curve(level).
    """
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tg_min(v ARRAY<BIGINT>) RETURNS BIGINT RETURN array_min(v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tg_order(v ARRAY<BIGINT>, i INT) RETURNS BIGINT RETURN element_at(sort_array(v), i)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tg_median(v ARRAY<BIGINT>) RETURNS DOUBLE RETURN (element_at(sort_array(v), CAST(floor((size(v) + 1) / 2) AS INT)) + element_at(sort_array(v), CAST(floor(size(v) / 2) AS INT) + 1)) / 2")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tg_trimmed(v ARRAY<BIGINT>, n INT) RETURNS DOUBLE RETURN aggregate(slice(sort_array(v), n + 1, size(v) - 2 * n), CAST(0 AS DOUBLE), (a, x) -> a + x) / (size(v) - 2 * n)")

    def tg_ks(v: pd.Series, w: pd.Series) -> float:
        a, b = np.sort(v.dropna().to_numpy()), np.sort(w.dropna().to_numpy())
        at = np.union1d(a, b)
        below = lambda x: np.searchsorted(x, at, side="right") / max(1, len(x))
        return float(np.abs(below(a) - below(b)).max()) if len(at) else 0.0

    spark.udf.register("tg_ks", F.pandas_udf(tg_ks, "double"))

    class DyadicCover:
        def eval(self, low: int, high: int):
            for item in grid.dyadic_cover(low, high, 6):
                yield (item,)

    spark.udtf.register("dyadic_cover", F.udtf(DyadicCover, returnType="item: bigint"))
    if spline is not None:
        rows = lambda v: np.stack(v.to_numpy()).astype(np.float64)

        def tg_mle(v: pd.Series) -> pd.Series:
            return pd.Series(np.maximum(0, mle(rows(v), spline)))

        def tg_bayes(v: pd.Series) -> pd.Series:
            return pd.Series([bayes(*posterior(x, spline)) for x in rows(v)])

        spark.udf.register("tg_mle", F.pandas_udf(tg_mle, "double"))
        spark.udf.register("tg_bayes", F.pandas_udf(tg_bayes, "double"))
    if curve is not None:

        class DepthCurve:
            def eval(self, level: float):
                for depth, own, width in curve:
                    if abs(own - level) < 1e-9:
                        yield depth, width

        spark.udtf.register("depth_curve", F.udtf(DepthCurve, returnType="depth: int, width: double"))
    if kept is None:
        return
    kept.df.createOrReplaceTempView("grid")
    errors.error_hist(kept).createOrReplaceTempView("error_law")
    if kept.spec.family == "poly4":
        spec = kept.spec

        class GridCells:
            def eval(self, item: int, c: int):
                for rep in range(spec.r):
                    yield rep, python_cell(item, rep, spec), c

        spark.udtf.register("grid_cells", F.udtf(GridCells, returnType="rep: int, idx: bigint, c: bigint"))
    if items is not None:
        grid.probe(items, kept).createOrReplaceTempView("grid_probe")


def _surface(spark: SparkSession, d: str, **more) -> Setting:
    s = Setting(spark, d)
    register(spark, s.grid, s.items, PINNED, **more)
    return s


def sql_query(name: str, text: str, oracle: str) -> None:
    """A query that is SQL text over the registered views and functions."""

    def run(spark, d):
        _surface(spark, d)
        return spark.sql(text)

    add(name, oracle)(run)


BASE = sql_base()
sql_query("tg_min", "SELECT item, tg_min(v) AS est FROM grid_probe", f"{BASE} SELECT item, s[1] AS est FROM p")
sql_query("tg_median", "SELECT item, tg_median(v) AS est FROM grid_probe", f"{BASE} SELECT item, (s[2] + s[3]) / 2.0 AS est FROM p")
sql_query("tg_order", "SELECT item, tg_order(v, 3) AS est FROM grid_probe", f"{BASE} SELECT item, s[3] AS est FROM p")
sql_query("tg_trimmed", "SELECT item, tg_trimmed(v, 1) AS est FROM grid_probe", f"{BASE} SELECT item, (s[2] + s[3]) / 2.0 AS est FROM p")
sql_query("tg_mle", "SELECT item, round(tg_mle(v), 6) AS est FROM grid_probe", f"{BASE}, {SQL_MLE} SELECT item, round(greatest(0, raw), 6) AS est FROM ml")
sql_query("tg_bayes", "SELECT item, round(tg_bayes(v), 5) AS est FROM grid_probe", f"{BASE}, {SQL_POST} SELECT item, round(sum(n * q), 5) AS est FROM po GROUP BY item")
sql_query("grid", "SELECT rep, count(*) AS cells, sum(v) AS total, max(v) AS top FROM grid GROUP BY rep", f"{BASE} SELECT rep, count(*) AS cells, CAST(sum(v) AS BIGINT) AS total, max(v) AS top FROM g GROUP BY rep")
sql_query("grid_probe", "SELECT item, element_at(v, 1) AS v0, element_at(v, 4) AS v3 FROM grid_probe WHERE item IN (SELECT l_partkey FROM (SELECT 5 AS l_partkey UNION ALL SELECT 17))", f"{BASE} SELECT item, v0, v3 FROM p WHERE item IN (5, 17)")
sql_query("error_law", "WITH q AS (SELECT min(v) AS low FROM error_law WHERE cum >= 500) SELECT item, greatest(0, tg_min(v) - low) AS est FROM grid_probe CROSS JOIN q WHERE EXISTS (SELECT 1 FROM error_law e WHERE e.v = array_min(grid_probe.v))", f"{BASE}, {SQL_HIST} SELECT item, greatest(0, s[1] - (SELECT min(v) FROM hc WHERE cum >= 500)) AS est FROM p WHERE s[1] IN (SELECT v FROM h)")
sql_query("sql_functions", "SELECT item, tg_min(v) AS low, tg_order(v, 2) AS second, round(tg_median(v), 6) AS median FROM grid_probe", f"{BASE} SELECT item, s[1] AS low, s[2] AS second, round((s[2] + s[3]) / 2.0, 6) AS median FROM p")


@add("register", "SELECT name FROM (VALUES ('depth_curve'), ('dyadic_cover'), ('error_law'), ('grid'), ('grid_cells'), ('grid_probe'), ('tg_bayes'), ('tg_ks'), ('tg_median'), ('tg_min'), ('tg_mle'), ('tg_order'), ('tg_trimmed')) t(name)")
def registered(spark, d):
    """The names that SQL text can use after registering."""
    _surface(spark, d, curve=[(1, 0.9, 1.0)])
    names = [n for n in ("tg_min", "tg_median", "tg_order", "tg_trimmed", "tg_mle", "tg_bayes", "tg_ks", "grid_cells", "dyadic_cover", "depth_curve") if spark.catalog.functionExists(n)]
    return spark.createDataFrame([(n,) for n in names + [v for v in ("grid", "grid_probe", "error_law") if spark.catalog.tableExists(v)]], "name string")


@add("tg_ks", f"WITH t AS ({TUPLES_SQL['parts']}), u AS ({TUPLES_SQL['users']}), {sql_grid('g', 't')}, {sql_grid('w', 'u')}, b AS (SELECT rep, v, count(*) AS a, 0 AS b FROM g GROUP BY rep, v UNION ALL SELECT rep, v, 0, count(*) FROM w GROUP BY rep, v), s AS (SELECT rep, v, sum(a) AS a, sum(b) AS b FROM b GROUP BY rep, v) SELECT rep, round(max(abs(x)), 9) AS ks FROM (SELECT rep, sum(a) OVER (PARTITION BY rep ORDER BY v) / sum(a) OVER (PARTITION BY rep) - sum(b) OVER (PARTITION BY rep ORDER BY v) / sum(b) OVER (PARTITION BY rep) AS x FROM s) GROUP BY rep")
def tg_ks_query(spark, d):
    """Gap between the counters of two grids, replicate by replicate."""
    register(spark)
    a, b = (grid.build_grid(source(spark, d), SPEC).df for source in (tables.parts, tables.users))
    both = a.join(b.withColumnRenamed("v", "w"), ["rep", "idx"], "full_outer")
    return spark.sql("SELECT rep, round(tg_ks(v, w), 9) AS ks FROM {both} GROUP BY rep", both=both)


@add("grid_cells", f"{BASE} SELECT rep, idx, v FROM g")
def grid_cells(spark, d):
    """The grid built in SQL text, by a lateral call of the table function."""
    s = _surface(spark, d)
    return spark.sql("SELECT x.rep, x.idx, sum(x.c) AS v FROM {t} t, LATERAL grid_cells(t.item, t.c) x GROUP BY x.rep, x.idx", t=s.truth)


DYADIC = GridSpec(4, 64, "poly4")


@add("dyadic_cover", "WITH r(low, high) AS (VALUES (1, 10), (5, 37), (17, 17)), b AS (SELECT CAST(l_quantity AS BIGINT) AS q FROM lineitem), t AS (" + " UNION ALL ".join(f"SELECT {l} * 64 + (q >> {l}) AS item, CAST(1 AS BIGINT) AS c FROM b" for l in range(6)) + "), cover(low, high, item) AS (VALUES " + ", ".join(f"({a}, {b}, CAST({x} AS BIGINT))" for a, b in ((1, 10), (5, 37), (17, 17)) for x in grid.dyadic_cover(a, b, 6)) + f"), {sql_grid('g', 't', DYADIC)}, {sql_probe('p', 'cover', 'g', DYADIC)} SELECT CAST(low AS BIGINT) AS low, CAST(high AS BIGINT) AS high, CAST(sum(s[1]) AS BIGINT) AS est FROM p GROUP BY low, high")
def dyadic_cover(spark, d):
    """Ranges asked in SQL text: the table function lists their dyadic items, the probe answers them."""
    t = tables.table(spark, d, "lineitem").select(F.col("l_quantity").cast("long").alias("item"), F.lit(1).cast("long").alias("c"))
    register(spark)
    cover = spark.sql("SELECT r.low, r.high, x.item FROM (VALUES (1L, 10L), (5L, 37L), (17L, 17L)) r(low, high), LATERAL dyadic_cover(r.low, r.high) x")
    return grid.probe(cover, grid.build_grid(grid.dyadic(t, 6), DYADIC)).groupBy("low", "high").agg(F.sum(F.array_min("v")).alias("est"))


_Q1, _Q2 = beta_quantile(0.9, 1, 1), beta_quantile(0.9, 1, 2)


@add("depth_curve", f"WITH t AS ({TUPLES_SQL['parts']}), {sql_grid('g', 't', TUNE_SPEC)}, h AS (SELECT v, CAST(sum(m) AS DOUBLE) / {TUNE_SPEC.cells} AS p FROM (SELECT v, count(*) AS m FROM g GROUP BY v UNION ALL SELECT 0, {TUNE_SPEC.cells} - count(*) FROM g) GROUP BY v), h2 AS (SELECT a.v + b.v AS v, sum(a.p * b.p) AS p FROM h a CROSS JOIN h b GROUP BY 1), c1 AS (SELECT v, sum(p) OVER (ORDER BY v) AS f FROM h), c2 AS (SELECT v, sum(p) OVER (ORDER BY v) AS f FROM h2) SELECT CAST(1 AS INTEGER) AS depth, CAST(min(v) AS DOUBLE) AS width FROM c1 WHERE f >= {_Q1!r} - 1e-9 UNION ALL SELECT 2, CAST(min(v) AS DOUBLE) FROM c2 WHERE f >= {_Q2!r} - 1e-9")
def depth_curve(spark, d):
    f = estimates.grid_law(grid.build_grid(tables.parts(spark, d), TUNE_SPEC))
    register(spark, curve=tuning.depth_widths(tuning.mass(f, 16 * (int(f.x.max()) + 1)), list(range(1, 17)), [0.5, 0.9, 0.95]))
    return spark.sql("SELECT depth, width FROM depth_curve(CAST(0.9 AS DOUBLE)) WHERE depth <= 2")
