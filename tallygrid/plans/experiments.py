"""The experiment workloads on the given tables and by simulation; sizes are parameters, small by default."""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.density import LogSpline, fit_logconcave, mle
from ..functions.hashing import GridSpec, cell_sql, sign_sql
from ..functions.statistics import beta_quantile, t_mean, t_median, t_min
from ..operators import errors, estimates, grid, joint, likelihood, metrics, store, tuning, variants
from ..sources import tables
from ..sources.shared import keep
from . import simulation, workloads
from .base import LEVEL, ORACLE_SQL, PINNED, PINNED_SQL, QUERIES, SPEC, SQL_HIST, STATS, TUPLES_SQL, Setting, add, r6, sql_base, sql_columns, sql_grid, sql_law, sql_probe, sql_rank
from .methods import SQL_IP, _pair, _signed_probe_sql

WIDE, DEEP = GridSpec(4, 1000), GridSpec(8, 500)


def frame(spark, rows, schema) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def packets(spark, d) -> DataFrame:
    return grid.tuples(tables.table(spark, d, "events"), F.struct("user_id", "event_type", F.hour("ts")))


def part_suppliers(spark, d) -> DataFrame:
    return grid.tuples(tables.table(spark, d, "lineitem"), F.struct("l_partkey", "l_suppkey"))


def distinct_suppliers(spark, d) -> DataFrame:
    """A tuple for each (part, supplier): a grid of them holds exact distinct counts."""
    return tables.flows(spark, d).distinct().select("item", F.lit(1).cast("long").alias("c"))


def distinct_days(spark, d) -> DataFrame:
    return tables.table(spark, d, "events").select(F.col("user_id").alias("item"), "event_type", F.to_date("ts").alias("day")).distinct().select("item", F.lit(1).cast("long").alias("c"))


# --- Accuracy
add("w01_power_law")(lambda spark, d: workloads.power_law_sweep(spark))
add("w02_packets")(lambda spark, d: workloads.compare_all({"user_type_hour": (packets(spark, d), [GridSpec(4, 2500)]), "part_supplier": (part_suppliers(spark, d), [GridSpec(4, 10_000)])}))
add("w03_bigrams")(lambda spark, d: workloads.compare(tables.ngrams(spark, d, 2, "th"), [WIDE, DEEP]))
add("w04_flows")(lambda spark, d: workloads.compare_all({"suppliers_of_parts": (distinct_suppliers(spark, d), [GridSpec(4, 250)]), "days_of_users": (distinct_days(spark, d), [GridSpec(4, 20)])}))
add("w16_lowskew")(lambda spark, d: workloads.compare_all({"customers": (tables.customers(spark, d), [GridSpec(4, 48), GridSpec(4, 190)]), "users": (tables.users(spark, d), [GridSpec(4, 20)])}))


@add("w05_compare")
def w05_compare(spark, d):
    """All estimators on every kind of data, one grid each."""
    return workloads.compare_all({
        "power_law": (tables.power_law(spark, 20_000, 2.2), [DEEP]), "packets": (part_suppliers(spark, d), [GridSpec(4, 10_000)]), "bigrams": (tables.ngrams(spark, d, 2, "th"), [DEEP]),
        "flows": (distinct_suppliers(spark, d), [GridSpec(4, 250)]), "customers": (tables.customers(spark, d), [GridSpec(4, 100)]), "users": (tables.users(spark, d), [GridSpec(4, 20)]),
    })


# --- Intervals
LEVELS = [0.5, 0.8, 0.9, 0.95, 0.99]
#: Counts that a coverage study may send to each of its tasks.
MOST_COUNTS = 2_000_000


def coverage_study(counts: DataFrame, r: int, k: int, salts: int = 20, most: int = 2000, levels: list[float] | None = None) -> DataFrame:
    """(method, level, coverage, shrunk, width): means over `salts` grids of the counts (item, c), each worked out in a task of its own."""
    spark, levels = counts.sparkSession, levels or LEVELS
    known = np.sort(np.asarray([row[0] for row in counts.select("c").limit(MOST_COUNTS + 1).collect()], dtype=np.float64))[::-1]
    if len(known) > MOST_COUNTS:
        raise ValueError("too many items for a study by simulation")
    sent = spark.sparkContext.broadcast(known)

    def run(frames):
        for pdf in frames:
            for salt in pdf["id"]:
                rows = simulation.coverage_of_salt(sent.value, np.arange(min(most, len(sent.value))), r, k, levels, int(salt))
                yield pd.DataFrame(rows, columns=["method", "level", "coverage", "shrunk", "width"])

    told = spark.range(salts).repartition(salts, "id").mapInPandas(run, "method string, level double, coverage double, shrunk double, width double")
    return told.groupBy("method", "level").agg(*[F.round(F.avg(c), 6).alias(c) for c in ("coverage", "shrunk", "width")])


@add("w06_coverage")
def w06_coverage(spark, d):
    """Actual coverage by level and estimator over 20 salts, and with half a count less at each end: likelihood intervals too."""
    customers = tables.customers(spark, d).groupBy("item").agg(F.sum("c").alias("c"))
    named = {"customers": coverage_study(customers, 4, 150), "power_law": coverage_study(tables.power_law(spark, 5000, 2.0), 4, 250)}
    return reduce(DataFrame.unionByName, [df.select(F.lit(n).alias("workload"), "*") for n, df in named.items()])


@add("w07_width")
def w07_width(spark, d):
    """Markov's width over the tight one, by data and level."""
    rows = []
    named = {f"power_law_{a}": tables.power_law(spark, 20_000, a) for a in (2.0, 2.5, 3.0)} | {"words": tables.words(spark, d), "parts": tables.parts(spark, d)}
    for name, t in named.items():
        f = estimates.grid_law(grid.build_grid(t, WIDE))
        for level in (0.5, 0.9, 0.95, 0.99):
            tight, classic = f.quantile(beta_quantile(level, 1, 4)), estimates.markov_width(float(f.x @ f.m / 4), 4, 1000, level)
            rows.append((name, level, tight, classic, classic / max(tight, 1.0)))
    return frame(spark, rows, "workload string, level double, tight double, classical double, ratio double")


# --- Regression
@add("w08_regression")
def w08_regression(spark, d, items: int = 100_000, salts: int = 3):
    """Error by the number of jointly estimated items: Zipf(2) counts in a small grid, with a wide one as control, and words of documents."""
    jobs = [("zipf2", 1024), ("zipf2_wide", 65_536)]

    def run(frames):
        for pdf in frames:
            for job in pdf["id"]:
                name, k = jobs[int(job) % len(jobs)]
                rows = simulation.regression_of_salt(simulation.zipf(items, 2.0, seed=1), [8, 32, 128, 512], 4, k, int(job))
                yield pd.DataFrame([(name, *row) for row in rows], columns=["workload", "items", "mass_share", "method", "square"])

    told = spark.range(salts * len(jobs)).repartition(salts * len(jobs), "id").mapInPandas(run, "workload string, items long, mass_share double, method string, square double")
    told = told.groupBy("workload", "items", "method").agg(F.avg("mass_share").alias("mass_share"), F.sqrt(F.avg("square")).alias("rmse"))
    return told.unionByName(_words_regression(spark, d, told.columns))


def _words_regression(spark, d, columns: list[str]) -> DataFrame:
    spec = GridSpec(4, 1024)
    t = keep(tables.words(spark, d).groupBy("item").agg(F.sum("c").alias("c")), "counts")
    g = store.kept(grid.build_grid(t, spec))
    f, rows = estimates.grid_law(g), []
    spline = likelihood.density(f)
    bias = likelihood.column_mle_law(g, spline).mean()
    total = t.agg(F.sum("c")).first()[0]
    for n in (8, 32, 128):
        top = variants.top_items(t, n)
        truth = {r["item"]: r["c"] for r in top.collect()}
        items, cells, values = joint.system(top.select("item"), g)
        y = np.asarray([truth[i] for i in items], dtype=float)
        start = np.maximum(0, values[cells].min(axis=1) - f.order_mean(1, spec.r))
        own = {"least_squares": joint.least_squares(cells, values), "constrained_l1": joint.constrained(cells, values, start, "l1"), "joint_mle": joint.joint_mle(cells, values, start)[0], "debiased_min": start, "debiased_mle": np.maximum(0, mle(values[cells], spline) - bias)}
        rows += [("words", n, k, float(y.sum() / total), float(np.sqrt(((v - y) ** 2).mean()))) for k, v in own.items()]
    return frame(spark, rows, "workload string, items long, method string, mass_share double, rmse double").select(*columns)


@add("rmse_per_item", f"{sql_base()}, truth AS (SELECT item, CAST(sum(c) AS BIGINT) AS truth, row_number() OVER (ORDER BY sum(c) DESC, item) AS place FROM t GROUP BY item), x AS (SELECT i.items, s[1] - truth AS off, 'min' AS method FROM p JOIN truth USING (item) JOIN (VALUES (10), (100), (1000)) i(items) ON place <= i.items) SELECT CAST(items AS BIGINT) AS items, method, round(sqrt(avg(off * off)), 6) AS rmse FROM x GROUP BY items, method")
def rmse_per_item(spark, d):
    """The classical minimum's error per item, over the 10, 100 and 1,000 largest."""
    s = Setting(spark, d)
    est = estimates.classical(s.probed)
    rows = [variants.top_items(s.truth, n).join(est, "item").select(F.lit(n).cast("long").alias("items"), F.lit("min").alias("method"), F.col("c").alias("truth"), "est") for n in (10, 100, 1000)]
    return metrics.rmse_by_size(reduce(DataFrame.unionByName, rows)).select("items", "method", r6("rmse").alias("rmse"))


@add("joint_constrained")
def joint_constrained(spark, d):
    """The largest 100 items by three losses within the same constraints, and what the constraints leave: no cell overdrawn."""
    s = Setting(spark, d)
    items, cells, values = joint.system(variants.top_items(s.truth, 100).select("item"), s.grid)
    f = estimates.grid_law(s.grid)
    start = np.maximum(0, values[cells].min(axis=1) - f.order_mean(1, SPEC.r))
    spline = likelihood.density(f)
    found = {loss: joint.constrained(cells, values, start, loss, spline) for loss in ("l1", "l2", "likelihood")}
    return frame(spark, [(i, *(float(found[k][n]) for k in found)) for n, i in enumerate(items)], "item long, l1 double, l2 double, likelihood double")


@add("joint_mle_cluster")
def joint_mle_cluster(spark, d):
    """The same alternation with items and cells on the cluster, for all users."""
    s = Setting(spark, d, tables.users, GridSpec(4, 60, "poly4"))
    return joint.joint_mle_cluster(s.items, s.grid, 3).join(s.truth.withColumnRenamed("c", "truth"), "item")


# --- Shapes, growth, depth
def _spread(est: np.ndarray) -> float:
    return float(np.sqrt(((est - est.mean()) ** 2).mean()))


@add("w09_shapes")
def w09_shapes(spark, d):
    """Errors of light and heavy tails, off grids of parts and of words at a load of 8, in units of the spread of their middle half (1 for the normal law) and cut off at offsets: each estimator debiased by the mean of its own
    law over fresh draws, as over a grid's columns."""
    rows = []
    for shape, source in (("parts", tables.parts), ("words", tables.words)):
        counts = keep(source(spark, d).groupBy("item").agg(F.sum("c").alias("c")), "counts")
        f = estimates.grid_law(grid.build_grid(counts, GridSpec(4, max(50, counts.count() // 8))))
        low, middle, high = (f.quantile(p) for p in (0.25, 0.5, 0.75))
        whole = 1.349 * (f.x - middle) / max(1.0, high - low)
        for offset in (-1.0, 0.0, 1.0, 3.0):
            kept = whole + offset > 0
            pool = errors.Law(whole[kept] + offset, f.m[kept])
            x, at = np.unique(np.round(pool.x, 2), return_inverse=True)
            s = fit_logconcave(x, np.bincount(at, weights=pool.m).astype(np.int64)).extended()
            for r in (4, 8, 16):
                e, columns = pool.draws((1500, r), seed=r), pool.draws((1500, r), seed=r + 100)
                stats = {"min": lambda x: x.min(axis=1), "mean": lambda x: x.mean(axis=1), "median": lambda x: np.median(x, axis=1), "mle": lambda x, s=s: mle(x, s)}
                rmse = {k: float(np.sqrt(((f(e) - f(columns).mean()) ** 2).mean())) for k, f in stats.items()}
                rows += [(shape, offset, r, k, v, (v / max(1e-12, rmse["mle"])) ** 2) for k, v in rmse.items()]
    return frame(spark, rows, "shape string, offset double, r int, method string, rmse double, rel_eff double")


GROWTH = "load int, items long, min double, conservative double, mle_debiased double"


@add("growth_study")
def growth_study(spark, d, k: int = 64):
    """Error against load over the orders of all customers: the minimum's grows with the load, with conservative updates as well; the debiased likelihood estimate's with its root.

    Customers are dealt by hash to grids of about `k` columns at each load, so that every order counts, one update after the other, whatever their number.
    """
    counts = keep(tables.customers(spark, d).groupBy("item").agg(F.sum("c").alias("c")), "counts")
    n, loads = counts.count(), (4, 16, 64)
    blocks = F.element_at(F.create_map(*[F.lit(x) for load in loads for x in (load, max(1, round(n / (load * k))))]), F.col("load"))
    dealt = counts.select("item", "c", F.explode(F.array(*[F.lit(load) for load in loads])).alias("load")).withColumn("block", F.pmod(F.xxhash64(F.lit(5), "item"), blocks))

    def study(key, pdf):
        load, block = int(key[0]), int(key[1])
        known = pdf.sort_values("item")["c"].to_numpy(np.float64)
        return pd.DataFrame([(load, len(known), *simulation.growth_of_block(known, load, 4, load * 1_000_003 + block))], columns=["load", "items", "min", "conservative", "mle_debiased"])

    told = dealt.groupBy("load", "block").applyInPandas(study, GROWTH)
    return told.groupBy("load").agg(F.sum("items").alias("items"), *[F.sqrt(F.sum(c) / F.sum("items")).alias(c) for c in ("min", "conservative", "mle_debiased")])


@add("wide_rule")
def wide_rule(spark, d):
    """Shallow against deep splits of one budget, by data and level, from 1 x B grids alone: what to prefer when nothing is known."""
    rows = []
    for name, t in {"parts": tables.parts(spark, d), "users": tables.users(spark, d), "words": tables.words(spark, d), "power_law": tables.power_law(spark, 20_000, 2.0)}.items():
        f = estimates.grid_law(grid.build_grid(t, GridSpec(1, 4000)))
        base = tuning.mass(f, min(400_000, 20 * (int(f.x.max()) + 1)))
        told = {(dp, lv): w for dp, lv, w in tuning.depth_widths(base, list(range(1, 17)), [0.5, 0.9, 0.99])}
        for level in (0.5, 0.9, 0.99):
            best = min(range(1, 17), key=lambda dp: (told[dp, level], dp))
            rows.append((name, level, best, told[best, level], told[4, level], told[16, level], "shallow" if told[4, level] <= told[16, level] else "deep"))
    return frame(spark, rows, "workload string, level double, best_depth int, best double, depth_4 double, depth_16 double, prefer string")


@add("w11_depth")
def w11_depth(spark, d):
    """Interval width by depth at a fixed budget, predicted from one 1 x B grid: negative binomial counts and summed quantities of parts; `kind` tells the usual depths and the best one."""
    g, rows = np.random.default_rng(0), []
    c = g.negative_binomial(30, 0.01, 4000)
    line = np.bincount(g.integers(0, 8000, 4000), weights=c, minlength=8000).astype(int)
    parts = estimates.grid_law(grid.build_grid(tables.part_quantities(spark, d), GridSpec(1, 8000)))
    for name, base in (("negative_binomial", np.bincount(line, minlength=24 * (line.max() + 1)) / 8000), ("part_quantities", tuning.mass(parts, 24 * (int(parts.x.max()) + 1)))):
        depths = list(range(1, 13)) + [d_ for d_ in tuning.DEPTH_PRESETS if d_ > 12]
        for level in LEVELS:
            told = tuning.depth_widths(base, depths, [level])
            best = min(told, key=lambda x: (x[2], x[0]))[0]
            rows += [(name, dp, level, w, "best" if dp == best else "preset" if dp in (4, 10) else "other") for dp, _, w in told]
    return frame(spark, rows, "workload string, depth int, level double, width double, kind string")


# --- Time
def timed(spark, t: DataFrame, spec: GridSpec, most: int = 2000) -> tuple[int, int, float, float, float]:
    """(items, cells, ms per count, evaluations per count, seconds of the fit): grid and density are there before the clock runs for the estimates."""
    counts = keep(t.groupBy("item").agg(F.sum("c").alias("c")), "counts")
    g = store.kept(grid.build_grid(counts, spec))
    f = estimates.grid_law(g)
    began = time.perf_counter()
    spline = likelihood.density(f)
    fitted = time.perf_counter() - began
    v = np.asarray([r["v"] for r in grid.probe(variants.top_items(counts, most).select("item"), g).collect()])
    many = likelihood.mle_counts(v, spline)[0].mean()
    began = time.perf_counter()
    mle(v, spline)
    return len(v), spec.cells, (time.perf_counter() - began) / len(v) * 1e3, float(many), fitted


TIMED = "items int, cells long, ms double, evaluations double, fit_seconds double"
add("ms_per_count")(lambda spark, d: frame(spark, [timed(spark, tables.parts(spark, d), SPEC)], TIMED))
add("w12_timing")(lambda spark, d: frame(spark, [timed(spark, tables.ngrams(spark, d, 2), GridSpec(8, 1_000_000))], TIMED))


# --- Corpora, inner products, sets, ablations, signed grids
@add("w13_corpus_tuning")
def w13_corpus_tuning(spark, d):
    """Sizing for 5-grams: widths told from one 1 x B grid of a fifth of the items, scaled back to the whole rate, from the whole table's, and rebuilt ones."""
    whole, budget = keep(tables.ngrams(spark, d, 5).groupBy("item").agg(F.sum("c").alias("c")), "counts"), 20_000
    some = variants.coordinated_sample(whole, 0.2)
    laws = {n: estimates.grid_law(grid.build_grid(t, GridSpec(1, budget))) for n, t in (("sampled", some), ("whole", whole))}
    # A fifth of the items at five times the depth has the whole table's load; the quantile is that of the real depth.
    sampled, full = (tuning.split_widths(laws[n], [1, 2, 4], [0.9, 0.95], power) for n, power in (("sampled", 5), ("whole", 1)))
    rows = []
    for depth in (1, 2, 4):
        f = estimates.grid_law(grid.build_grid(whole, GridSpec(depth, budget // depth)))
        rows += [(depth, level, sampled[depth, level], full[depth, level], f.quantile(beta_quantile(level, 1, depth))) for level in (0.9, 0.95)]
    return frame(spark, rows, "depth int, level double, from_sample double, from_whole double, rebuilt double")


SQL_ERRORS = f"{SQL_IP}, tr AS (SELECT CAST(sum(a.c * b.c) AS DOUBLE) AS truth FROM (SELECT item, sum(c) AS c FROM t GROUP BY item) a JOIN (SELECT item, sum(c) AS c FROM u GROUP BY item) b USING (item)), su AS (SELECT avg(p) AS bias FROM (SELECT g.rep, s, sum(g.v * w.v) AS p FROM range(1, 21) x(s), g JOIN w ON g.rep = w.rep WHERE w.idx = (g.idx + s) % 250 GROUP BY g.rep, s)), m AS (SELECT CAST(min(product) AS DOUBLE) AS low, median(250 / 249.0 * (product - st / 250)) AS middle FROM ip, tot) SELECT method, round(est, 3) AS est, round((est - truth) / truth, 6) AS rel_error FROM (SELECT 'min' AS method, low AS est, truth FROM m, tr UNION ALL SELECT 'unbiased', middle, truth FROM m, tr UNION ALL SELECT 'surrogate', low - bias, truth FROM m, tr, su)"


def _ip_errors(u: grid.CounterGrid, w: grid.CounterGrid, exact: DataFrame) -> DataFrame:
    found = variants.inner_products(u, w).agg(F.min("product").cast("double").alias("min"), F.percentile("unbiased", 0.5).alias("unbiased"))
    surrogate = variants.surrogate_products(u, w, 20).agg(F.avg("product").alias("bias"))
    rows = found.crossJoin(exact).crossJoin(surrogate)
    rows = rows.select(F.expr("stack(3, 'min', min, 'unbiased', unbiased, 'surrogate', min - bias) AS (method, est)"), "truth")
    return rows.select("method", F.round("est", 3).alias("est"), F.round((F.col("est") - F.col("truth")) / F.col("truth"), 6).alias("rel_error"))


@add("ip_rel_error", SQL_ERRORS)
def ip_rel_error(spark, d):
    return _ip_errors(*[store.kept(g) for g in _pair(spark, d)], QUERIES["ip_exact"](spark, d).select(F.col("product").alias("truth")))


_SECOND = SQL_ERRORS.replace(SQL_IP.split("t AS (")[1].split("), u AS (")[0], "SELECT CAST(o_custkey AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM orders").replace(SQL_IP.split("), u AS (")[1].split("), g AS")[0], TUPLES_SQL["users"])


@add("w14_inner", f"SELECT 'returned_accepted' AS pair, * FROM ({SQL_ERRORS}) UNION ALL SELECT 'customers_users', * FROM ({_SECOND})")
def w14_inner(spark, d):
    """Inner products of two pairs: parts returned and accepted, and orders with events by id."""
    named = {"returned_accepted": ip_rel_error(spark, d)}
    a, b = (s.groupBy("item").agg(F.sum("c").alias(n)) for s, n in ((tables.customers(spark, d), "a"), (tables.users(spark, d), "b")))
    exact = a.join(b, "item").agg(F.sum(F.col("a") * F.col("b")).cast("double").alias("truth"))
    named["customers_users"] = _ip_errors(*[store.kept(grid.build_grid(s(spark, d), SPEC)) for s in (tables.customers, tables.users)], exact)
    return reduce(DataFrame.unionByName, [df.select(F.lit(n).alias("pair"), "*") for n, df in named.items()])


RANGES = [(1, 10), (5, 37), (17, 17), (0, 63)]
DYADIC = GridSpec(4, 64, "poly4")


def _sets_sql() -> str:
    cover = ", ".join(f"({low}, {high}, CAST({x} AS BIGINT))" for low, high in RANGES for x in grid.dyadic_cover(low, high, 6))
    spread = " UNION ALL ".join(f"SELECT {l} * 64 + (q >> {l}) AS item, CAST(1 AS BIGINT) AS c FROM bq" for l in range(6))
    sets = f"{sql_base()}, n AS (SELECT p_brand AS b, sum(s[1]) AS est FROM p JOIN part ON p_partkey = item GROUP BY p_brand), tr AS (SELECT p_brand AS b, count(*) AS truth FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY p_brand) SELECT 'brands' AS kind, count(*) AS n, round(sqrt(avg((est - truth) ** 2)), 6) AS rmse FROM n JOIN tr USING (b)"
    ranges = f"WITH bq AS (SELECT CAST(l_quantity AS BIGINT) AS q FROM lineitem), t AS ({spread}), cover(low, high, item) AS (VALUES {cover}), {sql_grid('g', 't', DYADIC)}, {sql_probe('p', 'cover', 'g', DYADIC)}, e AS (SELECT low, high, sum(s[1]) AS est FROM p GROUP BY low, high), x AS (SELECT low, high, est, (SELECT count(*) FROM bq WHERE q BETWEEN low AND high) AS truth FROM e) SELECT 'ranges' AS kind, count(*) AS n, round(sqrt(avg((est - truth) ** 2)), 6) AS rmse FROM x"
    return f"SELECT * FROM ({sets}) UNION ALL SELECT * FROM ({ranges})"


@add("w15_sets", _sets_sql())
def w15_sets(spark, d):
    """Errors of set and range answers: parts by brand, and ranges of quantities."""
    s = Setting(spark, d)
    brands = tables.table(spark, d, "part").select(F.col("p_partkey").alias("item"), F.col("p_brand").alias("set"))
    sets = grid.probe(s.truth, s.grid).join(brands, "item").groupBy("set").agg(F.sum(F.array_min("v")).alias("est"), F.sum("c").alias("truth"))
    t = tables.table(spark, d, "lineitem").select(F.col("l_quantity").cast("long").alias("item"), F.lit(1).cast("long").alias("c"))
    t = keep(t.groupBy("item").agg(F.sum("c").alias("c")), "counts")
    cover = frame(spark, [(a, b, x) for a, b in RANGES for x in grid.dyadic_cover(a, b, 6)], "low long, high long, item long")
    est = grid.probe(cover, grid.build_grid(grid.dyadic(t, 6), DYADIC)).groupBy("low", "high").agg(F.sum(F.array_min("v")).alias("est"))
    bounds = F.broadcast(frame(spark, RANGES, "low long, high long"))
    truth = t.join(bounds, F.col("item").between(F.col("low"), F.col("high"))).groupBy("low", "high").agg(F.sum("c").alias("truth"))
    off = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count("*").alias("n"), F.round(F.sqrt(F.avg(F.pow(F.col("est") - F.col("truth"), F.lit(2.0)))), 6).alias("rmse"))
    return off(sets, "brands").unionByName(off(est.join(truth, ["low", "high"]), "ranges"))


@add("w17_ablation")
def w17_ablation(spark, d):
    """Error and coverage of choices: bias rule, own cells in or out, cutting at 0, half a count off each end, likelihood with and without debiasing, and the trim."""
    out = []
    for name, s in {"customers": Setting(spark, d, tables.customers, GridSpec(4, 150)), "bigrams": Setting(spark, d, lambda a, b: tables.ngrams(a, b, 2, "th"), DEEP)}.items():
        r = s.spec.r
        top = keep(grid.probe(variants.top_items(s.truth, 2000), s.grid), "probed")
        probed, truth = top.select("item", "v"), top.select("item", F.col("c").alias("truth"))
        f, g = estimates.grid_law(s.grid), estimates.statistic_law(s.grid, t_median)
        found = {f"min_{m}": estimates.debiased_min(probed, f, r, LEVEL, m) for m in ("plugin", "rank", "exact")} | {
            "min_exact_free": estimates.debiased_min(probed, f, r, LEVEL, "exact", truncate=False), "median": estimates.debiased(probed, t_median, g, LEVEL),
            "median_shrunk": estimates.debiased(probed, t_median, g, LEVEL, shrink=0.5),
            "min_own_out": estimates.debiased_min_own_out(probed, f, r).join(estimates.min_interval_own_out(probed, f, r, LEVEL).select("item", "lo", "hi"), "item"),
        }
        for trim in (0.001, 0.01, 0.05):
            spline = likelihood.density(f, trim)
            found[f"mle_trim_{trim}"] = likelihood.max_likelihood(probed, spline).withColumn("lo", F.lit(None).cast("double")).withColumn("hi", F.lit(None).cast("double"))
            found[f"debiased_mle_trim_{trim}"] = likelihood.debiased_mle(probed, s.grid, spline, LEVEL)
        rows = reduce(DataFrame.unionByName, [e.select("item", F.lit(k).alias("method"), *[F.col(c).cast("double").alias(c) for c in ("est", "lo", "hi")]) for k, e in found.items()])
        rows = rows.join(F.broadcast(truth), "item")
        inside = ((F.col("lo") <= F.col("truth")) & (F.col("truth") <= F.col("hi"))).cast("double")
        off = F.col("est") - F.col("truth")
        out.append(rows.groupBy("method").agg(F.sqrt(F.avg(off * off)).alias("rmse"), F.avg(off).alias("bias"), F.avg(inside).alias("coverage"), F.avg(F.col("hi") - F.col("lo")).alias("width")).select(F.lit(name).alias("workload"), "*"))
    return reduce(DataFrame.unionByName, out)


#: Equal space: a signed grid of the same shape.
SIGNED_SQL = f"{sql_base()}, {sql_law(STATS['median'][1])}, tr AS (SELECT item, sum(c) AS truth FROM t GROUP BY item), sg AS (SELECT rep, idx, sum(c) AS v FROM (" + " UNION ALL ".join(f"SELECT {a} AS rep, {cell_sql('item', a, SPEC)} AS idx, {sign_sql('item', a, SPEC)} * c AS c FROM t" for a in range(4)) + ") GROUP BY rep, idx), sp AS (SELECT i.item, list_sort([" + ", ".join(f"coalesce(s{a}.v, 0) * {sign_sql('i.item', a, SPEC)}" for a in range(4)) + "]) AS s FROM items i " + " ".join(f"LEFT JOIN sg s{a} ON s{a}.rep = {a} AND s{a}.idx = {cell_sql('i.item', a, SPEC)}" for a in range(4)) + "), e AS (SELECT item, 'one_sided_median' AS method, greatest(0, (s[2] + s[3]) / 2.0 - mu) AS est FROM p, mu UNION ALL SELECT item, 'signed_median', (s[2] + s[3]) / 2.0 FROM sp) SELECT method, count(*) AS n, round(sqrt(avg((est - truth) ** 2)), 5) AS rmse FROM e JOIN tr USING (item) GROUP BY method"


def _signed_pair(t: DataFrame, spec: GridSpec) -> DataFrame:
    counts = keep(t.groupBy("item").agg(F.sum("c").alias("c")), "counts")
    truth = counts.withColumnRenamed("c", "truth")
    g = store.kept(grid.build_grid(counts, spec))
    one = estimates.debiased(grid.probe(truth.select("item"), g), t_median, estimates.statistic_law(g, t_median), LEVEL).select("item", "est")
    two = estimates.classical(variants.probe_signed(truth.select("item"), store.kept(variants.build_signed(counts, spec))), t_median)
    rows = one.withColumn("method", F.lit("one_sided_median")).unionByName(two.withColumn("method", F.lit("signed_median"))).join(truth, "item")
    return metrics.accuracy(rows).select("method", "n", F.round("rmse", 5).alias("rmse"))


add("w18_signed", SIGNED_SQL)(lambda spark, d: _signed_pair(tables.parts(spark, d), SPEC))


@add("w18_signed_skew")
def w18_signed_skew(spark, d):
    """The same on heavy tails: power-law counts and 2-grams."""
    named = {"power_law": tables.power_law(spark, 20_000, 2.2), "bigrams": tables.ngrams(spark, d, 2, "th")}
    return reduce(DataFrame.unionByName, [_signed_pair(t, DEEP).select(F.lit(n).alias("workload"), "*") for n, t in named.items()])


@add("signed_ci", f"{_signed_probe_sql()}, k AS (SELECT r.i AS idx, list_sort([{', '.join(f'coalesce(sum(CASE WHEN rep = {a} THEN v END), 0)' for a in range(4))}]) AS s FROM range({SPEC.k}) r(i) LEFT JOIN g ON g.idx = r.i GROUP BY r.i), m AS (SELECT (s[2] + s[3]) / 2.0 AS v FROM k), b AS (SELECT v FROM m UNION ALL SELECT -v FROM m), lc AS (SELECT v, sum(count(*)) OVER (ORDER BY v) AS cum FROM b GROUP BY v) SELECT item, round((s[2] + s[3]) / 2.0, 6) AS est, round((s[2] + s[3]) / 2.0 - {sql_rank((1 + LEVEL) / 2, 2 * SPEC.k, 'lc')}, 6) AS lo, round((s[2] + s[3]) / 2.0 - {sql_rank((1 - LEVEL) / 2, 2 * SPEC.k, 'lc')}, 6) AS hi FROM p")
def signed_ci(spark, d):
    """Intervals of the signed median by the law of the median over the grid's columns, each with both signs, as errors are even around 0."""
    counts = keep(tables.parts(spark, d).groupBy("item").agg(F.sum("c").alias("c")), "counts")
    g = store.kept(variants.build_signed(counts, SPEC))
    own = estimates.statistic_law(g, t_median)
    x, at = np.unique(np.concatenate([own.x, -own.x]), return_inverse=True)
    both = errors.Law(x, np.bincount(at, weights=np.concatenate([own.m, own.m])).astype(np.int64))
    e = estimates.debiased(variants.probe_signed(counts.select("item"), g), t_median, errors.Law(both.x, both.m), LEVEL, truncate=False)
    raw = e.select("item", F.round(F.col("est") + F.lit(both.mean()), 6).alias("est"), r6("lo").alias("lo"), r6("hi").alias("hi"))
    return raw


_CONDITION = (
    "WITH c AS (SELECT count(*) AS x FROM lineitem WHERE l_partkey IS NOT NULL GROUP BY l_partkey, l_suppkey), h AS (SELECT x, count(*) AS m FROM c GROUP BY x), "
    "g AS (SELECT i AS x, coalesce(m, 0) / (SELECT CAST(sum(m) AS DOUBLE) FROM h) AS p FROM (SELECT unnest(range(1, (SELECT max(x) + 1 FROM h))) AS i) LEFT JOIN h ON h.x = i), "
    "s AS (SELECT p * x AS b, lag(p * x) OVER (ORDER BY x) AS l, lead(p * x) OVER (ORDER BY x) AS r FROM g), "
    "ok AS (SELECT coalesce(bool_and(b * b >= l * r * (1 - CAST(1e-12 AS DOUBLE))), true) AS lc FROM s WHERE l IS NOT NULL AND r IS NOT NULL), "
    "e AS (SELECT sum(CASE WHEN x = 1 THEN p ELSE 0 END) AS one, sum(CASE WHEN x = 2 THEN p ELSE 0 END) AS two FROM g) "
    "SELECT load, lc AND load >= 2 * two / (one * one) AS log_concave FROM (VALUES (CAST(0.01 AS DOUBLE)), (0.1), (0.2), (0.3), (1.0), (10.0)) t(load), ok, e"
)


@add("logconcave_condition", _CONDITION)
def logconcave_condition(spark, d):
    """From which load on counters of (part, supplier) counts have a log-concave law, by the counts' own law."""
    each = tables.flows(spark, d).where("item IS NOT NULL").groupBy("item", "element").agg(F.count("*").alias("x"))
    told = each.groupBy("x").agg(F.count("*").alias("m")).collect()
    g = np.zeros(max([2, *(r["x"] for r in told)]))
    for r in told:
        g[r["x"] - 1] = r["m"]
    g /= max(1.0, g.sum())
    return frame(spark, [(x, tuning.compound_is_logconcave(g, x)) for x in (0.01, 0.1, 0.2, 0.3, 1.0, 10.0)], "load double, log_concave boolean")


_DECAYED = "SELECT CAST(o_custkey AS BIGINT) AS item, CAST(round(1000000 * pow(2.0, -date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') / 365.0)) AS BIGINT) AS c FROM orders"


@add("decayed_query", f"WITH t AS ({_DECAYED}), items AS (SELECT DISTINCT item FROM t), {sql_grid('g', 't')}, {sql_probe('p', 'items')} SELECT item, round(s[1] / 1000000.0, 6) AS est FROM p")
def decayed_query(spark, d):
    """The classical answer of a time-weighted grid, in counts of the present."""
    g = store.kept(grid.CounterGrid(QUERIES["decayed_build"](spark, d), SPEC))
    items = tables.customers(spark, d).select("item").distinct()
    return estimates.classical(grid.probe(items, g)).select("item", F.round(F.col("est") / 1_000_000, 6).alias("est"))
