"""Experiment workloads: all estimators on one grid, measured against the true counts of the largest items."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.density import mle
from ..functions.hashing import GridSpec
from ..functions.statistics import beta_quantile, t_mean, t_median, t_min
from ..operators.errors import error_hist, law
from ..operators.estimates import markov_width, statistic_law
from ..operators.grid import build_grid, probe
from ..operators.likelihood import column_mle_law, counters, density
from ..operators.store import kept
from ..operators.variants import top_items
from ..sources.shared import keep
from ..sources.tables import power_law

METHODS = ("min", "debiased_min", "debiased_mean", "debiased_median", "mle", "debiased_mle")


def estimates(df: DataFrame, spec: GridSpec, most: int = 2000, level: float = 0.9) -> DataFrame:
    """(item, truth, method, est, lo, hi) for the `most` largest items.

    The input is read once, for counts by item; the grid is built from them and kept. All methods are answered in one pass over the probed items: laws are
    literals, and the likelihood kernel runs once for both of its methods.
    """
    counts = keep(df.groupBy("item").agg(F.sum("c").alias("c")), "counts")
    grid = kept(build_grid(counts, spec))
    probed = probe(top_items(counts, most).withColumnRenamed("c", "truth"), grid)
    errors = law(error_hist(grid))
    spline, r = density(errors), spec.r
    g = {"mean": statistic_law(grid, t_mean), "median": statistic_law(grid, t_median), "mle": column_mle_law(grid, spline)}
    kind = dict(probed.dtypes)["item"]

    def likely(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield batch.append_column("raw", pa.array(mle(counters(batch.column("v")), spline)))

    rows = probed.select("item", "truth", "v").mapInArrow(likely, f"item {kind}, truth long, v array<bigint>, raw double")
    low, none = t_min(F.col("v")), F.lit(None).cast("double")
    cut = lambda c: F.greatest(F.lit(0.0), c)
    markov = markov_width(float(errors.x @ errors.m / r), r, spec.k, level)
    tight = errors.quantile(beta_quantile(level, 1, r))

    def by_law(raw: Column, name: str) -> tuple[Column, Column, Column]:
        own = g[name]
        return cut(raw - own.mean()), cut(raw - own.quantile((1 + level) / 2)), raw - own.quantile((1 - level) / 2)

    found = {
        "min": (low, cut(low - markov), low),
        "debiased_min": (cut(low - errors.order_mean(1, r)), cut(low - tight), low),
        "debiased_mean": by_law(t_mean(F.col("v")), "mean"),
        "debiased_median": by_law(t_median(F.col("v")), "median"),
        "mle": (cut(F.col("raw")), none, none),
        "debiased_mle": by_law(F.col("raw"), "mle"),
    }
    every = F.array(*[F.struct(F.lit(name).alias("method"), *[c.cast("double").alias(n) for n, c in zip(("est", "lo", "hi"), own, strict=True)]) for name, own in found.items()])
    return rows.select("item", "truth", F.explode(every).alias("x")).select("item", "truth", "x.*")


def compare(df: DataFrame, specs: list[GridSpec], most: int = 2000, level: float = 0.9) -> DataFrame:
    """(r, k, method, n, rmse, bias, rel_eff, coverage, width): rel_eff is the squared error over the debiased likelihood estimate's."""
    out = []
    for spec in specs:
        off = F.col("est") - F.col("truth")
        inside = ((F.col("lo") <= F.col("truth")) & (F.col("truth") <= F.col("hi"))).cast("double")
        m = estimates(df, spec, most, level).groupBy("method").agg(F.count("*").alias("n"), F.sqrt(F.avg(off * off)).alias("rmse"), F.avg(off).alias("bias"), F.avg(inside).alias("coverage"), F.avg(F.col("hi") - F.col("lo")).alias("width"))
        base = F.max(F.when(F.col("method") == "debiased_mle", F.col("rmse") * F.col("rmse"))).over(Window.partitionBy())  # one row for each method
        out.append(m.withColumn("rel_eff", F.col("rmse") * F.col("rmse") / F.greatest(base, F.lit(1e-12))).select(F.lit(spec.r).alias("r"), F.lit(spec.k).alias("k"), "method", "n", "rmse", "bias", "rel_eff", "coverage", "width"))
    return reduce(DataFrame.unionByName, out)


def compare_all(named: dict[str, tuple[DataFrame, list[GridSpec]]], most: int = 2000) -> DataFrame:
    """`compare` for several workloads, by name."""
    return reduce(DataFrame.unionByName, [compare(df, specs, most).select(F.lit(name).alias("workload"), "*") for name, (df, specs) in named.items()])


def power_law_sweep(spark: SparkSession, items: int = 20_000, alphas: tuple[float, ...] = (2.0, 3.0), offsets: tuple[float, ...] = (0.0, 10.0), specs: list[GridSpec] | None = None, most: int = 2000) -> DataFrame:
    """`compare` over tail exponents, offsets and grids; the published range is 10^6 items, r 2 to 16 and k 10^4 to 5 x 10^5."""
    specs = specs or [GridSpec(8, 500)]
    out = [compare(power_law(spark, items, a, o), specs, most).select(F.lit(a).alias("alpha"), F.lit(o).alias("offset"), "*") for a in alphas for o in offsets]
    return reduce(DataFrame.unionByName, out)


def minimum(df: DataFrame, spec: GridSpec) -> DataFrame:
    """(item, est) of all items by the classical estimator."""
    return probe(df.select("item").distinct(), build_grid(df, spec)).select("item", t_min(F.col("v")).alias("est"))
