"""Likelihood estimators over probed items: the density is fitted on the driver from the grid's histogram, items stay distributed."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.density import LogSpline, bayes, credible, fit_logconcave, mle, mle_counts, posterior
from ..functions.statistics import location
from .errors import Law, columns, law
from .grid import CounterGrid


def density(errors: Law, trim: float = 0.01) -> LogSpline:
    """The log-concave density of error counters, ready for use from 0 on."""
    return fit_logconcave(errors.x, errors.m, trim).extended()


def counters(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def by_item(probed: DataFrame, kernel, names: str) -> DataFrame:
    """`kernel` gives, for a matrix of counters, one array for each name."""
    kind = dict(probed.dtypes)["item"]

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                found = kernel(counters(batch.column("v")))
                yield pa.RecordBatch.from_arrays([batch.column("item"), *[pa.array(f, pa.float64()) for f in found]], names=["item", *names.split()])

    return probed.select("item", "v").mapInArrow(blocks, f"item {kind}, " + ", ".join(f"{n} double" for n in names.split()))


def max_likelihood(probed: DataFrame, spline: LogSpline) -> DataFrame:
    """item, est. With a density that only falls the smallest counter is the answer, and no Python runs."""
    if spline.falling:
        return probed.select("item", F.array_min("v").cast("double").alias("est"))
    return by_item(probed, lambda v: [np.maximum(0, mle(v, spline))], "est")


def kernel_counts(probed: DataFrame, spline: LogSpline) -> DataFrame:
    """(item, evaluations, tied): what the maximisation of each item did."""
    kind = dict(probed.dtypes)["item"]

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                many, tied = mle_counts(counters(batch.column("v")), spline)
                yield pa.RecordBatch.from_arrays([batch.column("item"), pa.array(many), pa.array(tied)], names=["item", "evaluations", "tied"])

    return probed.select("item", "v").mapInArrow(blocks, f"item {kind}, evaluations long, tied boolean")


def column_mle_law(grid: CounterGrid, spline: LogSpline) -> Law:
    """The law of the estimator, not cut off at 0, over the grid's columns."""
    values = by_item(columns(grid).select(F.col("idx").alias("item"), "v"), lambda v: [mle(v, spline)], "est")
    return law(values.groupBy(F.col("est").alias("v")).agg(F.count("*").alias("m")))


def debiased_mle(probed: DataFrame, grid: CounterGrid, spline: LogSpline, level: float = 0.9, truncate: bool = True) -> DataFrame:
    """item, est, lo, hi."""
    g = column_mle_law(grid, spline)
    raw = by_item(probed, lambda v: [mle(v, spline)], "raw")
    cut = (lambda c: F.greatest(F.lit(0.0), c)) if truncate else (lambda c: c)
    low, high = g.quantile((1 - level) / 2), g.quantile((1 + level) / 2)
    return raw.select("item", cut(F.col("raw") - g.mean()).alias("est"), cut(F.col("raw") - high).alias("lo"), (F.col("raw") - low).alias("hi"))


def bayes_estimates(probed: DataFrame, spline: LogSpline, loss: str = "l2", level: float = 0.9, power: float | None = None, cap: float = 10.0, log_prior: Callable | None = None) -> DataFrame:
    """item, est, lo, hi by the posterior of each count; flat prior, (n + 1)^-power, or `log_prior` of counts."""
    prior = log_prior if power is None else (lambda n: -power * np.log(n + 1))

    def kernel(v: np.ndarray) -> list[np.ndarray]:
        out = []
        for row in v:
            n, p = posterior(row, spline, prior)
            out.append((bayes(n, p, loss, cap), *credible(n, p, level)))
        return list(np.asarray(out).T)

    return by_item(probed, kernel, "est lo hi")


def posteriors(probed: DataFrame, spline: LogSpline, least: float = 0.0) -> DataFrame:
    """(item, n, p): the posterior of each count under a flat prior; probabilities below `least` are left out."""
    kind = dict(probed.dtypes)["item"]

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, row in enumerate(counters(batch.column("v")) if batch.num_rows else ()):
                n, p = posterior(row, spline)
                n, p = n[p >= least], p[p >= least]
                item = batch.column("item").take(pa.array(np.full(len(n), at)))
                yield pa.RecordBatch.from_arrays([item, pa.array(n.astype(np.int64)), pa.array(p)], names=["item", "n", "p"])

    return probed.select("item", "v").mapInArrow(blocks, f"item {kind}, n long, p double")


def empirical_prior(sample: DataFrame) -> Callable:
    """Log shares of counts in `sample` (item, c), an item for each; counts are gathered in bins a factor of two wide and shared evenly inside them."""
    bins = sample.groupBy("item").agg(F.sum("c").alias("c")).groupBy(F.floor(F.log2(F.col("c") + 1)).alias("b")).agg(F.count("*").alias("m")).collect()
    share = np.full(64, 0.5)
    for row in bins:
        share[row["b"]] += row["m"]
    log = np.log(share / share.sum()) - np.arange(64) * np.log(2)
    return lambda n: log[np.floor(np.log2(n + 1)).astype(int)]


def location_estimates(probed: DataFrame, loss: str = "huber") -> DataFrame:
    return by_item(probed, lambda v: [location(v, loss)], "est")
