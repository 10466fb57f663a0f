"""Point estimates with intervals: classical, debiased, and their bounds.

Input is `probe`'s output (item, v). A law is worked out once per grid; what it gives enters the plan as literals, so estimating is a projection of
built-in functions.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.statistics import beta_quantile, t_min, t_order
from .errors import Law, column_hist, error_hist, law
from .grid import CounterGrid


def classical(probed: DataFrame, statistic=t_min) -> DataFrame:
    return probed.select("item", statistic(F.col("v")).alias("est"))


def debiased(probed: DataFrame, statistic, errors: Law, level: float = 0.9, truncate: bool = True, shrink: float = 0.0) -> DataFrame:
    """item, est, lo, hi by the law of the statistic over error counters; `truncate`: estimates and bounds of non-negative counts end at 0."""
    mean, low, high = errors.mean(), errors.quantile((1 - level) / 2), errors.quantile((1 + level) / 2)
    return _shifted(probed, statistic(F.col("v")), mean, low + shrink, high - shrink, truncate)


def _shifted(probed: DataFrame, raw: Column, mean: float, low: float, high: float, truncate: bool) -> DataFrame:
    cut = (lambda c: F.greatest(F.lit(0.0), c)) if truncate else (lambda c: c)
    return probed.select("item", cut(raw - F.lit(mean)).alias("est"), cut(raw - F.lit(high)).alias("lo"), (raw - F.lit(low)).alias("hi"))


def statistic_law(grid: CounterGrid, statistic) -> Law:
    return law(column_hist(grid, statistic))


def debiased_min(probed: DataFrame, errors: Law, r: int, level: float = 0.95, mode: str = "plugin", truncate: bool = True) -> DataFrame:
    """The minimum less its bias; the upper bound, the minimum itself, is never violated."""
    return _shifted(probed, t_min(F.col("v")), errors.order_mean(1, r, mode), 0.0, errors.quantile(beta_quantile(level, 1, r)), truncate)


def debiased_order(probed: DataFrame, errors: Law, i: int, r: int, level: float = 0.9, mode: str = "exact", truncate: bool = True) -> DataFrame:
    """The i-th smallest counter less its bias, with a two-sided interval; ranks are rounded outwards."""
    low, high = errors.quantile(beta_quantile((1 - level) / 2, i, r)), errors.quantile(beta_quantile((1 + level) / 2, i, r))
    return _shifted(probed, t_order(i)(F.col("v")), errors.order_mean(i, r, mode), low, high, truncate)


class OwnOut:
    """The law of the least of r errors when an item's own r counters are left out of the grid's law.

    The own counters part the law's atoms into r + 1 stretches; inside each, a constant number of them is left out. Prefix sums for each such number
    give every item's mean from its stretches' ends, so an item costs r look-ups and not a pass over the atoms.
    """

    def __init__(self, errors: Law, r: int):
        self.x, self.cum, self.r, self.left = errors.x, np.cumsum(errors.m), r, errors.n - r
        self.sums = np.empty((r + 1, len(self.x) + 1))
        for j in range(r + 1):
            self.sums[j] = np.append(0.0, np.cumsum(self.x * -np.diff(self.tail(np.append(0, self.cum), j), prepend=1.0)[1:]))

    def tail(self, cum: np.ndarray, out: np.ndarray | int) -> np.ndarray:
        """P(all of r draws lie beyond) where `out` own counters aren't."""
        return (1 - np.clip((cum - out) / self.left, 0, 1)) ** self.r

    def means(self, v: np.ndarray) -> np.ndarray:
        s = np.sort(v, axis=1)
        at = np.searchsorted(self.x, s)  # the atoms of own counters; equal ones meet in one
        n = len(self.x)
        before = np.append(0, self.cum)
        total = self.sums[0][at[:, 0]].copy()
        for j in range(1, self.r + 1):
            here = at[:, j - 1]
            onward = at[:, j] if j < self.r else np.full(len(s), n)
            first = here if j == 1 else np.where(here == at[:, j - 2], -1, here)
            out_before = np.sum(at < here[:, None], axis=1)  # own counters before this atom
            out_here = np.sum(at <= here[:, None], axis=1)
            atom = self.x[here] * (self.tail(before[here], out_before) - self.tail(before[here + 1], out_here))
            total += np.where(first >= 0, atom, 0.0)
            total += np.where(onward > here, self.sums[j][np.maximum(onward, here + 1)] - self.sums[j][here + 1], 0.0)
        return total

    def quantiles(self, v: np.ndarray, p: float) -> np.ndarray:
        """The ceil(p n)-th smallest of the n counters that are left."""
        at = np.searchsorted(self.x, np.sort(v, axis=1))
        rank = min(self.left, max(1, int(np.ceil(p * self.left - 1e-9))))
        spot = np.searchsorted(self.cum, np.full(len(v), rank))
        for _ in range(self.r):  # each own counter at or before the spot moves the rank on by one
            spot = np.searchsorted(self.cum, rank + (at <= spot[:, None]).sum(axis=1))
        return self.x[np.minimum(spot, len(self.x) - 1)]


def _own_out(probed: DataFrame, errors: Law, r: int, kernel, names: str) -> DataFrame:
    from .likelihood import by_item

    sent = probed.sparkSession.sparkContext.broadcast(OwnOut(errors, r))
    return by_item(probed, lambda v: kernel(sent.value, v), names)


def debiased_min_own_out(probed: DataFrame, errors: Law, r: int, truncate: bool = True) -> DataFrame:
    """The minimum less its exact mean under the error law without the item's own counters."""
    cut = (lambda e: np.maximum(0.0, e)) if truncate else (lambda e: e)
    return _own_out(probed, errors, r, lambda law_, v: [cut(v.min(axis=1) - law_.means(v))], "est")


def min_interval_own_out(probed: DataFrame, errors: Law, r: int, level: float = 0.95) -> DataFrame:
    """item, est, lo, hi: the one-sided interval of the minimum under the error law without the item's own counters."""
    p = beta_quantile(level, 1, r)
    return _own_out(probed, errors, r, lambda law_, v: [v.min(axis=1), np.maximum(0.0, v.min(axis=1) - law_.quantiles(v, p)), v.min(axis=1)], "est lo hi")


def markov_width(n_total: float, r: int, k: int, level: float) -> float:
    """Width below the minimum that Markov's inequality gives: the mean error times alpha to the -1/r."""
    return n_total * (1 - level) ** (-1 / r) / k


def markov_best(n_total: float, budget: int, level: float) -> tuple[float, float]:
    """(k, width): the width and depth that make Markov's interval shortest for `budget` cells."""
    k = budget / math.log(1 / (1 - level))
    return k, math.e * math.log(1 / (1 - level)) * n_total / budget


def markov_ci(probed: DataFrame, n_total: float, r: int, k: int, level: float) -> DataFrame:
    low = t_min(F.col("v"))
    return probed.select("item", low.alias("est"), F.greatest(F.lit(0.0), low - F.lit(markov_width(n_total, r, k, level))).alias("lo"), low.alias("hi"))


def top_heavy_width(n_rest: float, heavy: int, r: int, k: int, level: float) -> float:
    """Markov's width when the `heavy` largest items are set apart: P(error > t) <= (heavy / k + rest / (k t))^r."""
    room = (1 - level) ** (1 / r) - heavy / k
    return math.inf if room <= 0 else n_rest / (k * room)


def size_classic(eps: float, delta: float) -> tuple[int, int]:
    """Depth ceil(ln 1/delta), width ceil(e / eps)."""
    return math.ceil(math.log(1 / delta)), math.ceil(math.e / eps)


def nominal_coverage(errors: Law, level: float) -> float:
    """What the closed interval covers; discrete data may give more than the level."""
    low, high = errors.quantile((1 - level) / 2), errors.quantile((1 + level) / 2)
    return errors.cdf(high) - errors.cdf(low, left=True)


def as_error_bound(estimates: DataFrame) -> DataFrame:
    """Centre and half width of each interval: the error is above the half width with no more than the level's rest."""
    return estimates.select("item", ((F.col("lo") + F.col("hi")) / 2).alias("centre"), ((F.col("hi") - F.col("lo")) / 2).alias("delta"))


def narrowest(grid: CounterGrid, statistics: dict, level: float = 0.9) -> tuple[str, dict[str, float]]:
    """The statistic whose interval is narrowest on this grid, and all widths."""
    widths = {}
    for name, statistic in statistics.items():
        g = statistic_law(grid, statistic)
        widths[name] = g.quantile((1 + level) / 2) - g.quantile((1 - level) / 2)
    return min(widths, key=lambda n: (widths[n], n)), widths


def grid_law(grid: CounterGrid) -> Law:
    return law(error_hist(grid))
