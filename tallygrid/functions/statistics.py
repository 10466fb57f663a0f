"""Statistics of an item's own counters, and the laws of order statistics.

Each statistic moves with its counters: adding c to all of them adds c to it. They are expressions over an array column, so they stay inside generated
code, and none is cut off at zero.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def t_min(v: Column) -> Column:
    return F.array_min(v).cast("double")


def t_mean(v: Column) -> Column:
    return F.aggregate(v, F.lit(0).cast("double"), lambda a, x: a + x.cast("double")) / F.size(v)


def t_order(i: int):
    """The i-th smallest, from 1."""
    return lambda v: F.element_at(F.sort_array(v), i).cast("double")


def t_median(v: Column) -> Column:
    s, n = F.sort_array(v), F.size(v)
    low, high = F.floor((n + 1) / 2).cast("int"), F.floor(n / 2).cast("int") + 1
    return (F.element_at(s, low).cast("double") + F.element_at(s, high).cast("double")) / 2


def t_quantile(p: float):
    """The ceil(p r)-th smallest."""
    return lambda v: F.element_at(F.sort_array(v), F.greatest(F.lit(1), F.ceil(F.lit(p) * F.size(v))).cast("int")).cast("double")


def t_trimmed(low: int, high: int):
    """The mean without the `low` smallest and `high` largest."""
    return lambda v: t_mean(F.slice(F.sort_array(v), low + 1, F.size(v) - low - high))


def location(v: np.ndarray, loss: str = "huber", c: float = 1.345, rounds: int = 60) -> np.ndarray:
    """Minimiser of the sum of losses over each row: `l1`, `l2` or `huber` (with bend c times the spread around the median)."""
    middle = np.median(v, axis=1)
    if loss == "l1":
        return middle
    if loss == "l2":
        return v.mean(axis=1)
    bend = c * np.maximum(1e-9, 1.4826 * np.median(np.abs(v - middle[:, None]), axis=1))[:, None]
    at = middle.astype(np.float64)
    for _ in range(rounds):
        off = v - at[:, None]
        weight = np.minimum(1.0, bend / np.maximum(np.abs(off), 1e-300))
        at = (weight * v).sum(axis=1) / weight.sum(axis=1)
    return at


def order_statistic_cdf(p: float, i: int, r: int) -> float:
    """P(the i-th smallest of r uniforms <= p): at least i of r below p."""
    return math.fsum(math.comb(r, j) * p**j * (1 - p) ** (r - j) for j in range(i, r + 1))


def beta_quantile(level: float, i: int, r: int) -> float:
    """Quantile of the i-th smallest of r uniforms; closed for i = 1, else by bisection on the binomial tail."""
    if i == 1:
        return 1 - (1 - level) ** (1 / r)
    low, high = 0.0, 1.0
    for _ in range(80):
        middle = (low + high) / 2
        low, high = (middle, high) if order_statistic_cdf(middle, i, r) < level else (low, middle)
    return (low + high) / 2
