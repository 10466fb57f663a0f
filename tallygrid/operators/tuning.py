"""Depth and width from one 1 x B grid: convolution powers give the error law of every split of the same budget."""

from __future__ import annotations

import numpy as np

from ..functions.density import conv_power, convolved
from ..functions.statistics import beta_quantile
from .errors import Law

#: Depths in common use, to compare with the best.
DEPTH_PRESETS = (4, 10, 20, 30)
#: Steps of a mass function that `split_widths` works on; longer ones are counted in wider steps.
MOST_STEPS = 1 << 22


def mass(errors: Law, length: int | None = None) -> np.ndarray:
    """Mass function on 0, 1, ... of integer counters; what lies at or beyond `length` is left out, so the sum may be under 1."""
    length = length or int(errors.x.max()) + 1
    out = np.zeros(length)
    inside = errors.x < length
    out[errors.x[inside].astype(int)] = errors.m[inside] / errors.n
    return out


def depth_widths(base: np.ndarray, depths: list[int], levels: list[float]) -> list[tuple[int, float, float]]:
    """(depth, level, width): the one-sided interval's width of the minimum for each depth, at depth times the load of the 1 x B grid.

    inf where the law that `base` covers doesn't reach the quantile.
    """
    rows, f, at = [], base.copy(), 1
    for depth in sorted(depths):
        f = conv_power(base, depth) if depth > at + 1 or depth == 1 else convolved(f, base)[: len(base)] if depth == at + 1 else f
        at = depth
        cum = np.cumsum(f)
        for level in levels:
            spot = int(np.searchsorted(cum, beta_quantile(level, 1, depth) - 1e-12))
            rows.append((depth, level, float(spot) if spot < len(cum) else float("inf")))
    return rows


def reach(errors: Law, power: int, p: float) -> int:
    """A value that the p-quantile of the sum of `power` independent draws doesn't exceed: with probability p at least, no draw is above its share's quantile."""
    return power * int(np.ceil(errors.quantile(min(1.0, 1 - (1 - p) / power + 1e-9))))


def split_widths(errors: Law, depths: list[int], levels: list[float], power: int = 1, most: int = MOST_STEPS) -> dict[tuple[int, float], float]:
    """{(depth, level): width} as `depth_widths` gives them, at `power` times the load, on arrays as long as the quantiles reach, whatever the largest counter.

    What lies beyond a quantile has no part in it, so nothing is lost. A law that reaches further than `most` values is counted in steps of u of them, all rounded down,
    which takes less than depth x power x u off a width.
    """
    found = {}
    for depth in depths:
        quantiles = {level: beta_quantile(level, 1, depth) for level in levels}
        last = max(reach(errors, depth * power, p) for p in quantiles.values())
        unit = -(-(last + 1) // most)
        at = np.floor(errors.x / unit).astype(np.int64)
        inside = at <= last // unit
        cum = np.cumsum(conv_power(np.bincount(at[inside], weights=errors.m[inside] / errors.n, minlength=last // unit + 1), depth * power))
        found |= {(depth, level): float(unit * min(int(np.searchsorted(cum, p - 1e-12)), last // unit)) for level, p in quantiles.items()}
    return found


def best_depth(base: np.ndarray, most: int, level: float) -> tuple[int, float]:
    """(depth, width): the split of the budget with the narrowest interval; the width of the grid is the budget over the depth."""
    rows = depth_widths(base, list(range(1, most + 1)), [level])
    depth, _, width = min(rows, key=lambda r: (r[2], r[0]))
    return depth, width


def budget_for(base: np.ndarray, base_load: float, items: int, depth: int, level: float, target: float) -> int:
    """Smallest number of cells whose interval at this depth is within `target`, by halving the load of `base` in steps of whole powers."""
    for power in range(64, 0, -1):
        width = depth_widths(conv_power(base, power), [1], [1 - (1 - beta_quantile(level, 1, depth))])[0][2]
        if width <= target:
            return int(np.ceil(items * depth / (base_load * power)))
    return int(np.ceil(items * depth / base_load))


def compound_is_logconcave(g: np.ndarray, load: float) -> bool:
    """Is the compound Poisson law of counts g (from 1) at this load log-concave? It is if x g(x) is log-concave and load >= 2 g(2) / g(1)^2."""
    biased = g * np.arange(1, len(g) + 1)
    ok = bool((biased[1:-1] ** 2 >= biased[:-2] * biased[2:] * (1 - 1e-12)).all())
    return ok and bool(load >= 2 * g[1] / g[0] ** 2)
