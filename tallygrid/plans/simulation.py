"""Experiments on arrays: many salts of one grid, over counts that one task holds."""

from __future__ import annotations

import numpy as np

from ..functions.density import fit_logconcave, mle
from ..functions.statistics import beta_quantile
from ..operators import joint
from ..operators.errors import Law


def sketch(counts: np.ndarray, r: int, k: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """(cells, values): own cell numbers of each item, and all counters, by fully random hashes."""
    cells = rng.integers(0, k, (len(counts), r)) + np.arange(r) * k
    return cells, np.bincount(cells.ravel(), weights=np.repeat(counts, r), minlength=r * k)


def law_of(values: np.ndarray) -> Law:
    x, m = np.unique(values, return_counts=True)
    return Law(x.astype(np.float64), m.astype(np.int64))


def zipf(items: int, alpha: float, offset: float = 0.0, most: int = 1_000_000, seed: int = 0) -> np.ndarray:
    """Counts x with P(x) in proportion to (offset + x)^-alpha, largest first."""
    law = np.cumsum((offset + np.arange(1, most + 1)) ** -alpha)
    return np.sort(np.searchsorted(law / law[-1], np.random.default_rng(seed).random(items)) + 1)[::-1].astype(np.float64)


def coverage_of_salt(counts: np.ndarray, top: np.ndarray, r: int, k: int, levels: list[float], seed: int) -> list[tuple]:
    """(method, level, covered, shrunk, width): shares of the items `top` whose interval holds the count, as it is and half a count less at each end, and the mean width."""
    cells, values = sketch(counts, r, k, np.random.default_rng(seed))
    v, truth, errors = values[cells[top]], counts[top], law_of(values)
    spline = fit_logconcave(errors.x, errors.m).extended()
    columns = values.reshape(r, k).T
    plain = {"mean": lambda x: x.mean(axis=1), "median": lambda x: np.median(x, axis=1), "mle": lambda x: mle(x, spline)}
    laws = {n: (f(v), law_of(f(columns))) for n, f in plain.items()}
    low, rows = v.min(axis=1), []
    for level in levels:
        ends = {"min_onesided": (low - errors.quantile(beta_quantile(level, 1, r)), low)}
        ends["min_twosided"] = tuple(low - errors.quantile(beta_quantile(p, 1, r)) for p in ((1 + level) / 2, (1 - level) / 2))
        for name, (raw, own) in laws.items():
            ends[name] = (raw - own.quantile((1 + level) / 2), raw - own.quantile((1 - level) / 2))
        for name, (a, b) in ends.items():
            inside = lambda less, a=a, b=b: float(((a + less <= truth) & (truth <= b - less)).mean())
            rows.append((name, level, inside(0.0), inside(0.5), float((b - np.maximum(0, a)).mean())))
    return rows


def regression_of_salt(counts: np.ndarray, sizes: list[int], r: int, k: int, seed: int) -> list[tuple]:
    """(items, mass_share, method, squared error): joint estimates of the largest items against single ones, on one grid."""
    cells, values = sketch(counts, r, k, np.random.default_rng(seed))
    errors = law_of(values)
    spline = fit_logconcave(errors.x, errors.m).extended()
    bias = law_of(mle(values.reshape(r, k).T, spline)).mean()
    rows = []
    for n in sizes:
        own, truth = cells[:n], counts[:n]
        start = np.maximum(0, values[own].min(axis=1) - errors.order_mean(1, r))
        found = {
            "least_squares": joint.least_squares(own, values), "constrained_l1": joint.constrained(own, values, start, "l1"), "joint_mle": joint.joint_mle(own, values, start)[0],
            "debiased_min": start, "debiased_mle": np.maximum(0, mle(values[own], spline) - bias),
        }
        rows += [(n, float(truth.sum() / counts.sum()), name, float(((e - truth) ** 2).mean())) for name, e in found.items()]
    return rows


def conservative_min(counts: np.ndarray, r: int, k: int, rng: np.random.Generator, parts: int = 4) -> np.ndarray:
    """The error of the minimum under conservative updates, the items' counts coming in `parts` rounds of random order."""
    cells = rng.integers(0, k, (len(counts), r)) + np.arange(r) * k
    grid = np.zeros(r * k)
    shares = np.stack([np.floor(counts * (p + 1) / parts) - np.floor(counts * p / parts) for p in range(parts)])
    for part in shares:
        for i in rng.permutation(len(counts)):
            if part[i]:
                own = cells[i]
                grid[own] = np.maximum(grid[own], grid[own].min() + part[i])
    return grid[cells].min(axis=1) - counts


def growth_of_block(counts: np.ndarray, load: int, r: int, seed: int) -> tuple[float, float, float]:
    """Summed squared errors of the minimum, the minimum under conservative updates, and the debiased likelihood estimate, on one grid at about `load`."""
    rng, k = np.random.default_rng(seed), max(1, round(len(counts) / load))
    cells, values = sketch(counts, r, k, rng)
    errors = law_of(values)
    spline = fit_logconcave(errors.x, errors.m).extended()
    bias = mle(values.reshape(r, k).T, spline).mean()
    off = (values[cells].min(axis=1) - counts, conservative_min(counts, r, k, rng), mle(values[cells], spline) - bias - counts)
    return tuple(float((e**2).sum()) for e in off)


def depth_widths(counts: np.ndarray, budget: int, depths: list[int], level: float, seed: int = 0) -> list[tuple[int, float]]:
    """(depth, width) of the one-sided interval on grids rebuilt at each depth of one budget."""
    out = []
    for r in depths:
        _, values = sketch(counts, r, budget // r, np.random.default_rng(seed + r))
        out.append((r, law_of(values).quantile(beta_quantile(level, 1, r))))
    return out
