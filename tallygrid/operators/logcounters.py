"""Grids whose cells hold small levels that stand for (b^level - 1) / (b - 1), raised at random so that they are right on average."""

from __future__ import annotations

from functools import cache
from math import erfc, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import GridSpec
from .grid import CounterGrid, cells_of


def level_value(level: np.ndarray, base: float) -> np.ndarray:
    return (base**level - 1) / (base - 1)


def raised(count: int, base: float, draw: np.random.Generator) -> int:
    """The level after `count` random increments: the waiting time at level j is geometric with chance b^-j."""
    level, left = 0, count
    while left > 0:
        left -= int(draw.geometric(base**-level))
        level += left >= 0
    return level


def build_logcounters(df: DataFrame, spec: GridSpec, base: float = 1.1, seed: int = 9) -> CounterGrid:
    """v is the level of each cell's total. Draws depend on seed and cell alone, so reruns agree."""
    spread = df.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), "c").groupBy("x.rep", "x.idx").agg(F.sum("c").alias("c"))

    def levels(batches):
        for b in batches:
            rep, idx, c = (b.column(n).to_numpy() for n in ("rep", "idx", "c"))
            v = [raised(int(n), base, np.random.default_rng([seed, int(a), int(i)])) for a, i, n in zip(rep, idx, c, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("rep"), b.column("idx"), pa.array(v, pa.int64())], names=["rep", "idx", "v"])

    return CounterGrid(spread.mapInArrow(levels, "rep int, idx long, v long"), spec)


def values(grid: CounterGrid, base: float) -> CounterGrid:
    """The grid of the counts that levels stand for, rounded."""
    return CounterGrid(grid.df.withColumn("v", F.round((F.pow(F.lit(base), F.col("v")) - 1) / (base - 1)).cast("long")), grid.spec)


def level_table(counts: np.ndarray, levels: int, base: float) -> np.ndarray:
    """P(level | count), counts by levels 0 to `levels`, from the waiting times' means and variances."""
    from math import erf

    j = np.arange(levels + 2, dtype=np.float64)
    mean, var = (base**j - 1) / (base - 1), (base ** (2 * j) - 1) / (base**2 - 1) - (base**j - 1) / (base - 1)
    z = (counts[:, None] + 0.5 - mean) / np.sqrt(np.maximum(var, 1e-9))
    reached = 0.5 * (1 + np.vectorize(erf)(np.clip(z, -40, 40) / np.sqrt(2)))
    reached[:, 0] = 1.0
    reached = np.minimum.accumulate(reached, axis=1)
    return np.maximum(reached[:, :-1] - reached[:, 1:], 1e-300)


DENSE, PER_E = 1024, 256


@cache
def _normal() -> tuple[np.ndarray, np.ndarray]:
    """Points and the normal distribution function there; between them it is taken as linear."""
    z = np.linspace(-40, 40, 160_001)
    return z, np.asarray([0.5 * erfc(-x / sqrt(2)) for x in z])


def chance_of(level: np.ndarray, counts: np.ndarray, base: float) -> np.ndarray:
    """P(level | count), arrays that broadcast: the entries of `level_table` without the rest of its rows."""

    def reached(j):
        mean, var = (base**j - 1) / (base - 1), (base ** (2 * j) - 1) / (base**2 - 1) - (base**j - 1) / (base - 1)
        return np.where(j == 0, 1.0, np.interp((counts + 0.5 - mean) / np.sqrt(np.maximum(var, 1e-9)), *_normal()))

    return np.maximum(reached(level) - reached(level + 1), 1e-300)


def _lattice(top: float) -> np.ndarray:
    """All whole numbers to DENSE, then steps of one in PER_E, up to `top`: points that don't depend on which items are together."""
    steps = int(np.ceil(np.log(max(top, DENSE) / DENSE) / np.log1p(1 / PER_E))) + 1
    return np.unique(np.concatenate([np.arange(DENSE), np.rint(DENSE * (1 + 1 / PER_E) ** np.arange(steps + 1))]))


def level_mle(v: np.ndarray, law, base: float, rows: int = 256) -> np.ndarray:
    """Whole counts that maximise the likelihood of own levels v: each cell's chance sums over the errors that may lie beside the count.

    `law`: errors in counts, all of its values used. Each item is searched up to the count that its own largest level can stand for, and the best point of a lattice
    finer than the spread of a level is refined between its neighbours to whole numbers. Items in one matrix have no part in one another's answers; they are worked off `rows` at a time.
    """
    own, back = np.unique(v.astype(np.int64), axis=0, return_inverse=True)
    weight, errors = law.m / law.n, np.asarray(law.x, dtype=np.float64)
    bound = np.ceil(level_value(own.max(axis=1) + 2.0, base) - min(0.0, errors[0]))
    tried = _lattice(bound.max())
    log = {}
    for level in np.unique(own):
        total = np.zeros(len(tried))
        for e, w in zip(errors, weight, strict=True):
            total += w * chance_of(np.float64(level), tried + e, base)
        log[level] = np.log(np.maximum(total, 1e-300))
    est = np.empty(len(own))
    for a in range(0, len(own), rows):
        part, top = own[a : a + rows], bound[a : a + rows]
        told = sum(np.stack([log[x] for x in column]) for column in part.T)
        best = np.argmax(np.where(tried <= top[:, None], told, -np.inf), axis=1)
        low, high = tried[np.maximum(best - 1, 0)], tried[np.minimum(best + 1, len(tried) - 1)]
        at = tried[best]
        while (open_ := np.flatnonzero(high - low > 2)).size:
            points = np.rint(low[open_, None] + (high - low)[open_, None] * np.arange(9) / 8)
            score = np.zeros(points.shape)
            for column in part[open_].T:
                total = np.zeros(points.shape)
                for e, w in zip(errors, weight, strict=True):
                    total += w * chance_of(column[:, None].astype(np.float64), points + e, base)
                score += np.log(np.maximum(total, 1e-300))
            k, row = np.argmax(score, axis=1), np.arange(len(open_))
            at[open_] = points[row, k]
            low[open_], high[open_] = points[row, np.maximum(k - 1, 0)], points[row, np.minimum(k + 1, 8)]
        est[a : a + rows] = at
    return est[back.reshape(-1)]
