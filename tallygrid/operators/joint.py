"""Joint estimates of many items: least squares, bound propagation, and likelihood with a density fitted along the way."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.density import LogSpline, fit_logconcave
from ..functions.hashing import GridSpec, cell
from ..sources.shared import keep
from .errors import error_hist, law
from .grid import CounterGrid, cells_of, incidence
from .likelihood import by_item

#: Items and cells that may be solved together on the driver; beyond, `joint_mle_cluster` is the way.
MOST_ITEMS, MOST_CELLS = 100_000, 20_000_000


def system(items: DataFrame, grid: CounterGrid) -> tuple[list, np.ndarray, np.ndarray]:
    """(items, cells, values): each item's row of r cell numbers, and all counters, on the driver; the set's size is checked."""
    spec = grid.spec
    if spec.cells > MOST_CELLS:
        raise ValueError("too many cells for a joint solution on the driver")
    rows = incidence(items, spec).groupBy("item").agg(F.sort_array(F.collect_list(F.struct("rep", "idx"))).alias("x")).limit(MOST_ITEMS + 1).collect()
    if len(rows) > MOST_ITEMS:
        raise ValueError("too many items for a joint solution on the driver")
    rows.sort(key=lambda r: r["item"])
    cells = np.asarray([[c["rep"] * spec.k + c["idx"] for c in r["x"]] for r in rows], dtype=np.int64).reshape(-1, spec.r)
    values = np.zeros(spec.cells)
    found = grid.df.select("rep", "idx", "v").toArrow()
    values[found.column("rep").to_numpy() * spec.k + found.column("idx").to_numpy()] = found.column("v").to_numpy()
    return [r["item"] for r in rows], cells, values


def least_squares(cells: np.ndarray, values: np.ndarray, intercept: bool = False, rounds: int = 500, tol: float = 1e-18) -> np.ndarray:
    """Counts that minimise the squared residuals over all cells, by conjugate gradients on the sparse system."""
    n, r = cells.shape
    shift = values.mean() if intercept else 0.0
    times = lambda x: np.bincount(cells.ravel(), weights=np.repeat(x, r), minlength=len(values))
    back = lambda y: y[cells].sum(axis=1)
    x = np.zeros(n)
    residual = back(values - shift)
    direction, size = residual.copy(), residual @ residual
    first = size
    for _ in range(rounds):
        if size <= tol * max(1.0, first):
            break
        ahead = back(times(direction))
        part = size / (direction @ ahead)
        x, residual = x + part * direction, residual - part * ahead
        new = residual @ residual
        direction, size = residual + new / size * direction, new
    return x


def least_squares_blocks(counts: DataFrame, spec: GridSpec, load: float = 0.5) -> DataFrame:
    """(item, est) by least squares when all items are known: items are dealt by hash to blocks of about load x k, each with a grid of its own that a task solves.

    A block's r x k cells outnumber its items by far, so counts are determined whatever the number of items, and no machine holds more than a block.
    """
    blocks = -(-counts.count() // max(1, int(load * spec.k)))
    dealt = counts.select("item", "c", F.pmod(F.xxhash64(F.lit(spec.seed), "item"), F.lit(max(1, blocks))).alias("block"))
    own = dealt.select("block", "item", *[cell(F.col("item"), a, spec).alias(f"i{a}") for a in range(spec.r)])
    grids = dealt.select("block", F.explode(cells_of(F.col("item"), spec)).alias("x"), "c").groupBy("block", "x.rep", "x.idx").agg(F.sum("c").alias("v"))

    def solve(items: pa.Table, grid: pa.Table) -> pa.Table:
        cells = np.stack([items.column(f"i{a}").to_numpy() + a * spec.k for a in range(spec.r)], axis=1)
        values = np.zeros(spec.cells)
        values[grid.column("rep").to_numpy() * spec.k + grid.column("idx").to_numpy()] = grid.column("v").to_numpy()
        return pa.table({"item": items.column("item"), "est": least_squares(cells, values, tol=1e-26)})

    kind = dict(counts.dtypes)["item"]
    return own.groupBy("block").cogroup(grids.groupBy("block")).applyInArrow(solve, f"item {kind}, est double")


def joint_mle(cells: np.ndarray, values: np.ndarray, start: np.ndarray, trim: float = 0.01, rounds: int = 20, tol: float = 1e-3, update: bool = True, spline: LogSpline | None = None, scope: str = "all") -> tuple[np.ndarray, int]:
    """(counts, rounds): density of the residuals and counts in turn.

    A round fits the density to all residual cells, then moves every count part of the way to its best value given the others, within 0 and what its cells leave.
    `scope`: the objective and the density see `all` cells, or the items' `own` cells alone.
    Items that share cells may overshoot together: a move that lowers the likelihood of the density in use is halved until it doesn't. With a density that is fitted anew the
    likelihoods of different rounds are each those of their own fit; the counts with the best of them are returned.
    """
    theta = start.astype(np.float64).copy()
    n, r = cells.shape
    best, best_value = theta.copy(), -np.inf
    seen = np.unique(cells) if scope == "own" else slice(None)
    left = lambda t: values - np.bincount(cells.ravel(), weights=np.repeat(t, r), minlength=len(values))
    told = lambda res: float(np.maximum(spline(np.maximum(0, res[seen])), -1e6).sum() - 1e3 * np.maximum(0, -res[seen]).sum() / max(1.0, values.max()))
    done = 0
    for done in range(1, rounds + 1):
        residual = left(theta)
        if spline is None or update:
            x, m = np.unique(np.maximum(0, residual[seen]), return_counts=True)
            spline = fit_logconcave(x, m, trim).extended()
        value = told(residual)
        if value > best_value:
            best, best_value = theta.copy(), value
        open_cells = residual[cells] + theta[:, None]
        move = 0.5 * (np.clip(_steps(open_cells, spline), 0, np.maximum(0, open_cells.min(axis=1))) - theta)
        for _ in range(8):
            if told(left(theta + move)) >= value:
                break
            move = move / 2
        theta = theta + move
        if np.abs(move).max(initial=0.0) < tol:
            break
    return (theta if told(left(theta)) >= best_value else best), done


def constrained(cells: np.ndarray, values: np.ndarray, start: np.ndarray, loss: str = "l2", spline: LogSpline | None = None, rounds: int = 400) -> np.ndarray:
    """Counts of at least 0, whose sums stay within every own cell, that minimise a loss of the own cells' residuals: `l2`, `l1`, or `likelihood` (less
    the log density `spline` of each).

    Projected subgradient steps that shrink; after each, cells that are overdrawn scale their items down, so what is returned meets every constraint. The best counts seen are kept.
    """
    seen, own = np.unique(cells, return_inverse=True)
    own, v, r = own.reshape(cells.shape), values[seen], cells.shape[1]
    sums = lambda t: np.bincount(own.ravel(), weights=np.repeat(t, r), minlength=len(seen))

    def within(t: np.ndarray) -> np.ndarray:
        t = np.maximum(0.0, t)
        share = np.minimum(1.0, v / np.maximum(sums(t), 1e-300))
        return t * np.minimum(1.0, share[own].min(axis=1))

    if loss == "likelihood":
        at = np.append(spline.t, spline.t[-1] + 1.0)
        slopes = np.diff(spline(at)) / np.diff(at)
        cost = lambda res: -float(spline(np.maximum(0, res)).sum())
        slope = lambda res: -slopes[np.clip(np.searchsorted(spline.t, res, side="right") - 1, 0, len(slopes) - 1)]
    else:
        cost = (lambda res: float(np.abs(res).sum())) if loss == "l1" else (lambda res: float(res @ res))
        slope = np.sign if loss == "l1" else (lambda res: 2 * res)
    theta = within(start.astype(np.float64))
    best, least = theta, cost(v - sums(theta))
    reach = max(1e-9, float(np.abs(v).max()) / 4)
    for k in range(rounds):
        push = slope(v - sums(theta))[own].sum(axis=1)  # what the cost falls by for each unit of a count
        size = float(np.abs(push).max())
        if size == 0:
            break
        theta = within(theta + reach / (1 + k / 8) / size * push)
        now = cost(v - sums(theta))
        if now < least:
            best, least = theta, now
    return best


def joint_mle_cluster(items: DataFrame, grid: CounterGrid, rounds: int = 8, trim: float = 0.01, spline: LogSpline | None = None) -> DataFrame:
    """(item, est): the joint likelihood estimate with items and cells on the cluster, for sets that the driver can't hold.

    A round is two shuffles: counts are added up by cell and taken off the grid, and every item's cells come together for its step. Only the histogram of residuals
    reaches the driver, for the density. Each round is written to the shared folder. With `spline`, the density is given and stays.
    """
    spec = grid.spec
    inc = keep(incidence(items.select("item").distinct(), spec))
    first = law(error_hist(grid))
    low = inc.join(grid.df, ["rep", "idx"], "left").groupBy("item").agg(F.min(F.coalesce("v", F.lit(0))).alias("low"))
    theta = keep(low.select("item", F.greatest(F.lit(0.0), F.col("low") - F.lit(first.order_mean(1, spec.r))).alias("est")))
    known = spline
    for _ in range(rounds):
        used = inc.join(theta, "item").groupBy("rep", "idx").agg(F.sum("est").alias("used"))
        rest = grid.df.join(used, ["rep", "idx"], "left").select("rep", "idx", (F.col("v") - F.coalesce("used", F.lit(0.0))).alias("rest"))
        if known is None:
            told = rest.select(F.greatest(F.lit(0.0), F.round("rest", 3)).alias("v")).groupBy("v").agg(F.count("*").alias("m"))
            empty = rest.agg((F.lit(spec.cells) - F.count("*")).alias("m")).select(F.lit(0.0).alias("v"), "m")
            f = law(told.unionByName(empty).groupBy("v").agg(F.sum("m").alias("m")).where("m > 0"))
            spline = fit_logconcave(f.x, f.m, trim).extended()
        shape = spline
        own = inc.join(rest, ["rep", "idx"], "left").join(theta, "item").groupBy("item", "est").agg(F.collect_list(F.coalesce("rest", F.lit(0.0)) + F.col("est")).alias("v"))
        step = by_item(own, lambda v, shape=shape: [np.clip(_steps(v, shape), 0, np.maximum(0, v.min(axis=1)))], "goal")
        theta = keep(own.select("item", "est").join(step, "item").select("item", (0.5 * (F.col("est") + F.col("goal"))).alias("est")))
    return theta


def _steps(v: np.ndarray, spline: LogSpline) -> np.ndarray:
    from ..functions.density import mle

    return mle(v, spline)


def propagate_bounds(universe: DataFrame, grid: CounterGrid, rounds: int = 3) -> DataFrame:
    """(item, lo, up) when all items are known: upper bounds from the others' lower bounds and back, cell by cell.

    A round is two groupings: sums by cell, then the least or largest room by item. Bounds only tighten.
    """
    inc = incidence(universe, grid.spec).join(grid.df, ["rep", "idx"], "left").fillna(0, ["v"])
    bounds = universe.select("item", F.lit(0).cast("long").alias("lo")).join(inc.groupBy("item").agg(F.min("v").alias("up")), "item")
    for _ in range(rounds):
        bounds = _tighten(_tighten(bounds, inc, "up", "lo", F.min, F.least), inc, "lo", "up", F.max, F.greatest)
    return bounds


def _tighten(bounds: DataFrame, inc: DataFrame, side: str, other: str, gather, choose) -> DataFrame:
    placed = inc.join(bounds.select("item", other), "item")
    sums = placed.groupBy("rep", "idx").agg(F.sum(other).alias("s"))
    room = placed.join(sums, ["rep", "idx"]).withColumn("room", F.col("v") - (F.col("s") - F.col(other)))
    found = room.groupBy("item").agg(gather("room").alias("room"))
    return bounds.join(found, "item").withColumn(side, choose(F.col(side), F.col("room"))).drop("room")
